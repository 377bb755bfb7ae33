"""The coordinator's two-way index: a state per tag, and owner edges laid out by tag and by client.

Tables are immutable; a change is a new version. States: 0 free, 1 held, 2 done.
"""

from __future__ import annotations

import json
import math
import os

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import fnv1a64, tag_key

FREE, HELD, DONE = 0, 1, 2
STATE = "tag binary, state int, holder long, last_holder long, epoch int, n_owners long"
EDGE = "sid long, tag binary, item_id long"


def append_edges(edges: DataFrame | None, requests: DataFrame) -> DataFrame:
    """Edges with the requests' unseen (tag, sid) pairs added; a repeated request changes nothing."""
    new = requests.groupBy("sid", "tag").agg(F.min("item_id").alias("item_id"))
    if edges is None:
        return new
    return edges.select("sid", "tag", "item_id").unionByName(new.join(edges.select("sid", "tag"), ["sid", "tag"], "left_anti"))


def append_state(state: DataFrame | None, requests: DataFrame) -> DataFrame:
    """States with a free entry for every unseen tag. Creation never sets a holder, and one tag gets one entry however many clients bring it."""
    new = requests.groupBy("tag").agg(F.count_distinct("sid").alias("n_owners"))
    fresh = new if state is None else new.join(state.select("tag"), "tag", "left_anti")
    fresh = fresh.select("tag", F.lit(FREE).alias("state"), F.lit(None).cast("long").alias("holder"), F.lit(None).cast("long").alias("last_holder"), F.lit(0).alias("epoch"), "n_owners")
    return fresh if state is None else state.select(*fresh.columns).unionByName(fresh)


def add_owners(state: DataFrame, edges: DataFrame, requests: DataFrame) -> DataFrame:
    """States whose ``n_owners`` count the requests' owners that ``edges`` do not have yet; only what is new is counted."""
    new = requests.select("sid", "tag").distinct().join(edges.select("sid", "tag"), ["sid", "tag"], "left_anti").groupBy("tag").agg(F.count(F.lit(1)).alias("more"))
    return state.join(new, "tag", "left").withColumn("n_owners", F.col("n_owners") + F.coalesce("more", F.lit(0))).drop("more")


def recount_owners(state: DataFrame, edges: DataFrame) -> DataFrame:
    """States with the owners counted anew from the edges."""
    n = edges.groupBy("tag").agg(F.count(F.lit(1)).alias("n"))
    return state.join(n, "tag", "left").withColumn("n_owners", F.coalesce("n", F.lit(0)).cast("long")).drop("n")


def locate(keys: DataFrame, state: DataFrame) -> DataFrame:
    """Entries of the tags asked for: the 64-bit key leads to the partition, equality of the whole tag decides."""
    return keys.select("tag").distinct().withColumn("tag_key", tag_key(F.col("tag"))).join(state.withColumn("tag_key", tag_key(F.col("tag"))), ["tag_key", "tag"]).drop("tag_key")


def slots(tags: DataFrame, buckets: int) -> DataFrame:
    """(tag, slot): first slot of each tag by FNV-1a in a table of ``buckets`` slots."""
    return tags.select("tag", F.pmod(fnv1a64("tag"), F.lit(buckets)).alias("slot"))


def owners_view(edges: DataFrame) -> DataFrame:
    """Owner arrays per tag, for display; operators work on edges, whose size per row is fixed."""
    return edges.groupBy("tag").agg(F.array_sort(F.collect_set("sid")).alias("owners"))


def capacity(total_input: int, slots_per_record: float = 1.0) -> int:
    """Slots to reserve for a total input: the next power of two, so it depends on nothing but that total."""
    return 1 << max(0, math.ceil(math.log2(max(1, total_input * slots_per_record))))


def _saved(rows: DataFrame, database: str, name: str, layout: str, buckets: int, mode: str, folder: str | None) -> None:
    key = {"by_tag": "tag_key", "by_sid": "sid"}[layout]
    writer = rows.write.mode(mode).bucketBy(buckets, key).sortBy(key)
    writer = writer.option("path", f"{folder}/{name}_{layout}") if folder else writer
    writer.saveAsTable(f"{database}.{name}_{layout}")


def create(spark: SparkSession, database: str, name: str, expected: int, rows_per_bucket: int = 2_000_000, least: int = 1, folder: str | None = None) -> int:
    """Empty bucketed tables of both directions, sized before anything is inserted; returns the number of buckets.

    They lie in ``folder`` if it is given, else in the warehouse.
    """
    buckets = max(least, capacity(expected) // rows_per_bucket)
    spark.sql(f"CREATE DATABASE IF NOT EXISTS {database}")
    empty = spark.createDataFrame([], EDGE).withColumn("tag_key", tag_key(F.col("tag")))
    for layout in ("by_tag", "by_sid"):
        _saved(empty, database, name, layout, buckets, "overwrite", folder)
    return buckets


def store(edges: DataFrame, database: str, name: str, buckets: int, mode: str = "append", folder: str | None = None) -> None:
    """Appends edges (tags in binary) to both layouts, so joins by tag and reads by client need no shuffle of the stored side."""
    rows = edges.select("sid", "tag", "item_id", tag_key(F.col("tag")).alias("tag_key"))
    for layout in ("by_tag", "by_sid"):
        _saved(rows, database, name, layout, buckets, mode, folder)


class Versions:
    """Versioned snapshots under a path: a version is there once its manifest is, which is written last."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")

    def _fs(self):
        p = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
        return p.getFileSystem(self.spark._jsc.hadoopConfiguration()), self.spark._jvm.org.apache.hadoop.fs.Path

    def latest(self) -> int | None:
        fs, jpath = self._fs()
        folder = jpath(f"{self.path}/manifest")
        found = [int(s.getPath().getName()[1:]) for s in fs.listStatus(folder)] if fs.exists(folder) else []
        return max(found, default=None)

    def commit(self, df: DataFrame, base: int | None) -> int:
        """Writes ``df`` as the version after ``base``; fails if another writer has published that version meanwhile."""
        if self.latest() != base:
            raise RuntimeError(f"version {base} is no longer the latest")
        version = 0 if base is None else base + 1
        df.write.mode("overwrite").parquet(f"{self.path}/data/v{version}")
        fs, jpath = self._fs()
        made = fs.create(jpath(f"{self.path}/manifest/v{version}"), False)  # fails if it exists
        made.write(bytearray(json.dumps({"version": version, "columns": df.columns}), "utf-8"))
        made.close()
        return version

    def read(self, version: int | None = None) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/data/v{self.latest() if version is None else version}")

    def changes(self, older: int, newer: int, key: str) -> DataFrame:
        """Rows whose values differ between two versions, by full outer join on ``key``."""
        a, b = self.read(older), self.read(newer)
        cols = [c for c in b.columns if c != key]
        pack = lambda df, n: df.select(F.col(key), F.struct(*cols).alias(n))
        return pack(a, "was").join(pack(b, "now"), key, "full_outer").where(~F.col("was").eqNullSafe(F.col("now")))

    def compact(self, files: int) -> int:
        """Rewrites the latest version into fewer files, as a new version."""
        base = self.latest()
        return self.commit(self.read(base).coalesce(files), base)


def inspect_store(spark: SparkSession, checkpoint: str, **options) -> DataFrame:
    """State of a streaming query's stateful operator, read from its checkpoint."""
    return spark.read.format("statestore").options(**options).load(os.fspath(checkpoint))
