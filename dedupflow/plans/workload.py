"""Experiment workloads: corpus split, duplicate allocation over clients, plans of arrival, failure and joining."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import arrival_ms
from .. import sources

PAIRINGS = ("matched", "round_robin", "random")


def split(df: DataFrame, id_col: str, held_out: float = 0.05, seed: int = 17) -> DataFrame:
    """``df`` with ``held_out``: decided by a hash of the stable id alone, so any order or partitioning gives the same split."""
    digest = F.sha2(F.concat(F.lit(f"{seed}:"), F.col(id_col).cast("string")), 256)
    return df.withColumn("held_out", F.conv(F.substring(digest, 1, 15), 16, 10).cast("long") % 10000 < int(held_out * 10000))


def pool(spark: SparkSession, sf_dir: str, unit: str = "line") -> DataFrame:
    """(tag) of distinct records: documents or their non-blank lines."""
    return sources.documents(spark, sf_dir, unit).select(F.sha2("content", 256).alias("tag")).distinct()


def records_per_client(distinct: int) -> int:
    """The published 1,024 records per client where ten such clients without duplicates can be filled, else a quarter or a sixteenth."""
    return 1024 if distinct >= 10240 else 256 if distinct >= 2560 else 64


def shared_slots(n_clients: int, n: int, d: float) -> tuple[int, list[int]]:
    """(shared records, duplicates per client) of matched pairs: client of a slot = slot mod N; an odd total loses one slot."""
    shared = n_clients * round(n * d) // 2
    own = [0] * n_clients
    for client in range(n_clients):
        own[client] = len(range(client, 2 * shared, n_clients))
    return shared, own


def pairwise(records: DataFrame, n_clients: int, n: int, d: float, seed: int = 17, pairing: str = "matched") -> DataFrame:
    """(sid, item_id, tag): n records per client, a share d of them on exactly two clients and the others on one.

    Records are taken in order of their tags; item_id is the record's place in that order times 64 plus the client, so
    the two copies of a record are two items. The number taken is the workload's size (at most N * n).
    """
    if pairing not in PAIRINGS:
        raise ValueError(f"pairing {pairing} is none of {PAIRINGS}")
    spark = records.sparkSession
    m = round(n * d)
    shared, own = shared_slots(n_clients, n, d)
    pairs = [(a, b) for a in range(n_clients) for b in range(a + 1, n_clients)]
    slots = spark.range(shared)
    if pairing == "matched":
        two = F.array(F.pmod(F.col("id") * 2, F.lit(n_clients)), F.pmod(F.col("id") * 2 + 1, F.lit(n_clients)))
    else:
        which = F.pmod("id", F.lit(len(pairs))) if pairing == "round_robin" else F.pmod(F.xxhash64(F.lit(seed), "id"), F.lit(len(pairs)))
        table = F.array(*[F.array(F.lit(a).cast("long"), F.lit(b).cast("long")) for a, b in pairs])
        two = F.element_at(table, (which + 1).cast("int"))
    twice = slots.select(F.col("id").alias("place"), F.explode(two).alias("sid"))
    if pairing != "matched":
        found = {r.sid: r.n for r in twice.groupBy("sid").agg(F.count(F.lit(1)).alias("n")).collect()}  # N clients
        own = [found.get(c, 0) for c in range(n_clients)]
    offsets, at = [], shared
    for c in range(n_clients):
        offsets.append(at)
        at += max(0, n - own[c])
    singles = None
    if at > shared:
        clients = spark.createDataFrame([(c, offsets[c], max(0, n - own[c])) for c in range(n_clients)], "sid long, first long, n long").where("n > 0")
        singles = clients.select("sid", F.explode(F.sequence(F.col("first"), F.col("first") + F.col("n") - 1)).alias("place"))
    placed = twice.select("sid", "place") if singles is None else twice.select("sid", "place").unionByName(singles.select("sid", "place"))
    taken = records.orderBy("tag").limit(at).withColumn("place", (F.row_number().over(Window.orderBy("tag")) - 1).cast("long"))  # at most N * n rows
    return placed.join(F.broadcast(taken), "place").select("sid", (F.col("place") * 64 + F.col("sid")).alias("item_id"), "tag")


def natural(spark: SparkSession, sf_dir: str, table: str = "documents") -> DataFrame:
    """Records with the copies that the tables hold anyway: documents, lines, parts by supplier, conversations."""
    if table in ("documents", "lines"):
        return sources.documents(spark, sf_dir, "doc" if table == "documents" else "line")
    if table == "parts":
        return sources.parts_by_supplier(spark, sf_dir)
    return sources.conversations(spark, sf_dir)


def online_plan(spark: SparkSession, n_clients: int, low_s: int = 0, high_s: int = 20, seed: int | None = None) -> DataFrame:
    """(sid, online_ms): delays before clients come online; seeded uniform, or the fixed arrival rule without a seed."""
    base = spark.range(n_clients).select(F.col("id").alias("sid"))
    if seed is None:
        return base.select("sid", arrival_ms(F.col("sid")).alias("online_ms"))
    span = (high_s - low_s) * 1000
    return base.select("sid", (F.lit(low_s * 1000) + F.pmod(F.xxhash64(F.lit(seed), "sid"), F.lit(max(span, 1)))).alias("online_ms"))


def failure_order(sid):
    """Rank key by which clients fail: the first share of them in this order."""
    return F.sha2(F.concat(F.lit("fail:"), sid.cast("string")), 256)


def failure_plan(clients: DataFrame, rate: float) -> DataFrame:
    """(sid) of the clients that fail: a share ``rate`` of them, in an order that is fixed by hash, so higher rates only add clients."""
    n = clients.count()
    return clients.orderBy(failure_order(F.col("sid"))).limit(round(n * rate)).select("sid")


def join_plan(spark: SparkSession, first: int, joiners: int) -> DataFrame:
    """(sid, wait_ms): newcomers and their waits."""
    return spark.range(first, first + joiners).select(F.col("id").alias("sid"), arrival_ms(F.col("id")).alias("wait_ms"))
