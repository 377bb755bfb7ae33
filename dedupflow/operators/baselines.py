"""What the concurrent scheme is compared with."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import content_hash
from ..functions.storage import written
from .claims import claim_serialized  # noqa: F401  (the global lock)
from .recovery import release_scan  # noqa: F401  (release without the inverted layout)


def levels(n_clients: int) -> int:
    """Levels of a binary tree over the clients."""
    return math.ceil(math.log2(n_clients)) if n_clients > 1 else 0


def tree_dedup(edges: DataFrame, n_clients: int) -> tuple[DataFrame, DataFrame]:
    """(survivors, removed): groups of clients are paired up a binary tree; at each level the right group drops what the left one has.

    Every level needs all clients and ends in a barrier. ``removed`` (level, removed) counts what each level dropped.
    """
    now, counts = edges.select("sid", "tag", "item_id"), None
    for level in range(levels(n_clients)):
        side = F.shiftright("sid", level).bitwiseAND(F.lit(1))
        placed = now.withColumn("side", side).withColumn("pair", F.shiftright("sid", level + 1))
        left = placed.where("side = 0").select("pair", "tag").distinct()
        marked = placed.join(left.withColumn("common", F.lit(True)), ["pair", "tag"], "left")
        marked = written(marked.withColumn("drop", F.coalesce("common", F.lit(False)) & (F.col("side") == 1)).select("sid", "tag", "item_id", "drop"), "tree")
        gone = marked.agg(F.lit(level).alias("level"), F.count(F.when(F.col("drop"), 1)).alias("removed"))
        counts = gone if counts is None else counts.unionAll(gone)
        now = marked.where("NOT drop").select("sid", "tag", "item_id")
    if counts is None:
        counts = edges.agg(F.lit(0).alias("level"), F.lit(0).cast("long").alias("removed")).limit(0)
    return now, counts


def tag_for(items: DataFrame, psi: str, authority=None) -> DataFrame:
    """Edges for group intersections: ``symmetric`` compares keyed hashes, ``oprf`` the oblivious tags."""
    from . import tags

    if psi not in ("symmetric", "oprf"):
        raise ValueError("psi is symmetric or oprf")
    authority = authority or tags.Authority.create("keyed" if psi == "symmetric" else "modp2048", seed=11)
    return tags.protect(items, authority).drop("copies")


def pair_overlaps(edges: DataFrame) -> DataFrame:
    """(a, b, common): records that every two clients share; one intersection per pair of clients."""
    a, b = edges.select(F.col("sid").alias("a"), "tag"), edges.select(F.col("sid").alias("b"), "tag")
    return a.join(b, "tag").where("a < b").groupBy("a", "b").agg(F.count(F.lit(1)).alias("common"))


def pairwise_weighted(edges: DataFrame) -> DataFrame:
    """(sid, tag, freq, w): every copy trained with the inverse of how many clients have it.

    As in the compared scheme a client learns that number from its intersections with every other one, a pair of
    clients at a time: one for itself and one for each intersection that holds the record.
    """
    a, b = edges.select("sid", "tag"), edges.select(F.col("sid").alias("other"), "tag")
    met = a.join(b, "tag").where("sid <> other").groupBy("sid", "tag").agg(F.count(F.lit(1)).alias("met"))
    freq = F.lit(1) + F.coalesce("met", F.lit(0))
    return edges.select("sid", "tag").join(met, ["sid", "tag"], "left").select("sid", "tag", freq.alias("freq"), (1 / freq).alias("w"))


def group_intersections(edges: DataFrame, n_clients: int, record_bytes: int = 32) -> DataFrame:
    """(level, pairs, common, sent_bytes): the tree's group intersections, with what both groups of every pair send each other.

    The edges' tags come from ``tag_for`` with either cipher; ``record_bytes`` is what a record of it takes on the wire.
    They are written first, or every level would run the cipher again.
    """
    edges, out = written(edges.select("sid", "tag"), "edges"), None
    for level in range(levels(n_clients)):
        groups = edges.select("tag", F.shiftright("sid", level).alias("g")).distinct().withColumn("pair", F.shiftright("g", 1))
        met = groups.groupBy("pair", "tag").agg(F.count(F.lit(1)).alias("n"))
        row = met.agg(F.lit(level).alias("level"), F.count_distinct("pair").alias("pairs"), F.count(F.when(F.col("n") == 2, 1)).alias("common"), (F.sum("n") * record_bytes).alias("sent_bytes"))
        out = row if out is None else out.unionAll(row)
    return out


def rerun_after_loss(edges: DataFrame, lost: DataFrame, n_clients: int) -> tuple[DataFrame, DataFrame]:
    """Serial recovery: the whole tree again, on the survivors."""
    return tree_dedup(edges.join(F.broadcast(lost.select("sid")), "sid", "left_anti"), n_clients)


def join_pairwise(edges: DataFrame, new_edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(kept, checks): each newcomer is checked against every present client; kept are records no present client has."""
    present, news = edges.select("sid").distinct(), new_edges.select(F.col("sid").alias("new")).distinct()
    grid = news.crossJoin(F.broadcast(present))  # clients, not records
    common = new_edges.select(F.col("sid").alias("new"), "tag").join(edges.select("sid", "tag"), "tag").groupBy("new", "sid").agg(F.count(F.lit(1)).alias("common"))
    checks = grid.join(common, ["new", "sid"], "left").select("new", F.col("sid").alias("present"), F.coalesce("common", F.lit(0)).alias("common"))
    return new_edges.join(edges.select("tag").distinct(), "tag", "left_anti"), checks


def no_dedup(items: DataFrame) -> DataFrame:
    """(sid, trained): plain federated training uses every record."""
    return items.where("content IS NOT NULL").groupBy("sid").agg(F.count(F.lit(1)).alias("trained"))


def local_only(items: DataFrame) -> DataFrame:
    """(sid, trained): each client drops its own copies and sees no others."""
    return items.where("content IS NOT NULL").groupBy("sid").agg(F.count_distinct(content_hash(F.col("content"))).alias("trained"))


def exact_distinct(items: DataFrame) -> DataFrame:
    """(tag, sid): smallest client of each content over all."""
    return items.where("content IS NOT NULL").groupBy(content_hash(F.col("content")).alias("tag")).agg(F.min("sid").alias("sid"))
