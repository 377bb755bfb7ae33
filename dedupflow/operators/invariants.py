"""Checks that hold in every state; each gives the number of violations."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .index import DONE, FREE, HELD

#: Columns that frames of the coordinator must not have.
PRIVATE = frozenset({"content", "text", "hash", "mask", "blinded", "secret", "key"})


def uniqueness(state: DataFrame) -> DataFrame:
    """Tags with several entries, and entries held or done without a holder or free with one."""
    many = state.groupBy("tag").agg(F.count(F.lit(1)).alias("n")).agg(F.count(F.when(F.col("n") > 1, 1)).alias("double_entries"))
    odd = state.agg(F.count(F.when(F.col("state").isin(HELD, DONE) == F.col("holder").isNull(), 1)).alias("bad_holders"))
    return many.crossJoin(F.broadcast(odd))  # one row each


def holders_own(state: DataFrame, edges: DataFrame) -> DataFrame:
    """(foreign): holders that do not own their tag."""
    held = state.where("holder IS NOT NULL").select("tag", F.col("holder").alias("sid"))
    return held.join(edges, ["tag", "sid"], "left_anti").agg(F.count(F.lit(1)).alias("foreign"))


def coverage(state: DataFrame, edges: DataFrame, online: DataFrame) -> DataFrame:
    """(reachable, done): tags with an online owner, and how many of them are done."""
    reach = edges.join(F.broadcast(online.select("sid")), "sid", "left_semi").select("tag").distinct()
    s = state.join(reach, "tag", "left_semi")
    return s.agg(F.count(F.lit(1)).alias("reachable"), F.count(F.when(F.col("state") == DONE, 1)).alias("done"))


def lanes(queue: DataFrame, edges: DataFrame) -> DataFrame:
    """(missing, twice): owned records in no lane, and records in two."""
    per = queue.groupBy("sid", "tag").agg(F.count(F.lit(1)).alias("n"))
    j = edges.join(per, ["sid", "tag"], "left")
    return j.agg(F.count(F.when(F.col("n").isNull(), 1)).alias("missing"), F.count(F.when(F.col("n") > 1, 1)).alias("twice"))


def layouts_agree(by_tag: DataFrame, by_sid: DataFrame) -> DataFrame:
    """(different): edges in one layout only."""
    a, b = by_tag.select("sid", "tag"), by_sid.select("sid", "tag")
    return a.exceptAll(b).unionAll(b.exceptAll(a)).agg(F.count(F.lit(1)).alias("different"))


def visibility(*frames: DataFrame) -> list[str]:
    """Private columns that frames of the coordinator would show; empty if there are none."""
    return sorted({c for f in frames for c in f.columns if c in PRIVATE})


def private_columns(*frames: DataFrame) -> DataFrame:
    """(private_columns): how many columns the frames of the coordinator show by a private name, or with the content that a row's tag stands for.

    The second is decided on the rows, for plain tags: a text or binary whose hash is the tag of its row.
    """
    found = None
    for f in frames:
        wide = [c.name for c in f.schema if c.dataType.simpleString() in ("string", "binary")]
        shows = lambda c: F.coalesce(F.max(F.unhex(F.sha2(F.col(c).cast("binary"), 256)) == F.col("tag")), F.lit(False))
        names = [F.when(F.lit(c in PRIVATE) | (shows(c) if c in wide and "tag" in f.columns else F.lit(False)), F.lit(c)) for c in f.columns]
        row = f.agg(F.array_compact(F.array(*names)).alias("names"))
        found = row if found is None else found.unionAll(row)
    return found.select(F.explode("names").alias("name")).agg(F.count_distinct("name").alias("private_columns"))


def legal_moves(before: DataFrame, after: DataFrame) -> DataFrame:
    """(illegal): changes of state other than free to held, held to done, and held to free with a new epoch."""
    a = before.select("tag", F.col("state").alias("s0"), F.col("epoch").alias("e0"))
    b = after.select("tag", F.col("state").alias("s1"), F.col("epoch").alias("e1"))
    ok = (F.col("s0") == F.col("s1")) | ((F.col("s0") == FREE) & (F.col("s1") == HELD)) | ((F.col("s0") == HELD) & (F.col("s1") == DONE)) | ((F.col("s0") == HELD) & (F.col("s1") == FREE) & (F.col("e1") > F.col("e0")))
    return a.join(b, "tag").agg(F.count(F.when(~ok, 1)).alias("illegal"))
