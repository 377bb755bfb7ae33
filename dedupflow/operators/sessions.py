"""Sessions: unique client numbers, heartbeats, and who is lost when."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def admit(known: DataFrame | None, names: DataFrame) -> DataFrame:
    """(name, sid): known clients keep their number, new names get the next ones in alphabetical order. N is the number of clients."""
    if known is None:
        return names.select("name").distinct().select("name", (F.row_number().over(Window.orderBy("name")) - 1).cast("long").alias("sid"))
    new = names.select("name").distinct().join(known, "name", "left_anti")
    top = known.agg(F.coalesce(F.max("sid"), F.lit(-1)).alias("top"))
    numbered = new.select("name", F.row_number().over(Window.orderBy("name")).alias("n")).crossJoin(F.broadcast(top))  # one row
    return known.select("name", "sid").unionByName(numbered.select("name", (F.col("top") + F.col("n")).cast("long").alias("sid")))


def check_beat_plan(beat_every: float = 1.0, timeout: float = 3.0) -> None:
    """A client that beats in time must not be taken for lost."""
    if not timeout > beat_every > 0:
        raise ValueError("timeout must be longer than beat_every")


def sessions(beats: DataFrame, timeout: str) -> DataFrame:
    """(sid, session, start, last_beat, n): runs of beats with no gap longer than ``timeout``; a gap of exactly that is none."""
    w = Window.partitionBy("sid").orderBy("ts", "beat_id")
    gap = F.col("ts") > F.lag("ts").over(w) + F.expr(f"INTERVAL {timeout}")
    marked = beats.withColumn("new", F.coalesce(gap.cast("int"), F.lit(0)))
    numbered = marked.withColumn("session", F.sum("new").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return numbered.groupBy("sid", "session").agg(F.min("ts").alias("start"), F.max("ts").alias("last_beat"), F.count(F.lit(1)).alias("n"))


def losses(beats: DataFrame, timeout: str, asof: Column) -> DataFrame:
    """(sid, last_beat, lost_at): every silence longer than ``timeout`` up to ``asof``; lost a microsecond after it has passed."""
    w = Window.partitionBy("sid").orderBy("ts", "beat_id")
    seen = beats.where(F.col("ts") <= asof).withColumn("next", F.coalesce(F.lead("ts").over(w), asof))
    limit = F.col("ts") + F.expr(f"INTERVAL {timeout}")
    return seen.where(F.col("next") > limit).select("sid", F.col("ts").alias("last_beat"), (limit + F.expr("INTERVAL 1 MICROSECOND")).alias("lost_at"))


def online(beats: DataFrame, timeout: str, at: Column) -> DataFrame:
    """(sid, last_beat, online) of all clients that have beaten by ``at``."""
    last = beats.where(F.col("ts") <= at).groupBy("sid").agg(F.max("ts").alias("last_beat"))
    return last.withColumn("online", ~(F.col("last_beat") + F.expr(f"INTERVAL {timeout}") < at))


def recent_beats(beats: DataFrame, seconds: int) -> DataFrame:
    """Every beat with the number of its client's beats in the ``seconds`` before and at it."""
    w = Window.partitionBy("sid").orderBy(F.col("ts").cast("timestamp").cast("long")).rangeBetween(-seconds, 0)
    return beats.withColumn("recent", F.count(F.lit(1)).over(w))


def last_beat_before(requests: DataFrame, beats: DataFrame) -> DataFrame:
    """As-of join: each request (sid, at, rid) with its client's last beat at or before it, by one pass over the union."""
    rows = requests.select("sid", F.col("at").alias("ts"), "rid", F.lit(None).cast("timestamp").alias("beat")).unionByName(beats.select("sid", "ts", F.lit(None).cast("long").alias("rid"), F.col("ts").alias("beat")))
    w = Window.partitionBy("sid").orderBy("ts", F.col("rid").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0)
    return rows.withColumn("last_beat", F.last("beat", ignorenulls=True).over(w)).where("rid IS NOT NULL").select("sid", "rid", F.col("ts").alias("at"), "last_beat")


def session_of(requests: DataFrame, spans: DataFrame) -> DataFrame:
    """Range join: each request with the session that it falls into, if any."""
    return requests.alias("r").join(spans.alias("s"), (F.col("r.sid") == F.col("s.sid")) & F.col("r.at").between(F.col("s.start"), F.col("s.last_beat")), "left").select("r.sid", "r.rid", "r.at", "s.session")
