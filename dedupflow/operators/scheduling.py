"""Allocation of a new round that avoids clients with a recent disconnection."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

KEPT, MOVED, NEW, NONE = "kept", "moved", "new", "unassigned"


def risky(risk_log: DataFrame, round_: int, risk_rounds: int = 1) -> DataFrame:
    """Clients lost in the last ``risk_rounds`` rounds before ``round_``."""
    return risk_log.where((F.col("round") < round_) & (F.col("round") >= round_ - risk_rounds)).select("sid").distinct()


def _preference(pick: str, load: DataFrame | None) -> Column:
    if pick == "rendezvous":  # spreads tags over owners without any shared state
        return F.sha2(F.concat_ws(":", F.lower(F.hex("tag")), F.col("sid")), 256)
    if pick == "lowest_sid":
        return F.lpad(F.col("sid").cast("string"), 20, "0")
    if pick == "least_loaded":
        return F.concat(F.lpad(F.coalesce(F.col("m"), F.lit(0)).cast("string"), 20, "0"), F.lpad(F.col("sid").cast("string"), 20, "0"))
    raise ValueError(f"no rule named {pick}")


def assign(state: DataFrame, edges: DataFrame, risk: DataFrame, online: DataFrame, pick: str = "rendezvous", use_history: bool = True, load: DataFrame | None = None) -> DataFrame:
    """(tag, sid, how): the trainer of every tag in the new round.

    A healthy online last trainer keeps the tag. Otherwise a safe online owner by ``pick``; without any, the last
    trainer if online though risky; else the smallest online owner; else nobody. With ``use_history`` off the
    record of losses is ignored, and only that: absent trainers are replaced and new tags assigned as well. Only tags
    without a healthy trainer meet the edges.
    """
    risk = risk if use_history else risk.limit(0)
    risk_ = F.broadcast(risk.select(F.col("sid").alias("last_holder"), F.lit(True).alias("risky")).distinct())
    alive = F.broadcast(online.select(F.col("sid").alias("last_holder"), F.lit(True).alias("alive")).distinct())
    marked = state.select("tag", "last_holder").join(risk_, "last_holder", "left").join(alive, "last_holder", "left")
    healthy = F.coalesce("alive", F.lit(False)) & ~F.coalesce("risky", F.lit(False))
    kept = marked.where(healthy).select("tag", F.col("last_holder").alias("sid"), F.lit(KEPT).alias("how"))
    rest = marked.where(~healthy).select("tag", "last_holder", F.coalesce("alive", F.lit(False)).alias("alive"))
    owners = rest.join(edges.select("tag", "sid"), "tag").join(F.broadcast(online.select("sid").distinct()), "sid", "left_semi")
    owners = owners.join(F.broadcast(risk.select("sid", F.lit(True).alias("risky")).distinct()), "sid", "left")
    if load is not None:
        owners = owners.join(F.broadcast(load.select("sid", "m")), "sid", "left")
    elif pick == "least_loaded":
        owners = owners.withColumn("m", F.lit(0))
    key = F.when(~F.coalesce("risky", F.lit(False)), F.concat(F.lit("0"), _preference(pick, load))).when(F.col("sid") == F.col("last_holder"), F.lit("1")).otherwise(F.concat(F.lit("2"), F.lpad(F.col("sid").cast("string"), 20, "0")))
    best = owners.groupBy("tag").agg(F.min_by("sid", key).alias("sid"))
    got = rest.join(best, "tag", "left")
    how = F.when(F.col("sid").isNull(), NONE).when(F.col("sid").eqNullSafe(F.col("last_holder")), KEPT).when(F.col("last_holder").isNull(), NEW).otherwise(MOVED)
    return kept.unionByName(got.select("tag", "sid", how.alias("how")))


def demotions(assignment: DataFrame, edges: DataFrame, risk: DataFrame) -> DataFrame:
    """(sid, tag): records that risky owners park because another client trains them."""
    return edges.join(F.broadcast(risk.select("sid").distinct()), "sid", "left_semi").select("sid", "tag").join(assignment.select("tag", F.col("sid").alias("trainer")), "tag").where("trainer IS NOT NULL AND trainer <> sid").select("sid", "tag")
