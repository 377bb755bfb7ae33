"""Replies to clients and their local lanes: what a client won is active, what another trains stays parked as a spare."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

RUN, PARK, LOCAL = "RUN", "PARK", "LOCAL_COPY"
ACTIVE, STANDBY = "active", "standby"


def reply(edges: DataFrame, state: DataFrame) -> DataFrame:
    """(sid, tag, item_id, op): RUN to the holder (again if it asks again), PARK to every other owner."""
    held = state.select("tag", "holder")
    return edges.join(held, "tag").select("sid", "tag", "item_id", F.when(F.col("holder") == F.col("sid"), RUN).otherwise(PARK).alias("op"))


def reply_items(items: DataFrame, replies: DataFrame) -> DataFrame:
    """(sid, item_id, op) of every record: further copies inside one client are LOCAL_COPY and never trained."""
    own = replies.select("sid", "tag", F.col("item_id").alias("first_item"), "op")
    return items.join(own, ["sid", "tag"]).select("sid", "item_id", F.when(F.col("item_id") == F.col("first_item"), F.col("op")).otherwise(LOCAL).alias("op"))


def message(replies: DataFrame) -> DataFrame:
    """One map of tag (hex) to operation per client: a view of the reply as it travels."""
    return replies.groupBy("sid").agg(F.map_from_entries(F.collect_list(F.struct(F.hex("tag"), "op"))).alias("ops"))


def route(replies: DataFrame) -> DataFrame:
    """(sid, item_id, tag, lane): refused copies are kept in standby; nothing is deleted."""
    return replies.select("sid", "item_id", "tag", F.when(F.col("op") == RUN, ACTIVE).otherwise(STANDBY).alias("lane"))


def _moved(queue: DataFrame, moves: DataFrame, lane: str) -> DataFrame:
    marked = moves.select("sid", "tag").distinct().withColumn("moved", F.lit(True))
    return queue.join(marked, ["sid", "tag"], "left").withColumn("lane", F.when(F.col("moved"), lane).otherwise(F.col("lane"))).drop("moved").select("sid", "item_id", "tag", "lane")


def promote(queue: DataFrame, moves: DataFrame) -> DataFrame:
    """Takeover: the named (sid, tag) records become active."""
    return _moved(queue, moves, ACTIVE)


def demote(queue: DataFrame, moves: DataFrame) -> DataFrame:
    """Rejoin or reassignment: the named (sid, tag) records go back to standby."""
    return _moved(queue, moves, STANDBY)


def save(queue: DataFrame, path: str) -> None:
    """Writes lanes as partitions, so a client reads only the one it trains from."""
    queue.write.mode("overwrite").partitionBy("lane").parquet(path)
