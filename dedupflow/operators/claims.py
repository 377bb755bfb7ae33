"""Claiming: of all requests for a free tag exactly one wins.

The winner is the minimum of a total order over the requests. A minimum is associative, commutative and idempotent, so
partial aggregation, retries and speculative tasks cannot make a second winner: it is what any serial run of
compare-and-swap attempts in that order would leave.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import arrival_ms, order_key, wide_order_key
from .index import FREE, HELD


def requests_of(edges: DataFrame, sent: Column | None = None, narrow: bool = False) -> DataFrame:
    """(sid, tag, item_id, claim_key): edges with the order of their requests.

    ``narrow`` packs the order into 63 bits where item and client numbers are bounded (see ``order_key``).
    """
    pack = order_key if narrow else wide_order_key
    sent = arrival_ms(F.col("sid")) if sent is None else sent
    return edges.select("sid", "tag", "item_id", pack(sent, F.col("item_id"), F.col("sid")).alias("claim_key"))


def winners(requests: DataFrame) -> DataFrame:
    """(tag, holder, item_id): first request of each tag; a hash aggregate with map-side combine, safe on hot tags."""
    first = requests.groupBy("tag").agg(F.min_by("sid", "claim_key").alias("holder"), F.min_by("item_id", "claim_key").alias("item_id"))
    return first.select("tag", "holder", "item_id")


def claim(state: DataFrame, requests: DataFrame) -> DataFrame:
    """The next state: free tags that are asked for become held by their first request. Held and done tags refuse early, before the aggregate."""
    free = state.where(F.col("state") == FREE).select("tag")
    won = winners(requests.join(free, "tag", "left_semi")).select("tag", F.col("holder").alias("won"))
    return state.join(won, "tag", "left").select("tag", F.when(F.col("won").isNotNull(), HELD).otherwise(F.col("state")).alias("state"), F.coalesce("won", "holder").alias("holder"), "last_holder", "epoch", "n_owners")


def claim_serialized(requests: DataFrame) -> DataFrame:
    """Baseline: one lock serialises all claims. Same winners as ``winners``, one task, no parallelism."""
    line = requests.repartition(1).withColumn("turn", F.row_number().over(Window.orderBy("claim_key")))
    first = line.groupBy("tag").agg(F.min("turn").alias("turn"))
    return line.join(first, ["tag", "turn"]).select("tag", F.col("sid").alias("holder"), "item_id")


def claim_windowed(requests: DataFrame) -> DataFrame:
    """The same by ranking, as an audit of the order: sorts every tag's requests."""
    ranked = requests.withColumn("r", F.row_number().over(Window.partitionBy("tag").orderBy("claim_key")))
    return ranked.where("r = 1").select("tag", F.col("sid").alias("holder"), "item_id")
