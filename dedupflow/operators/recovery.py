"""Loss of clients: release what they hold, hand it to other owners, take them back."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import contact_ms, wide_order_key
from .claims import claim, requests_of
from .index import FREE, HELD

COLUMNS = ("tag", "state", "holder", "last_holder", "epoch", "n_owners")


#: Lost clients named as literals, which prune a layout by client; more than these are joined.
MOST_LITERALS = 1000


def owned_by(edges_by_sid: DataFrame, lost: DataFrame) -> DataFrame:
    """(tag, sid) that the lost own. Their numbers are literals in the filter, so a stored layout opens their buckets only."""
    sids = [r.sid for r in lost.select("sid").where("sid IS NOT NULL").distinct().limit(MOST_LITERALS + 1).collect()]
    if len(sids) > MOST_LITERALS:
        return edges_by_sid.join(lost.select("sid").distinct(), "sid", "left_semi").select("tag", "sid")
    return edges_by_sid.where(F.col("sid").isin(sids)).select("tag", "sid")


def release(state: DataFrame, edges_by_sid: DataFrame, lost: DataFrame) -> DataFrame:
    """(tag, from_sid): tags that lost clients hold, found through the layout by client.

    Only what the lost own is read, and only entries held by them are released: done work stays, and in the dedup
    phase, when nobody holds anything, the result is empty.
    """
    owned = owned_by(edges_by_sid, lost)
    held = state.where(F.col("state") == HELD).select("tag", "holder")
    return held.join(owned, (held["tag"] == owned["tag"]) & (held["holder"] == owned["sid"])).select(held["tag"], F.col("sid").alias("from_sid"))


def release_scan(state: DataFrame, edges: DataFrame, lost: DataFrame) -> DataFrame:
    """Baseline without the inverted layout: all entries are read with their owner arrays."""
    owners = edges.groupBy("tag").agg(F.collect_set("sid").alias("owners"))
    gone = F.broadcast(lost.select(F.col("sid").alias("from_sid")))
    return state.join(owners, "tag").join(gone, F.array_contains("owners", F.col("from_sid")) & (F.col("holder") == F.col("from_sid"))).where(F.col("state") == HELD).select("tag", "from_sid")


def apply_release(state: DataFrame, released: DataFrame) -> DataFrame:
    """States with the released tags free and their epoch raised, which fences off late uploads."""
    mark = released.select("tag", F.lit(True).alias("freed")).distinct()
    out = state.join(mark, "tag", "left")
    freed = F.coalesce("freed", F.lit(False))
    return out.select("tag", F.when(freed, FREE).otherwise(F.col("state")).alias("state"), F.when(~freed, F.col("holder")).alias("holder"), "last_holder", (F.col("epoch") + freed.cast("int")).alias("epoch"), "n_owners")


def candidates(released: DataFrame, edges: DataFrame, online: DataFrame) -> DataFrame:
    """(tag, from_sid, sid): online owners of released tags; a tag whose only owner is away has none and waits."""
    owners = edges.join(F.broadcast(online.select("sid")), "sid", "left_semi").select("tag", "sid")
    return released.join(owners, "tag").where("sid <> from_sid")


def takeover(released: DataFrame, edges: DataFrame, contacts: DataFrame) -> DataFrame:
    """(tag, from_sid, to_sid, taken_at): each released tag goes to the owner in contact first, by beat or by request; ties to the smallest sid.

    ``contacts`` (sid, at) are the first contacts after the release, at most one row per client.
    """
    near = F.broadcast(contacts.groupBy("sid").agg(F.min("at").alias("at")))
    offers = released.join(edges.select("tag", "sid"), "tag").where("sid <> from_sid").join(near, "sid")
    key = wide_order_key(F.col("at"), F.lit(0), F.col("sid"))
    first = offers.withColumn("k", key).groupBy("tag").agg(F.min_by("from_sid", "k").alias("from_sid"), F.min_by("sid", "k").alias("to_sid"), F.min("at").alias("taken_at"))
    return first.select("tag", "from_sid", "to_sid", "taken_at")


def contacts_after(online: DataFrame, at: int) -> DataFrame:
    """First contacts of online clients in the second after ``at``."""
    return online.select("sid", contact_ms(F.col("sid"), at).alias("at"))


def apply_takeover(state: DataFrame, taken: DataFrame) -> DataFrame:
    """States with the taken tags held by their new holders."""
    out = state.join(taken.select("tag", "to_sid"), "tag", "left")
    got = F.col("to_sid").isNotNull() & (F.col("state") == FREE)
    return out.select("tag", F.when(got, HELD).otherwise(F.col("state")).alias("state"), F.when(got, F.col("to_sid")).otherwise(F.col("holder")).alias("holder"), "last_holder", "epoch", "n_owners")


def log(taken: DataFrame, released_at: Column, round_: int) -> DataFrame:
    """Rows of the takeover log."""
    return taken.select("tag", "from_sid", "to_sid", released_at.alias("released_at"), "taken_at", F.lit(round_).alias("round"))


def waiting(state: DataFrame, edges: DataFrame, online: DataFrame) -> DataFrame:
    """Free tags none of whose owners is online."""
    free = state.where(F.col("state") == FREE)
    reachable = edges.join(F.broadcast(online.select("sid")), "sid", "left_semi").select("tag").distinct()
    return free.join(reachable, "tag", "left_anti")


def rejoin_dedup(state: DataFrame, edges: DataFrame, sid: int) -> DataFrame:
    """Return after a loss in the dedup phase: an ordinary request for all own tags."""
    return claim(state, requests_of(edges.where(F.col("sid") == sid)))


def rejoin_training(state: DataFrame, edges: DataFrame, sid: int) -> tuple[DataFrame, DataFrame]:
    """(next state, replies) of a client lost in training: PARK for tags others hold or have done, ordinary claims on the free rest.

    Old progress is void; a regained tag is trained anew.
    """
    own = edges.where(F.col("sid") == sid)
    after = claim(state, requests_of(own))
    regained = after.where((F.col("holder") == sid) & (F.col("state") == HELD)).select("tag", F.lit("RUN").alias("op"))
    replies = own.join(regained, "tag", "left").select("sid", "tag", "item_id", F.coalesce("op", F.lit("PARK")).alias("op"))
    return after, replies
