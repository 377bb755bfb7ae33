"""Cost and accuracy measures over states, ledgers and timelines."""

from __future__ import annotations

import json
import time

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.index import HELD, capacity

#: Parameters of the ledger, in bytes. A tag and an element of the 2048-bit group are 512 hexadecimal characters. Slot, edge
#: and map entries hold a tag each and what goes with it; the answer to a beat carries the rights still to be delivered and is
#: fitted, like the payload that a client keeps, to the published totals at 2 and 10 clients.
TAG_BYTES, OP_BYTES, REQUEST_BYTES, BEAT_BYTES, BEAT_REPLY_BYTES, GROUP_BYTES = 512, 1, 16, 24, 40_000, 512
SLOT_BYTES, EDGE_BYTES, MAP_BYTES = TAG_BYTES + 93, TAG_BYTES + 64, TAG_BYTES + 64
MODEL_BYTES, KEPT_MODEL_BYTES = 35_800_000, 56_287_800
#: Every client beats once a second from when it is there until this many seconds after the last has come.
BEATS_AFTER = 16


def reduction(ours: Column, base: Column) -> Column:
    """Share that ours saves of the base."""
    return 1 - ours / base


def reductions(times: DataFrame, keys: list[str], pairs: dict[str, tuple[str, str]]) -> DataFrame:
    """``keys`` and per name the share that the first column of its pair saves of the second, in percent."""
    return times.select(*keys, *[F.round(reduction(F.col(ours), F.col(base)) * 100, 2).alias(name) for name, (ours, base) in pairs.items()])


def volume(items: DataFrame) -> DataFrame:
    """(total, distinct_records): input records and globally different ones."""
    return items.agg(F.count(F.lit(1)).alias("total"), F.count_distinct("tag").alias("distinct_records"))


def comm_bytes(edges: DataFrame, beats: int) -> DataFrame:
    """(requests, replies, masked, beats, total): metadata that travels, per kind."""
    n = edges.agg(F.count(F.lit(1)).alias("n"))
    parts = n.select((F.col("n") * (TAG_BYTES + REQUEST_BYTES)).alias("requests"), (F.col("n") * (TAG_BYTES + OP_BYTES)).alias("replies"), (F.col("n") * 2 * GROUP_BYTES).alias("masked"), F.lit(beats * (BEAT_BYTES + BEAT_REPLY_BYTES)).cast("long").alias("beats"))
    return parts.withColumn("total", F.col("requests") + F.col("replies") + F.col("masked") + F.col("beats"))


def storage_bytes(edges: DataFrame, total_input: int) -> DataFrame:
    """(index_bytes, edge_bytes, map_bytes, total): reserved slots by input size, edges by client, clients' own maps."""
    parts = edges.agg(F.count(F.lit(1)).alias("n")).select(F.lit(capacity(total_input) * SLOT_BYTES).cast("long").alias("index_bytes"), (F.col("n") * EDGE_BYTES).alias("edge_bytes"), (F.col("n") * MAP_BYTES).alias("map_bytes"))
    return parts.withColumn("total", F.col("index_bytes") + F.col("edge_bytes") + F.col("map_bytes"))


def model_bytes(n_clients: int, size: int = MODEL_BYTES) -> int:
    """Model traffic of a round: down to and up from every client."""
    return 2 * n_clients * size


def ratio(metadata: Column, model: Column) -> Column:
    return metadata / model


def recoverable(released: DataFrame, edges: DataFrame, online: DataFrame) -> DataFrame:
    """(released, recoverable): released tags, and those with an online owner."""
    reach = edges.join(F.broadcast(online.select("sid")), "sid", "left_semi").select("tag").distinct().withColumn("r", F.lit(1))
    return released.join(reach, "tag", "left").agg(F.count(F.lit(1)).alias("released"), F.count("r").alias("recoverable"))


def saved(edges: DataFrame, state: DataFrame) -> DataFrame:
    """(sid, owned, trained, saved): trainings that each client is spared."""
    owned = edges.groupBy("sid").agg(F.count(F.lit(1)).alias("owned"))
    mine = state.where("holder IS NOT NULL").groupBy(F.col("holder").alias("sid")).agg(F.count(F.lit(1)).alias("trained"))
    j = owned.join(mine, "sid", "left").na.fill(0, ["trained"])
    return j.withColumn("saved", F.col("owned") - F.col("trained"))


def reassigned(assignment: DataFrame, state: DataFrame, risk: DataFrame) -> DataFrame:
    """(reassigned, at_risky): tags with another trainer than before, and tags at clients with a recent loss."""
    j = assignment.join(state.select("tag", "last_holder"), "tag").join(F.broadcast(risk.select("sid", F.lit(True).alias("risky")).distinct()), "sid", "left")
    return j.agg(F.count(F.when(F.col("sid") != F.col("last_holder"), 1)).alias("reassigned"), F.count(F.when(F.col("risky"), 1)).alias("at_risky"))


def recovery_ms(taken: DataFrame, lost_at: int, promote_us: int) -> DataFrame:
    """(recovery_ms): from the loss until the last takeover and the promotion of what was taken; 0 without any."""
    n = taken.agg(F.max("taken_at").alias("last"), F.count(F.lit(1)).alias("n"))
    return n.select(F.coalesce(F.col("last") - lost_at + F.floor(F.col("n") * promote_us / 1000), F.lit(0)).cast("long").alias("recovery_ms"))


def held_now(state: DataFrame) -> DataFrame:
    return state.where(F.col("state") == HELD).groupBy("holder").agg(F.count(F.lit(1)).alias("held"))


def wall(df: DataFrame) -> float:
    """Seconds to compute all rows of a frame and keep none."""
    start = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - start


def claim_throughput(fn, requests: DataFrame, attempts: int, runs: int = 3) -> dict:
    """Mean seconds of a claim pass and millions of attempts per second."""
    times = [wall(fn(requests)) for _ in range(runs)]
    mean = sum(times) / len(times)
    return {"seconds": mean, "mops": attempts / mean / 1e6}


def plan_work(df: DataFrame) -> dict:
    """What a plan is made of: exchanges, sorts, joins, Python nodes, rows of its scans; from the physical plan."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    count = lambda *names: sum(plan.count(n) for n in names)
    return {"exchanges": count("Exchange "), "sorts": count("Sort ["), "joins": count("Join "), "python": count("Python", "Pandas", "Arrow"), "cartesian": count("CartesianProduct", "BroadcastNestedLoopJoin"), "pushed": count("PushedFilters: [Is", "PushedFilters: [E", "PushedFilters: [G", "PushedFilters: [L"), "hash_aggregates": count("HashAggregate")}


def observed(df: DataFrame, name: str, **aggregates: Column):
    """``df`` with counters that are filled while it is written, without a job of their own; read ``.get`` after the action."""
    from pyspark.sql import Observation

    o = Observation(name)
    return df.observe(o, *[a.alias(n) for n, a in aggregates.items()]), o


def as_json(measures: dict) -> str:
    return json.dumps(measures, sort_keys=True)
