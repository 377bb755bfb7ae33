"""Virtual time: what phases take, in whole milliseconds from unit costs, so any engine gets the same numbers."""

from __future__ import annotations

from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..operators.baselines import levels


@dataclass(frozen=True)
class Costs:
    """Unit costs in microseconds per record unless said otherwise; parameters of the model, not measurements.

    Fitted once to published figures at 10 clients of 1,024 records: deduplication about 2.9 s, a round about 41 s that
    hardly moves with the share of duplicates and grows in proportion to the clients. So one device trains all clients
    in turn, and starting a client (loading and returning its model) outweighs its records. ``check`` is a newcomer's
    comparison with one present client, which the compared scheme makes with all of them one after the other.
    """

    tag: int = 2400
    index: int = 450
    pair: int = 20
    check: int = 1000
    train: int = 250
    start_ms: int = 3600
    aggregate_ms: int = 300
    broadcast_ms: int = 200
    promote: int = 50
    servers: int = 4


COSTS = Costs()


def dedup_ends(clients: DataFrame, costs: Costs = COSTS) -> DataFrame:
    """``clients`` (grid, sid, ready_ms, n, ...) with ``dedup_end``: tags at the client, then the index at the first of the coordinator's servers to be free.

    Clients queue in order of (ready + tag time, sid). A grid point has as many rows as clients.
    """

    def serve(pdf: pd.DataFrame) -> pd.DataFrame:
        asked = pdf["ready_ms"] + pdf["n"] * costs.tag // 1000
        pdf = pdf.assign(asked=asked).sort_values(["asked", "sid"])
        free, ends = [0] * costs.servers, []
        for at, n in zip(pdf["asked"], pdf["n"]):
            free.sort()
            free[0] = max(free[0], int(at)) + int(n) * costs.index // 1000
            ends.append(free[0])
        return pdf.assign(dedup_end=ends).drop(columns="asked")

    schema = ", ".join(f"{n} {t}" for n, t in clients.dtypes) + ", dedup_end long"
    return clients.groupBy("grid").applyInPandas(serve, schema)


def in_turn(rows: DataFrame, asked: Column, work: Column) -> DataFrame:
    """``rows`` (grid, sid, ...) with ``begin`` and ``end`` on one server that takes them in order of (asked, sid).

    A row ends at the latest of what any row before it, or it itself, asked at plus all the work from there on.
    """
    w = Window.partitionBy("grid").orderBy("asked_at", "sid")
    queue = rows.withColumn("asked_at", asked.cast("long")).withColumn("own_work", work.cast("long")).withColumn("upto", F.sum("own_work").over(w))
    queue = queue.withColumn("end", F.max(F.col("asked_at") - F.col("upto") + F.col("own_work")).over(w) + F.col("upto"))
    return queue.withColumn("begin", F.col("end") - F.col("own_work")).drop("asked_at", "own_work", "upto")


def training_ms(costs: Costs = COSTS) -> Column:
    """What the device takes for a client with ``n_run`` records."""
    return F.lit(costs.start_ms) + F.floor(F.col("n_run") * costs.train / 1000)


def concurrent(clients: DataFrame, costs: Costs = COSTS) -> DataFrame:
    """(grid, end_to_end_ms, dedup_ms) of the concurrent mode from (grid, sid, ready_ms, n, n_run): everyone trains as soon as it has its replies and the device is free."""
    done = in_turn(dedup_ends(clients, costs), F.col("dedup_end"), training_ms(costs))
    return done.groupBy("grid").agg(
        (F.max("end") + costs.aggregate_ms + costs.broadcast_ms - F.min("ready_ms")).alias("end_to_end_ms"),
        F.max(F.col("dedup_end") - F.col("ready_ms")).alias("dedup_ms"),
    )


def serial(clients: DataFrame, level_sizes: DataFrame, costs: Costs = COSTS) -> DataFrame:
    """(grid, end_to_end_ms, dedup_ms) of the serial mode: all wait for the last client, then tags, tree levels, training in turn.

    ``level_sizes`` (grid, level, size): records of the largest pair of groups at each level.
    """
    tree = level_sizes.groupBy("grid").agg(F.sum(F.floor(F.col("size") * costs.pair / 1000)).alias("tree_ms"))
    sums = clients.groupBy("grid").agg(F.max("ready_ms").alias("last"), F.min("ready_ms").alias("first"), F.max("n").alias("n"), F.sum(training_ms(costs)).alias("train_ms"))
    j = sums.join(tree, "grid", "left").withColumn("dedup_ms", F.floor(F.col("n") * costs.tag / 1000) + F.coalesce("tree_ms", F.lit(0)))
    return j.select("grid", (F.col("last") - F.col("first") + F.col("dedup_ms") + F.col("train_ms") + costs.aggregate_ms + costs.broadcast_ms).alias("end_to_end_ms"), "dedup_ms")


def joins(joiners: DataFrame, present: int = 10, costs: Costs = COSTS) -> DataFrame:
    """(grid, concurrent_dedup_ms, serial_dedup_ms, concurrent_train_ms, serial_train_ms) of newcomers (grid, sid, ready_ms, n, n_run).

    From the first newcomer until all have detected their duplicates, and until all have begun to train. In the serial
    scheme each newcomer is compared with every client present, earlier newcomers included, one comparison at a time.
    """
    ours = dedup_ends(joiners, costs)
    asked = F.col("ready_ms") + F.floor(F.col("n") * costs.tag / 1000)
    turn = F.row_number().over(Window.partitionBy("grid").orderBy(asked, "sid")) - 1
    theirs = in_turn(joiners.withColumn("turn", turn), asked, (F.col("turn") + present) * F.floor(2 * F.col("n") * costs.check / 1000)).withColumnRenamed("end", "dedup_end").drop("begin", "turn")
    out = None
    for name, rows in (("concurrent", ours), ("serial", theirs)):
        begun = in_turn(rows, F.col("dedup_end"), training_ms(costs))
        part = begun.groupBy("grid").agg((F.max("dedup_end") - F.min("ready_ms")).alias(f"{name}_dedup_ms"), (F.max("begin") - F.min("ready_ms")).alias(f"{name}_train_ms"))
        out = part if out is None else out.join(part, "grid")
    return out


def level_sizes(edges: DataFrame, n_clients: int) -> DataFrame:
    """(level, size): at each level of the tree the records of the largest pair of groups, both without inner duplicates."""
    out = None
    for level in range(levels(n_clients)):
        groups = edges.groupBy(F.shiftright("sid", level).alias("g")).agg(F.count_distinct("tag").alias("size"))
        best = groups.groupBy(F.shiftright("g", 1).alias("pair")).agg(F.sum("size").alias("size")).agg(F.lit(level).alias("level"), F.max("size").alias("size"))
        out = best if out is None else out.unionAll(best)
    return out if out is not None else edges.agg(F.lit(0).alias("level"), F.lit(0).cast("long").alias("size"))
