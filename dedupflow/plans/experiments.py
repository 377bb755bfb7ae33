"""The seven experiments on given tables: which records meet whom is real, times are virtual, bytes come from a ledger."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import arrival_ms, contact_ms
from ..functions.storage import scratch, written
from ..operators import claims, index, joining, recovery
from ..operators.index import append_state
from ..sources import table
from . import metrics, timeline, workload
from .timeline import COSTS

CLIENTS = (2, 4, 6, 8, 10)
RATIOS = (0.0, 0.1, 0.3, 0.5, 0.7, 0.9)
SCALES = (0.25, 0.5, 1.0, 1.5)
FAILURES = (0.2, 0.4, 0.6, 0.8)
JOINERS = (1, 3, 5, 7)
WORKERS = (1, 2, 4, 8, 16)


def base_size(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, int]:
    """The pool of distinct lines, written, and the records per client it allows."""
    records = written(workload.pool(spark, sf_dir), "pool")
    return records, workload.records_per_client(records.count())


def grid_edges(records: DataFrame, points: list[tuple[int, int, int, float]]) -> DataFrame:
    """(grid, sid, item_id, tag) of matched workloads for points (grid, N, n, d)."""
    out = None
    for grid, n_clients, n, d in points:
        e = workload.pairwise(records, n_clients, n, d).select(F.lit(grid).cast("long").alias("grid"), "sid", "item_id", "tag")
        out = e if out is None else out.unionByName(e)
    return written(out, "grid")


def won(edges: DataFrame) -> DataFrame:
    """(grid, tag, sid): winner of each tag within its grid point."""
    named = edges.withColumn("tag", F.concat_ws(":", "grid", "tag"))
    first = claims.winners(claims.requests_of(named.select("sid", "tag", "item_id")))
    return first.select(F.substring_index("tag", ":", 1).cast("long").alias("grid"), F.substring_index("tag", ":", -1).alias("tag"), F.col("holder").alias("sid"))


def clients_of(edges: DataFrame) -> DataFrame:
    """(grid, sid, ready_ms, n, n_run)."""
    n = edges.groupBy("grid", "sid").agg(F.count(F.lit(1)).alias("n"))
    run = won(edges).groupBy("grid", "sid").agg(F.count(F.lit(1)).alias("n_run"))
    return n.join(run, ["grid", "sid"], "left").select("grid", "sid", arrival_ms(F.col("sid")).cast("long").alias("ready_ms"), "n", F.coalesce("n_run", F.lit(0)).cast("long").alias("n_run"))


def sizes_of(edges: DataFrame, points) -> DataFrame:
    """(grid, level, size) over all grid points."""
    out = None
    for grid, n_clients, _, _ in points:
        s = timeline.level_sizes(edges.where(F.col("grid") == grid), n_clients).select(F.lit(grid).cast("long").alias("grid"), F.col("level").cast("long").alias("level"), "size")
        out = s if out is None else out.unionByName(s)
    return out


def end_to_end(records: DataFrame, points) -> DataFrame:
    """(grid, clients, per_client, total, distinct_records, concurrent_ms, serial_ms, concurrent_dedup_ms, serial_dedup_ms)."""
    edges = grid_edges(records, points)
    clients = written(clients_of(edges), "clients")
    c = timeline.concurrent(clients).withColumnsRenamed({"end_to_end_ms": "concurrent_ms", "dedup_ms": "concurrent_dedup_ms"})
    s = timeline.serial(clients, sizes_of(edges, points)).withColumnsRenamed({"end_to_end_ms": "serial_ms", "dedup_ms": "serial_dedup_ms"})
    v = edges.groupBy("grid").agg(F.count(F.lit(1)).alias("total"), F.count_distinct("tag").alias("distinct_records"), F.count_distinct("sid").alias("clients"))
    return v.join(c, "grid").join(s, "grid").select("grid", "clients", "total", "distinct_records", *[F.col(x).cast("long").alias(x) for x in ("concurrent_ms", "serial_ms", "concurrent_dedup_ms", "serial_dedup_ms")])


def exp1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Number of clients; grid is that number."""
    records, n = base_size(spark, sf_dir)
    return end_to_end(records, [(c, c, n, 0.3) for c in CLIENTS])


def exp2(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of duplicates; grid is the share in percent."""
    records, n = base_size(spark, sf_dir)
    return end_to_end(records, [(round(d * 100), 10, n, d) for d in RATIOS])


def exp3(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Records per client; grid is that number."""
    records, n = base_size(spark, sf_dir)
    return end_to_end(records, [(int(n * s), 10, int(n * s), 0.3) for s in SCALES])


def exp4(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Failures, with duplicates spread over all pairs of clients: (percent, released, recoverable, recovery times of both modes and phases).

    In the deduplication phase tags have entries and no holders, so a loss releases nothing; in the training phase what
    the lost hold is released and taken over. The serial scheme runs tags and tree again on the survivors, and starts
    the broken-off training anew if it had begun.
    """
    records, n = base_size(spark, sf_dir)
    edges = written(workload.pairwise(records, 10, n, 0.3, pairing="round_robin"), "edges")
    clients = edges.select("sid").distinct()
    created = written(append_state(None, edges), "state")
    state = written(claims.claim(created, claims.requests_of(edges)), "state")
    out = None
    for rate in FAILURES:
        lost = written(workload.failure_plan(clients, rate), "lost")
        online = clients.join(F.broadcast(lost), "sid", "left_anti")
        contacts = recovery.contacts_after(online, 30_000)
        released = written(recovery.release(state, edges, lost), "released")
        ours = metrics.recovery_ms(recovery.takeover(released, edges, contacts), 30_000, COSTS.promote)
        early = metrics.recovery_ms(recovery.takeover(recovery.release(created, edges, lost), edges, contacts), 30_000, COSTS.promote)
        left = edges.join(F.broadcast(lost), "sid", "left_anti")
        tree = timeline.level_sizes(left, 10).agg(F.sum(F.floor(F.col("size") * COSTS.pair / 1000)).alias("tree"))
        base = tree.select((F.coalesce("tree", F.lit(0)) + n * COSTS.tag // 1000).cast("long").alias("serial_dedup_ms"))
        row = metrics.recoverable(released, edges, online).crossJoin(ours.withColumnRenamed("recovery_ms", "concurrent_training_ms")).crossJoin(early.withColumnRenamed("recovery_ms", "concurrent_dedup_ms")).crossJoin(base)  # one row each
        row = row.select(F.lit(round(rate * 100)).cast("long").alias("percent"), "released", "recoverable", "concurrent_dedup_ms", "serial_dedup_ms", "concurrent_training_ms", (F.col("serial_dedup_ms") + COSTS.start_ms).alias("serial_training_ms"))
        out = row if out is None else out.unionByName(row)
    return out


def joined(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(grid, sid, ready_ms, n, n_run, changed): newcomers of every setting after their joins, and entries of old tags that a join has changed."""
    records, n = base_size(spark, sf_dir)
    out = None
    for j in JOINERS:
        edges = written(workload.pairwise(records, 10 + j, n, 0.3), "edges")
        old, new = edges.where("sid < 10"), edges.where("sid >= 10")
        state = written(claims.claim(append_state(None, old), claims.requests_of(old)), "state")
        after, _, replies = joining.join_clients(state, old, new)
        counts = replies.groupBy("sid").agg(F.count(F.lit(1)).alias("n"), F.count(F.when(F.col("op") == "RUN", 1)).alias("n_run"))
        row = counts.crossJoin(joining.touched_rows(state, after)).select(F.lit(j).cast("long").alias("grid"), "sid", arrival_ms(F.col("sid")).cast("long").alias("ready_ms"), "n", "n_run", "changed")  # one row on the right
        out = row if out is None else out.unionByName(row)
    return out


def exp5(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Joiners: (joiners, new_edges, won, changed, times until duplicates are known and until all train, both modes)."""
    rows = written(joined(spark, sf_dir), "joiners")
    counts = rows.groupBy("grid").agg(F.sum("n").alias("new_edges"), F.sum("n_run").alias("won"), F.max("changed").alias("changed"))
    times = timeline.joins(rows.drop("changed"))
    return counts.join(times, "grid").select(F.col("grid").alias("joiners"), "new_edges", "won", "changed", *[F.col(c).cast("long").alias(c) for c in times.columns[1:]])


def reductions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(experiment, point, phase, percent): what the concurrent mode saves of the serial one's recovery and stabilisation times."""
    out = None
    for name, key, df in (("failures", "percent", exp4(spark, sf_dir)), ("joins", "joiners", exp5(spark, sf_dir))):
        for phase, short in (("dedup", "dedup"), ("training", "training" if name == "failures" else "train")):
            saved = metrics.reductions(df, [key], {"saved": (f"concurrent_{short}_ms", f"serial_{short}_ms")})
            row = saved.select(F.lit(name).alias("experiment"), F.col(key).alias("point"), F.lit(phase).alias("phase"), F.col("saved").alias("percent"))
            out = row if out is None else out.unionByName(row)
    return out


def exp6_claim(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contested claims: (attempts, tags, won, same): ten clients all ask for the same records; order minimum and lock agree."""
    records, n = base_size(spark, sf_dir)
    tags = records.orderBy("tag").limit(n)
    requests = claims.requests_of(spark.range(10).select(F.col("id").alias("sid")).crossJoin(F.broadcast(tags)).select("sid", "tag", (F.pmod(F.xxhash64("tag"), F.lit(10**9)) * 10 + F.col("sid")).alias("item_id")))  # ten clients times the workload
    free, lock = claims.winners(requests), claims.claim_serialized(requests)
    both = free.join(lock.select("tag", F.col("holder").alias("h2"), F.col("item_id").alias("i2")), "tag")
    same = both.agg(F.count(F.when((F.col("holder") == F.col("h2")) & (F.col("item_id") == F.col("i2")), 1)).alias("same"), F.count(F.lit(1)).alias("won"))
    return requests.agg(F.count(F.lit(1)).alias("attempts"), F.count_distinct("tag").alias("tags")).crossJoin(same).select("attempts", "tags", "won", "same")  # one row each


def exp6_scale(spark: SparkSession, workers: int, moves: int = 50_000, lock: bool = False) -> DataFrame:
    """(tag, holder, item_id): each worker claims its own ``moves`` tags, by the order minimum in as many partitions as workers, or under the lock."""
    rows = spark.range(0, workers * moves, 1, workers).select(F.floor(F.col("id") / moves).alias("sid"), F.col("id").alias("tag"), F.col("id").alias("item_id"))
    requests = claims.requests_of(rows)
    return claims.claim_serialized(requests) if lock else claims.winners(requests)


def exp6_scaling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(workers, arm, moves, holders, wrong): customers dealt to workers by their keys; every worker's moves succeed under both arms. ``bench.py`` times ``exp6_scale``."""
    keys = table(spark, sf_dir, "customer").select(F.col("c_custkey").cast("long").alias("tag")).where("tag IS NOT NULL")
    out = None
    for workers in WORKERS:
        worker = lambda tag: F.pmod(tag, F.lit(workers).cast("long"))  # noqa: E731, B023
        requests = claims.requests_of(keys.select(worker(F.col("tag")).alias("sid"), "tag", F.col("tag").alias("item_id")).repartition(workers, "sid"))
        for arm, won in (("order_minimum", claims.winners(requests)), ("lock", claims.claim_serialized(requests))):
            row = won.agg(F.lit(workers).cast("long").alias("workers"), F.lit(arm).alias("arm"), F.count(F.lit(1)).alias("moves"), F.count_distinct("holder").alias("holders"), F.count(F.when(F.col("holder") != worker(F.col("tag")), 1)).alias("wrong"))
            out = row if out is None else out.unionByName(row)
    return out


def stored_index(spark: SparkSession, edges: DataFrame, buckets: int = 32) -> tuple[DataFrame, DataFrame]:
    """Both layouts of ``edges``, by tag and by client, as stored tables of their own in the shared folder, read back."""
    name, folder = f"index_{uuid.uuid4().hex}", scratch(spark, "index")
    made = index.create(spark, "dedupflow", name, 0, least=buckets, folder=folder)
    index.store(edges, "dedupflow", name, made, folder=folder)
    return spark.table(f"dedupflow.{name}_by_tag"), spark.table(f"dedupflow.{name}_by_sid")


def scanned_rows(df: DataFrame) -> int:
    """Rows that the scans of ``df``'s plan give when it is computed, by Spark's own metrics."""
    run = df._jdf.queryExecution()
    run.executedPlan().executeCollect()  # what a release finds: tags of the lost
    total, todo = 0, [run.executedPlan()]
    while todo:
        node = todo.pop()
        name = node.nodeName()
        if name.startswith("AdaptiveSparkPlan"):
            todo.append(node.executedPlan())
            continue
        if "QueryStage" in name:
            todo.append(node.plan())
            continue
        if name.startswith("Scan"):
            total += node.metrics().apply("numOutputRows").value()
        kids = node.children()
        todo += [kids.apply(i) for i in range(kids.size())]
    return total


def exp6_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One client lost, on the stored index: (owned, shared, held, different, index_reads_less).

    ``index_reads_less``: the scan of the layout by client gives less than a fifth of the rows of the layout by tag,
    which the ablation reads. ``bench.py`` has the times.
    """
    records, n = base_size(spark, sf_dir)
    edges = written(workload.pairwise(records, 10, n, 0.3).withColumn("tag", F.unhex("tag")), "edges")
    by_tag, by_sid = stored_index(spark, edges)
    state = written(claims.claim(append_state(None, edges), claims.requests_of(edges)), "state")
    lost = spark.createDataFrame([(3,)], "sid long")
    by_index, by_scan = recovery.release(state, by_sid, lost), recovery.release_scan(state, by_tag, lost)
    diff = by_index.exceptAll(by_scan).unionAll(by_scan.exceptAll(by_index)).agg(F.count(F.lit(1)).alias("different"))
    owned = edges.where("sid = 3").join(state.select("tag", "n_owners"), "tag").agg(F.count(F.lit(1)).alias("owned"), F.count(F.when(F.col("n_owners") > 1, 1)).alias("shared"))
    less = scanned_rows(recovery.owned_by(by_sid, lost)) * 5 < scanned_rows(by_tag.select("tag", "sid"))
    return owned.crossJoin(by_index.agg(F.count(F.lit(1)).alias("held"))).crossJoin(diff).select("owned", "shared", "held", "different", F.lit(less).alias("index_reads_less"))  # one row each


def release_seconds(spark: SparkSession, sf_dir: str, runs: int = 3) -> dict:
    """Wall-clock seconds to locate and release, and to recover after detection, with the stored layout by client and by a scan of all."""
    records, n = base_size(spark, sf_dir)
    edges = written(workload.pairwise(records, 10, n, 0.3).withColumn("tag", F.unhex("tag")), "edges")
    by_tag, by_sid = stored_index(spark, edges)
    state = written(claims.claim(append_state(None, edges), claims.requests_of(edges)), "state")
    lost, online = spark.createDataFrame([(3,)], "sid long"), edges.select("sid").distinct().where("sid <> 3")
    out = {}
    for name, find, layout in (("index", recovery.release, by_sid), ("scan", recovery.release_scan, by_tag)):
        found = lambda: find(state, layout, lost)  # noqa: E731, B023
        whole = lambda: recovery.apply_takeover(recovery.apply_release(state, found()), recovery.takeover(found(), by_sid, recovery.contacts_after(online, 30_000)))  # noqa: E731, B023
        out[name] = {"release": min(metrics.wall(found()) for _ in range(runs)), "recovery": min(metrics.wall(whole()) for _ in range(runs))}
    return out


def ledger(edges: DataFrame, points) -> DataFrame:
    """(grid, comm_bytes, storage_bytes, model_bytes, comm_percent, storage_percent) per grid point.

    Requests, replies and the masked exchange per record; beats and their answers per client, more of them the longer
    the others take to come.
    """
    per_client = edges.groupBy("grid", "sid").agg(F.count(F.lit(1)).alias("n")).withColumn("ready", arrival_ms(F.col("sid")))
    beats = F.floor((F.max("ready") * F.count(F.lit(1)) - F.sum("ready")) / 1000) + F.count(F.lit(1)) * metrics.BEATS_AFTER
    n = per_client.groupBy("grid").agg(F.sum("n").alias("n"), beats.alias("beats"))
    table = edges.sparkSession.createDataFrame([(g, c, metrics.capacity(c * r)) for g, c, r, _ in points], "grid long, clients long, slots long")
    per = metrics.TAG_BYTES * 2 + metrics.REQUEST_BYTES + metrics.OP_BYTES + 2 * metrics.GROUP_BYTES
    j = n.join(F.broadcast(table), "grid")
    comm = F.col("n") * per + F.col("beats") * (metrics.BEAT_BYTES + metrics.BEAT_REPLY_BYTES)
    storage = F.col("slots") * metrics.SLOT_BYTES + F.col("n") * (metrics.EDGE_BYTES + metrics.MAP_BYTES)
    model = F.col("clients") * (2 * metrics.MODEL_BYTES)
    return j.select("grid", comm.alias("comm_bytes"), storage.alias("storage_bytes"), model.alias("model_bytes"), F.round(comm * 100 / model, 6).alias("comm_percent"), F.round(storage * 100 / (F.col("clients") * metrics.KEPT_MODEL_BYTES), 6).alias("storage_percent"))


def exp7_clients(spark: SparkSession, sf_dir: str) -> DataFrame:
    records, n = base_size(spark, sf_dir)
    points = [(c, c, n, 0.3) for c in CLIENTS]
    return ledger(grid_edges(records, points), points)


def exp7_ratio(spark: SparkSession, sf_dir: str) -> DataFrame:
    records, n = base_size(spark, sf_dir)
    points = [(round(d * 100), 10, n, d) for d in RATIOS]
    return ledger(grid_edges(records, points), points)


def contacts(online: DataFrame, at: int) -> DataFrame:
    return online.select("sid", contact_ms(F.col("sid"), at).alias("at"))
