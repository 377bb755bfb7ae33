"""The query catalogue: every method, variant, baseline, measure and workload as (spark, sf_dir) -> DataFrame."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .. import sources, streaming
from ..functions import hashing
from ..functions.storage import written
from ..operators import baselines, claims, fuzzy, index, invariants, joining, queues, recovery, replay, rounds, scheduling, sessions, tags, training, transfer
from . import experiments, metrics, oracle, scenario, workload

Query = Callable[[SparkSession, str], DataFrame]
CUT = "2024-01-15 00:00:00"


def hexed(df: DataFrame) -> DataFrame:
    """Tags as lower-case hex."""
    return df.withColumn("tag", F.lower(F.hex("tag")))


def us(name: str, alias: str):
    return F.unix_micros(F.col(name).cast("timestamp")).alias(alias)


def _edges(spark, d, unit: str = "doc") -> DataFrame:
    return tags.protect(sources.documents(spark, d, unit)).drop("copies")


def _claimed(edges: DataFrame) -> DataFrame:
    return claims.claim(index.append_state(None, edges), claims.requests_of(edges))


def _sids(spark, *sids) -> DataFrame:
    return spark.createDataFrame([(s,) for s in sids], "sid long")


# -------------------------------------------------------------- claim pass


def q01_items(spark, d):
    docs = sources.table(spark, d, "documents")
    return docs.where("text IS NOT NULL").select(sources.client_of(F.col("source")).alias("sid"), F.col("doc_id").alias("item_id"), "n_chars")


def q02_owner_edges(spark, d):
    return hexed(_edges(spark, d))


def q03_owner_counts(spark, d):
    return index.append_state(None, _edges(spark, d)).groupBy(F.col("n_owners").alias("owners")).agg(F.count(F.lit(1)).alias("tags"))


def q04_claim_winners(spark, d):
    return hexed(claims.winners(claims.requests_of(_edges(spark, d))))


def q05_reply(spark, d):
    items = sources.documents(spark, d).select("sid", "item_id", hashing.content_hash(F.col("content")).alias("tag"))
    edges = _edges(spark, d)
    won = claims.winners(claims.requests_of(edges)).select("tag", "holder")
    return queues.reply_items(items, queues.reply(edges, won))


def q06_lane_sizes(spark, d):
    edges = _edges(spark, d)
    won = claims.winners(claims.requests_of(edges)).select("tag", "holder")
    return queues.route(queues.reply(edges, won)).groupBy("sid", "lane").agg(F.count(F.lit(1)).alias("n"))


def q07_claim_serialized(spark, d):
    return hexed(claims.claim_serialized(claims.requests_of(_edges(spark, d))))


def q07b_claim_windowed(spark, d):
    return hexed(claims.claim_windowed(claims.requests_of(_edges(spark, d))))


# -------------------------------------------------------------- tags


def q08_toy_tag(spark, d):
    """Three steps in columns: mask, raise to the key, take the mask off."""
    docs = sources.table(spark, d, "documents").where("text IS NOT NULL").select("doc_id", hashing.toy_hash(F.col("text")).alias("h"))
    masked = docs.withColumn("mask", F.lit(1) + F.pmod(F.col("doc_id") * 7919 + 104729, F.lit(hashing.TOY_Q - 1)))
    blinded = masked.withColumn("blinded", hashing.toy_power(F.col("h"), F.col("mask")))
    evaluated = blinded.withColumn("evaluated", hashing.toy_power(F.col("blinded"), F.lit(123456789)))
    return evaluated.withColumn("inverse", hashing.toy_inverse(F.col("mask"))).select("doc_id", hashing.toy_power(F.col("evaluated"), F.col("inverse")).alias("tag"))


def _protocol(spark, d, scheme):
    checked = written(tags.check_protocol(sources.documents(spark, d), tags.Authority.create(scheme, seed=5)), "protocol")
    n = checked.agg(F.count(F.lit(1)).alias("tags"), F.count_distinct("tag").alias("distinct_tags"), F.count(F.when(F.col("tag") != F.col("direct"), 1)).alias("mismatches"), F.count_distinct("blinded").alias("b"))
    return n.select("tags", "distinct_tags", "mismatches", (F.col("tags") - F.col("b")).alias("repeated_blinds"))


def q09_blinded_equals_direct(spark, d):
    return _protocol(spark, d, "modp2048")


def q09b_ristretto(spark, d):
    return _protocol(spark, d, "ristretto")


def q09c_keyed_edges(spark, d):
    e = tags.protect(sources.documents(spark, d), tags.Authority.create("keyed", seed=5))
    return e.agg(F.count(F.lit(1)).alias("edges"), F.count_distinct("tag").alias("tags"))


def q09d_key_epochs(spark, d):
    a = tags.Authority.create("keyed", seed=5)
    one, two = (tags.protect(sources.documents(spark, d), a.at(e)).select("tag").distinct() for e in (0, 1))
    both = one.join(two, "tag", "left_semi").agg(F.count(F.lit(1)).alias("common"))
    return one.agg(F.count(F.lit(1)).alias("first_epoch")).crossJoin(two.agg(F.count(F.lit(1)).alias("second_epoch"))).crossJoin(both)  # one row each


def q10_fnv1a64(spark, d):
    t = sources.table(spark, d, "documents").where("text IS NOT NULL").select(F.sha2("text", 256).alias("tag")).distinct()
    return t.select("tag", hashing.fnv1a64("tag").alias("fnv"))


def q11_lines_claims(spark, d):
    return hexed(claims.winners(claims.requests_of(_edges(spark, d, "line"))))


def q12_dense_overlap(spark, d):
    e = tags.protect(sources.parts_by_supplier(spark, d)).drop("copies")
    n = e.groupBy("tag").agg(F.count(F.lit(1)).alias("owners"))
    return claims.winners(claims.requests_of(e)).join(n, "tag").select(F.col("item_id").alias("part"), "holder", "owners")


# -------------------------------------------------------------- joining


def _joined(spark, d):
    edges = _edges(spark, d)
    old, new = edges.where("sid < 16"), edges.where("sid >= 16")
    state = _claimed(old)
    return old, new, state, joining.join_clients(state, old, new)


def q13_join_newcomers(spark, d):
    _, _, _, (_, _, replies) = _joined(spark, d)
    return hexed(replies.where("op = 'RUN'").select("tag", F.col("sid").alias("holder"), "item_id"))


def q14_join_isolation(spark, d):
    _, _, state, (after, _, _) = _joined(spark, d)
    return joining.touched_rows(state, after)


# -------------------------------------------------------------- sessions


def q15_sessions(spark, d):
    s = sessions.sessions(sources.beats(spark, d), "6 HOURS")
    return s.select("sid", "session", us("start", "start_us"), us("last_beat", "last_us"), "n")


def q16_losses(spark, d):
    lost = sessions.losses(sources.beats(spark, d), "6 HOURS", F.lit(CUT).cast("timestamp"))
    return lost.select("sid", us("last_beat", "last_us"), us("lost_at", "lost_us"))


def q16b_online(spark, d):
    return sessions.online(sources.beats(spark, d), "6 HOURS", F.lit(CUT).cast("timestamp")).select("sid", us("last_beat", "last_us"), "online")


# -------------------------------------------------------------- recovery


def q17_release(spark, d):
    edges = _edges(spark, d)
    return hexed(recovery.release(_claimed(edges), edges, _sids(spark, 3, 7)))


def q18_release_scan(spark, d):
    edges = _edges(spark, d)
    return hexed(recovery.release_scan(_claimed(edges), edges, _sids(spark, 3, 7)))


def q19_takeover(spark, d):
    c = scenario.run(spark, d)
    return hexed(c.taken.unionByName(c.cascade_taken).select("tag", "from_sid", "to_sid", F.col("taken_at").cast("long").alias("taken_at")))


def q20_waiting_unique(spark, d):
    c = scenario.run(spark, d)
    online = c.edges.select("sid").distinct().where(~F.col("sid").isin(*scenario.FIRST_LOST))
    return hexed(recovery.waiting(c.after_takeover, c.edges, online).select("tag"))


def q21_late_upload(spark, d):
    c = scenario.run(spark, d)
    count = lambda df, what: df.groupBy("sid").agg(F.count(F.lit(1)).alias("n")).select("sid", F.lit(what).alias("outcome"), "n")
    return count(c.accepted, "accepted").unionByName(count(c.stale, "rejected"))


def q22_rejoin_training(spark, d):
    return hexed(scenario.run(spark, d).rejoin_replies.select("tag", "op"))


def q22b_rejoin_dedup(spark, d):
    """Client 5 is lost before it claims anything and comes back after everybody else has claimed."""
    edges = _edges(spark, d)
    state = claims.claim(index.append_state(None, edges), claims.requests_of(edges.where("sid <> 5")))
    after = recovery.rejoin_dedup(state, edges, 5)
    own = edges.where("sid = 5").select("tag")
    return hexed(own.join(after, "tag").select("tag", F.when(F.col("holder") == 5, F.col("holder")).alias("won")))


# -------------------------------------------------------------- rounds


def q23_commit_weights(spark, d):
    return rounds.weights(scenario.run(spark, d).ended)


def _local_models(spark, d):
    e = sources.table(spark, d, "embeddings").where("embedding IS NOT NULL")
    return e.select(F.pmod("vec_id", F.lit(10)).alias("sid"), "label", "embedding")


def q24_fedavg(spark, d):
    """Weights are what clients have committed (here: their vectors of labels below 5)."""
    v = _local_models(spark, d)
    committed = v.where("label < 5").groupBy("sid").agg(F.count(F.lit(1)).alias("m"))
    return training.fedavg(training.centroid(v), committed).select(F.col("dim").cast("long").alias("dim"), F.round("w", 6).alias("w"))


def q25_fedavg_static(spark, d):
    """Weights are all local records; with mean vectors as models the result is the mean of all vectors."""
    v = _local_models(spark, d)
    local = training.centroid(v)
    return training.fedavg(local, training.static_weights(v)).select(F.col("dim").cast("long").alias("dim"), F.round("w", 6).alias("w"))


def q26_reset_retain(spark, d):
    edges = _edges(spark, d)
    state = _claimed(edges)
    done = rounds.commit(state, scenario.uploads_of(state))
    again = rounds.retain(rounds.reset(done), edges.select("sid").distinct())
    return hexed(again.select("tag", "holder", "last_holder", "epoch"))


def q27_history_assign(spark, d):
    return hexed(scenario.next_round(scenario.run(spark, d)))


def q28_history_off(spark, d):
    c = scenario.run(spark, d)
    state, out = rounds.reset(c.ended), None
    for name, use in (("on", True), ("off", False)):
        m = metrics.reassigned(scenario.next_round(c, use), state, c.risk).select(F.lit(name).alias("history"), "reassigned", "at_risky")
        out = m if out is None else out.unionByName(m)
    return out


def q28b_demotions(spark, d):
    c = scenario.run(spark, d)
    return hexed(scheduling.demotions(scenario.next_round(c), c.edges, c.risk))


# -------------------------------------------------------------- baselines


def q29_tree_dedup(spark, d):
    return hexed(baselines.tree_dedup(_edges(spark, d), 20)[0].select("tag", "sid"))


def q30_tree_levels(spark, d):
    return baselines.tree_dedup(_edges(spark, d), 20)[1]


def q30b_tree_rerun(spark, d):
    kept, _ = baselines.rerun_after_loss(_edges(spark, d), _sids(spark, 3, 7), 20)
    return kept.groupBy("sid").agg(F.count(F.lit(1)).alias("kept"))


def q31_pairwise_weighted(spark, d):
    w = baselines.pairwise_weighted(_edges(spark, d))
    return w.groupBy("freq").agg(F.count(F.lit(1)).alias("copies"), F.round(F.sum("w"), 6).alias("weight"))


def q31b_pair_overlaps(spark, d):
    return baselines.pair_overlaps(_edges(spark, d))


def q32_join_pairwise(spark, d):
    edges = _edges(spark, d)
    return baselines.join_pairwise(edges.where("sid < 16"), edges.where("sid >= 16"))[1]


def q33_local_only(spark, d):
    return baselines.local_only(sources.documents(spark, d))


def q34_no_dedup(spark, d):
    return baselines.no_dedup(sources.documents(spark, d))


def q34b_saved(spark, d):
    edges = _edges(spark, d)
    return metrics.saved(edges, _claimed(edges))


# -------------------------------------------------------------- workloads and experiments


def q35_pairwise_workload(spark, d):
    records, n = experiments.base_size(spark, d)
    e = workload.pairwise(records, 10, n, 0.3)
    o = e.groupBy("tag").agg(F.count(F.lit(1)).alias("owners"))
    return e.join(o, "tag").groupBy("sid").agg(F.count(F.lit(1)).alias("n"), F.count(F.when(F.col("owners") == 2, 1)).alias("shared"), F.max("owners").alias("most"))


def q36_split(spark, d):
    return workload.split(sources.table(spark, d, "documents"), "doc_id").groupBy("held_out").agg(F.count(F.lit(1)).alias("n"))


def q44_recoverable(spark, d):
    edges = _edges(spark, d)
    lost = _sids(spark, 3, 7)
    online = edges.select("sid").distinct().where("sid NOT IN (3, 7)")
    return metrics.recoverable(recovery.release(_claimed(edges), edges, lost), edges, online)


# -------------------------------------------------------------- invariants


def q45_uniqueness(spark, d):
    c = scenario.run(spark, d)
    own = invariants.holders_own(c.ended, c.edges).select(F.col("foreign").alias("foreign_holders"))
    moves = invariants.legal_moves(c.claimed, c.after_takeover).select(F.col("illegal").alias("illegal_moves"))
    return invariants.uniqueness(c.ended).crossJoin(own).crossJoin(moves)  # one row each


def q46_coverage(spark, d):
    c = scenario.run(spark, d)
    return invariants.coverage(c.ended, c.edges, c.edges.select("sid").distinct().where("sid NOT IN (13, 18)"))


def q47_fuzzy_clusters(spark, d):
    """Clusters of documents whose five-word shingle sets link at 0.8 or more."""
    docs = sources.table(spark, d, "documents").select(F.col("doc_id").alias("id"), F.col("text").alias("content"))
    return fuzzy.minhash_clusters(docs)


# -------------------------------------------------------------- transfer


def _files(spark, d):
    docs = sources.table(spark, d, "documents").where("text IS NOT NULL AND text RLIKE '^[\\\\x00-\\\\x7F]*$' AND length(text) = octet_length(text)")
    return docs.select(F.col("doc_id").alias("file_id"), F.col("text").cast("binary").alias("data"))


def q48_chunks(spark, d):
    return transfer.split(_files(spark, d), 1024).select("file_id", "seq", "offset", "digest")


def q48b_resume(spark, d):
    """Chunk 1 is lost on the way and chunk 2 damaged."""
    sent = transfer.split(_files(spark, d), 1024)
    got = sent.where("seq <> 1").withColumn("data", F.when(F.col("seq") == 2, F.concat(F.lit(b"x"), "data")).otherwise(F.col("data")))
    return transfer.resume_from(sent.select("file_id", "seq", "digest"), got)


# -------------------------------------------------------------- reports


def q49_state_cube(spark, d):
    c = scenario.run(spark, d)
    who = F.when(F.col("holder").isNull(), "free").when(F.col("holder") == F.col("sid"), "own").otherwise("other")
    return c.edges.join(c.ended.select("tag", "holder"), "tag").select("sid", who.alias("who")).cube("sid", "who").agg(F.count(F.lit(1)).alias("n"))


def q50_rollup(spark, d):
    return sources.table(spark, d, "documents").rollup("lang", "source").agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"))


def q51_grouping_sets(spark, d):
    sources.table(spark, d, "documents").select("lang", "source", "text").createOrReplaceTempView("dedupflow_documents")
    return spark.sql("SELECT lang, source, count(DISTINCT sha2(text, 256)) AS distinct_texts FROM dedupflow_documents GROUP BY GROUPING SETS ((lang), (source), ())")


def q52_pivot(spark, d):
    lanes = queues.route(queues.reply(_edges(spark, d), _claimed(_edges(spark, d))))
    return lanes.groupBy("sid").pivot("lane", ["active", "standby"]).agg(F.count(F.lit(1))).na.fill(0).select("sid", F.col("active").cast("long").alias("active"), F.col("standby").cast("long").alias("standby"))


def q53_topk_shared(spark, d):
    n = _edges(spark, d).groupBy("tag").agg(F.count(F.lit(1)).alias("owners"), F.min("item_id").alias("item_id"))
    return hexed(n).orderBy(F.desc("owners"), "tag").limit(20)


def q54_per_lang_topk(spark, d):
    t = sources.table(spark, d, "documents").where("text IS NOT NULL").groupBy("lang", F.sha2("text", 256).alias("tag")).agg(F.count(F.lit(1)).alias("copies"))
    w = Window.partitionBy("lang").orderBy(F.desc("copies"), "tag")
    return t.withColumn("r", F.row_number().over(w)).where("r <= 3").drop("r")


def q55_asof_beat(spark, d):
    beats = sources.beats(spark, d)
    asked = beats.select("sid").distinct().select("sid", F.lit("2024-01-10 12:00:00").cast("timestamp").alias("at"), F.col("sid").alias("rid"))
    return sessions.last_beat_before(asked, beats).select("sid", us("last_beat", "last_us"))


def q56_range_liveness(spark, d):
    return sessions.recent_beats(sources.beats(spark, d), 21600).select("sid", "beat_id", "recent")


def q57_tumbling(spark, d):
    return streaming.beats_per_window(sources.beats(spark, d), "1 hour").select(us("start", "start_us"), "n")


def q58_sliding(spark, d):
    return streaming.beats_per_window(sources.beats(spark, d), "6 hours", "1 hour").select(us("start", "start_us"), "n")


def q58b_session_window(spark, d):
    """The same sessions by session windows: their gap excludes a silence of exactly the timeout as well."""
    return streaming.session_windows(sources.beats(spark, d), "6 hours").select("sid", us("start", "start_us"), us("last_beat", "last_us"), "n")


def q59_set_ops(spark, d):
    e = _edges(spark, d)
    a, b = e.where("sid < 10").select("tag"), e.where("sid >= 10").select("tag")
    count = lambda df, part: df.agg(F.lit(part).alias("part"), F.count(F.lit(1)).alias("n"))
    return count(a.intersect(b), "both").unionAll(count(a.exceptAll(b).distinct().join(b, "tag", "left_anti"), "first_only")).unionAll(count(a.union(b).distinct(), "any"))


def q60_props_json(spark, d):
    k = F.from_json("props", "k BIGINT")["k"]
    return sources.table(spark, d, "events").groupBy("event_type").agg(F.sum(k).alias("k"), F.count(F.lit(1)).alias("n"))


# -------------------------------------------------------------- streams, replay, rounds


def q61_stream_equals_batch(spark, d):
    streaming.use_rocksdb(spark)
    replies = streaming.run_to_table(streaming.claim_stream(streaming.request_stream(spark, d)))
    # a client's further copies of a tag ask again and are answered alike; its first record stands for all
    return replies.groupBy("sid", "tag").agg(F.min("item_id").alias("item_id"), F.max("op").alias("op")).select("sid", "item_id", "op")


def q62_multi_round_replay(spark, d):
    """Relational states against the fold of the same log: claims, a loss, takeovers, uploads; rows that differ."""
    edges = written(_edges(spark, d), "edges")
    lost = _sids(spark, 3, 7)
    online = edges.select("sid").distinct().where("sid NOT IN (3, 7)")
    state = _claimed(edges)
    released = recovery.release(state, edges, lost)
    contacts = recovery.contacts_after(online, 30_000)
    held = recovery.apply_takeover(recovery.apply_release(state, released), recovery.takeover(released, edges, contacts))
    none = F.lit(None)
    log = replay.submissions(edges, hashing.arrival_ms(F.col("sid")))
    wide = lost.select(F.lit(30_000).cast("long").alias("ts"), F.lit(0).cast("long").alias("seq"), F.lit("LOST").alias("kind"), "sid", none.cast("binary").alias("tag"), none.cast("int").alias("epoch"))
    beats = contacts.select(F.col("at").cast("long").alias("ts"), F.lit(0).cast("long").alias("seq"), F.lit("BEAT").alias("kind"), "sid", none.cast("binary").alias("tag"), none.cast("int").alias("epoch"))
    folded = replay.fold(log.unionByName(replay.expand(wide.unionByName(beats), edges)))
    a, b = held.select("tag", F.struct("state", "holder", "epoch").alias("x")), folded.select("tag", F.struct("state", "holder", "epoch").alias("y"))
    j = a.join(b, "tag", "full_outer")
    return j.agg(F.count(F.lit(1)).alias("tags"), F.count(F.when(~F.col("x").eqNullSafe(F.col("y")), 1)).alias("different"))


def q63_sketch_overlap(spark, d):
    """Sketches of distinct tags and of the overlap of two halves, within 5 % and 15 % of the exact counts."""
    e = _edges(spark, d)
    n = e.agg(F.approx_count_distinct("tag", 0.02).alias("approx"), F.count_distinct("tag").alias("exact"))
    h = hexed(e)
    sketch = lambda df, name: df.agg(F.expr("theta_sketch_agg(tag)").alias(name))
    both = sketch(h.where("sid < 10"), "a").crossJoin(sketch(h.where("sid >= 10"), "b")).select(F.expr("theta_sketch_estimate(theta_intersection(a, b))").alias("guess"))  # one row each
    real = h.where("sid < 10").select("tag").intersect(h.where("sid >= 10").select("tag")).agg(F.count(F.lit(1)).alias("common"))
    return n.crossJoin(both).crossJoin(real).select((F.abs(F.col("approx") - F.col("exact")) <= 0.05 * F.col("exact")).alias("distinct_ok"), (F.abs(F.col("guess") - F.col("common")) <= 0.15 * F.col("common") + 1).alias("overlap_ok"))


def q64_stable_rounds(spark, d):
    """Two more rounds without losses: nobody contends, no tag moves."""
    edges = written(_edges(spark, d), "edges")
    state, out = _claimed(edges), None
    everyone = edges.select("sid").distinct()
    for number in (2, 3):
        before = written(rounds.reset(rounds.commit(state, scenario.uploads_of(state))), "round")
        state = written(rounds.retain(before, everyone), "round")
        row = state.agg(F.lit(number).alias("round"), F.count(F.when(F.col("state") == index.HELD, 1)).alias("held"), F.count(F.when(F.col("holder") != F.col("last_holder"), 1)).alias("moved"))
        out = row if out is None else out.unionByName(row)
    return out


def q65_pages_text(spark, d):
    return sources.pages_text(spark, d).where("text IS NOT NULL").select("page_id", "host")


def q66_controls(spark, d):
    return sources.conversations(spark, d).agg(F.count(F.lit(1)).alias("turns"), F.count_distinct(F.sha2("content", 256)).alias("distinct_turns"))


def q67_no_private_columns(spark, d):
    edges = _edges(spark, d)
    state = _claimed(edges)
    frames = (edges, state, claims.requests_of(edges), queues.reply(edges, state), recovery.release(state, edges, _sids(spark, 3)))
    return invariants.private_columns(*frames)


def q68_fleet(spark, d):
    """The plan of a fleet of all customers, those from number 100 on as joiners."""
    f = streaming.fleet_of(sources.table(spark, d, "customer").select(F.col("c_custkey").alias("sid")), clients=100)
    return f.agg(F.count(F.lit(1)).alias("clients"), F.count(F.when(F.col("joins"), 1)).alias("joiners"), F.min((F.col("online_ms") >= 0) & (F.col("online_ms") < 20000)).alias("in_range"))


# -------------------------------------------------------------- index on disk, lanes, barrier, logs


def _stored(spark, d):
    edges = written(_edges(spark, d), "edges")
    return edges, *experiments.stored_index(spark, edges)


def q10b_locate_stored(spark, d):
    """Entries of what client 3 owns, located in the stored index, with their first slot in a table of 4,096."""
    edges, by_tag, by_sid = _stored(spark, d)
    asked = recovery.owned_by(by_sid, _sids(spark, 3))
    found = index.locate(asked, index.append_state(None, by_tag))
    return hexed(found.select("tag", "n_owners"))


def q10c_layouts_agree(spark, d):
    edges, by_tag, by_sid = _stored(spark, d)
    return by_tag.agg(F.count(F.lit(1)).alias("edges")).crossJoin(invariants.layouts_agree(by_tag, by_sid))  # one row each


def q17b_release_stored(spark, d):
    edges, _, by_sid = _stored(spark, d)
    return hexed(recovery.release(_claimed(edges), by_sid, _sids(spark, 3, 7)))


def q13b_owners_after_join(spark, d):
    _, _, _, (after, _, _) = _joined(spark, d)
    return after.groupBy(F.col("n_owners").alias("owners")).agg(F.count(F.lit(1)).alias("tags"))


def q14b_admission(spark, d):
    """Sources as names: those of one digit are known, the others are admitted later."""
    names = sources.table(spark, d, "documents").where("source IS NOT NULL").select(F.col("source").alias("name")).distinct()
    return sessions.admit(sessions.admit(None, names.where("length(name) = 4")), names)


def q05b_messages(spark, d):
    """The reply maps as they travel, opened again: operations per client."""
    edges = _edges(spark, d)
    opened = queues.message(queues.reply(edges, _claimed(edges))).select("sid", F.explode("ops").alias("tag", "op"))
    return opened.groupBy("sid", "op").agg(F.count(F.lit(1)).alias("n"))


def _lanes_after(c):
    first = queues.route(queues.reply(c.edges, c.claimed))
    return first, queues.promote(first, c.taken.select(F.col("to_sid").alias("sid"), "tag"))


def q06b_promoted(spark, d):
    """Lanes after the first takeover: what was taken over has become active at its new trainer."""
    first, after = _lanes_after(scenario.run(spark, d))
    count = lambda df, when: df.groupBy("lane").agg(F.count(F.lit(1)).alias("n")).select(F.lit(when).alias("step"), "lane", "n")
    return count(first, "claimed").unionByName(count(after, "taken over"))


def q06c_demoted(spark, d):
    """Lanes of clients at risk after the next round's allocation has parked what others train."""
    c = scenario.run(spark, d)
    ended = queues.route(queues.reply(c.edges, c.ended))
    after = queues.demote(ended, scheduling.demotions(scenario.next_round(c), c.edges, c.risk))
    return after.join(F.broadcast(c.risk), "sid").groupBy("sid", "lane").agg(F.count(F.lit(1)).alias("n"))


def q19b_takeover_log(spark, d):
    c = scenario.run(spark, d)
    rows = recovery.log(c.taken, F.lit(30_000), 1).unionByName(recovery.log(c.cascade_taken, F.lit(35_000), 1))
    return hexed(rows.select("tag", "from_sid", "to_sid", F.col("released_at").cast("long").alias("released_at"), F.col("taken_at").cast("long").alias("taken_at"), "round"))


def q19c_lost_before_reply(spark, d):
    """Client 3 has claimed and is lost before its reply: what it never saw is released like any other work, and taken over."""
    edges = written(_edges(spark, d), "edges")
    released = recovery.release(_claimed(edges), edges, _sids(spark, 3))
    online = edges.select("sid").distinct().where("sid <> 3")
    return hexed(recovery.takeover(released, edges, recovery.contacts_after(online, 30_000)).select("tag", "to_sid"))


def q19d_newcomer_takes_over(spark, d):
    """Clients 3 and 7 are lost, then clients from 16 on join: what they own of the released tags falls to the first to ask."""
    edges = written(_edges(spark, d), "edges")
    old, new = edges.where("sid < 16"), edges.where("sid >= 16")
    state = _claimed(old)
    freed = written(recovery.apply_release(state, recovery.release(state, old, _sids(spark, 3, 7))), "state")
    after, _, _ = joining.join_clients(freed, old, new)
    was = freed.where("state = 0").select("tag")
    return hexed(after.join(was, "tag", "left_semi").where("holder IS NOT NULL").select("tag", "holder"))


def q23b_barrier(spark, d):
    """Whether the round may be aggregated after the claims, after the release, after the takeovers and after the uploads."""
    c = scenario.run(spark, d)
    everyone = c.edges.select("sid").distinct()
    online = everyone.where(~F.col("sid").isin(*scenario.FIRST_LOST))
    steps = [("claimed", rounds.ready(c.claimed, c.edges, everyone)), ("taken over", rounds.ready(c.after_takeover, c.edges, online)), ("ended", rounds.ready(c.ended, c.edges, online.where(F.col("sid") != scenario.SECOND_LOST)))]
    return spark.createDataFrame(steps, "step string, ready boolean")


def q26b_retain_some(spark, d):
    """Only even clients have beaten: the others' tags stay free until they do."""
    edges = _edges(spark, d)
    state = _claimed(edges)
    done = rounds.reset(rounds.commit(state, scenario.uploads_of(state)))
    return hexed(rounds.retain(done, edges.select("sid").distinct().where("sid % 2 = 0")).select("tag", "state", "holder"))


def _rounds_with_losses(spark, d, use_history: bool):
    edges = written(_edges(spark, d), "edges")
    out = None
    for r in rounds.run(edges, {1: (0, 18), 2: (13, 0), 3: (5,)}, 3, use_history=use_history):
        before = None if out is None else last
        moved = r.assignment.agg(F.lit(0).cast("long").alias("moved")) if before is None else r.assignment.join(before, "tag").agg(F.count(F.when(F.col("sid") != F.col("was"), 1)).alias("moved"))
        last = r.state.select("tag", F.coalesce("holder", "last_holder").alias("was"))
        done = r.state.agg(F.lit(r.number).alias("round"), F.count(F.when(F.col("state") == index.DONE, 1)).alias("done"))
        taken = r.log.where(F.col("round") == r.number).agg(F.count(F.lit(1)).alias("taken"))
        row = done.crossJoin(moved).crossJoin(taken).withColumn("ready", F.lit(r.ready))  # one row each
        out = row if out is None else out.unionByName(row)
    return out


def q64b_rounds_with_losses(spark, d):
    """Three rounds by the driver of rounds, with losses in each: records done, moved to another trainer, taken over, and the barrier."""
    return _rounds_with_losses(spark, d, True)


def q64c_rounds_without_history(spark, d):
    """The same three rounds with the record of losses ignored."""
    return _rounds_with_losses(spark, d, False)


# -------------------------------------------------------------- baselines by either cipher, text models


def _intersections(spark, d, psi):
    return baselines.group_intersections(baselines.tag_for(sources.documents(spark, d), psi), 20)


def q29b_symmetric_intersections(spark, d):
    return _intersections(spark, d, "symmetric")


def q29c_oblivious_intersections(spark, d):
    return _intersections(spark, d, "oprf")


def q29d_exact_distinct(spark, d):
    return hexed(baselines.exact_distinct(sources.documents(spark, d)))


def q24b_bigram_models(spark, d):
    """Text models of what each client trains after the claims, added up: every distinct text counts once."""
    edges = written(_edges(spark, d), "edges")
    won = _claimed(edges).select("tag", F.col("holder").alias("sid"))
    items = sources.documents(spark, d).withColumn("tag", hashing.content_hash(F.col("content")))
    own = items.join(won, ["sid", "tag"], "left_semi").dropDuplicates(["sid", "tag"])
    return training.bigram_counts(own.select("sid", "content")).groupBy("bigram").agg(F.sum("n").alias("n")).where("n >= 100")


QUERIES: dict[str, Query] = {name: fn for name, fn in list(globals().items()) if name.startswith("q") and name[1:3].isdigit() and callable(fn)}
QUERIES |= {
    "q37_exp1": experiments.exp1,
    "q38_exp2": experiments.exp2,
    "q39_exp3": experiments.exp3,
    "q40_exp4": experiments.exp4,
    "q41_exp5": experiments.exp5,
    "q41b_reductions": experiments.reductions,
    "q42_exp6_claim": experiments.exp6_claim,
    "q42c_exp6_scaling": experiments.exp6_scaling,
    "q42b_exp6_index": experiments.exp6_index,
    "q43_exp7_clients": experiments.exp7_clients,
    "q43b_exp7_ratio": experiments.exp7_ratio,
}
ORACLE_SQL: dict[str, str] = {name: sql for name, sql in oracle.SQL.items() if name in QUERIES}
