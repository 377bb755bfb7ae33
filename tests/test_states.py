"""Scripted logs, the state machine, and rounds; relational operators against hand answers and the fold."""

import pytest
from pyspark.sql import functions as F

from dedupflow.operators import claims, index, invariants, joining, queues, recovery, replay, rounds, scheduling, sessions
from dedupflow.operators.index import DONE, FREE, HELD

A, U = bytearray(b"a"), bytearray(b"u")


def edges_of(spark, rows):
    return spark.createDataFrame([(s, t, i) for i, (s, t) in enumerate(rows)], "sid long, tag binary, item_id long")


def sids(spark, *values):
    return spark.createDataFrame([(v,) for v in values], "sid long")


def view(state):
    return {bytes(r.tag): (r.state, r.holder) for r in state.collect()}


def at(edges):
    return claims.requests_of(edges, F.col("item_id"))


def claimed(edges):
    return claims.claim(index.append_state(None, edges), at(edges))


def test_contested_tag_has_one_winner_and_two_owners(spark):
    e = edges_of(spark, [(1, A), (2, A)])
    s = claimed(e)
    assert view(s) == {b"a": (HELD, 1)} and s.first().n_owners == 2
    assert {(r.sid, r.op) for r in queues.reply(e, s).collect()} == {(1, "RUN"), (2, "PARK")}
    # asking again for what one holds is answered as before; nothing moves
    assert view(claims.claim(s, at(e))) == {b"a": (HELD, 1)}


def test_created_entry_binds_nobody(spark):
    e = edges_of(spark, [(1, A), (2, A)])
    s = index.append_state(None, e)
    assert view(s) == {b"a": (FREE, None)}
    assert recovery.release(s, e, sids(spark, 1)).count() == 0  # lost in the dedup phase: nothing to undo
    assert view(claims.claim(s, at(e.where("sid = 2")))) == {b"a": (HELD, 2)}


def lost_in_training(spark):
    e = edges_of(spark, [(1, A), (1, U), (2, A), (3, A)])
    s = claimed(e)
    released = recovery.release(s, e, sids(spark, 1))
    return e, s, released, recovery.apply_release(s, released)


def test_loss_in_training_hands_shared_tags_on(spark):
    e, s, released, freed = lost_in_training(spark)
    assert released.count() == 2 and {tuple(r) for r in released.collect()} == {tuple(r) for r in recovery.release_scan(s, e, sids(spark, 1)).collect()}
    contacts = spark.createDataFrame([(2, 10), (3, 5)], "sid long, at long")
    taken = recovery.takeover(released, e, contacts)
    after = recovery.apply_takeover(freed, taken)
    assert view(after) == {b"a": (HELD, 3), b"u": (FREE, None)}
    assert [bytes(r.tag) for r in recovery.waiting(after, e, sids(spark, 2, 3)).collect()] == [b"u"]
    log = recovery.log(taken, F.lit(1), 1).collect()
    assert [(r.from_sid, r.to_sid, r.taken_at) for r in log] == [(1, 3, 5)]
    # the taker is lost too: the next owner gets it, with a second log row
    again = recovery.release(after, e, sids(spark, 3))
    third = recovery.takeover(again, e, spark.createDataFrame([(2, 20)], "sid long, at long"))
    assert view(recovery.apply_takeover(recovery.apply_release(after, again), third))[b"a"] == (HELD, 2)
    assert invariants.legal_moves(s, freed).first().illegal == 0


def test_late_upload_is_rejected_and_rejoin_parks(spark):
    e, s, released, freed = lost_in_training(spark)
    old_rights = s.where("holder = 1").select("tag", F.col("holder").alias("sid"), "epoch")
    after = recovery.apply_takeover(freed, recovery.takeover(released, e, spark.createDataFrame([(2, 1)], "sid long, at long")))
    assert rounds.rejected(after, old_rights).count() == 2
    assert view(rounds.commit(after, old_rights)) == view(after)
    rejoined, replies = recovery.rejoin_training(after, e, 1)
    assert {bytes(r.tag): r.op for r in replies.collect()} == {b"a": "PARK", b"u": "RUN"}
    assert view(rejoined) == {b"a": (HELD, 2), b"u": (HELD, 1)}
    assert rounds.rejected(rejoined, old_rights).count() == 2  # the right of the first epoch stays void


def test_newcomer_takes_over(spark):
    e, s, released, freed = lost_in_training(spark)
    new = spark.createDataFrame([(9, A, 90)], "sid long, tag binary, item_id long")
    after, edges, replies = joining.join_clients(freed, e, new)
    assert view(after)[b"a"] == (HELD, 9) and replies.first().op == "RUN" and edges.count() == 5
    assert joining.touched_rows(s, joining.join_clients(s, e, new)[0]).first().changed == 0


def test_commit_before_loss_stays(spark):
    e = edges_of(spark, [(1, A)])
    s = claimed(e)
    done = rounds.commit(s, s.select("tag", F.col("holder").alias("sid"), "epoch"))
    assert view(done) == {b"a": (DONE, 1)} and recovery.release(done, e, sids(spark, 1)).count() == 0


def test_barrier(spark):
    e, s, released, freed = lost_in_training(spark)
    online = sids(spark, 2, 3)
    assert not rounds.ready(s, e, online)
    assert rounds.ready(freed, strict=False) and not rounds.ready(freed, e, online)  # the gap between release and takeover
    assert rounds.ready(freed, e, sids(spark, 7))


def test_history(spark):
    e = edges_of(spark, [(1, A), (1, U), (2, A)])
    s = claimed(e)
    ended = rounds.reset(rounds.commit(s, s.select("tag", F.col("holder").alias("sid"), "epoch")))
    plan = lambda risk, online, **o: {bytes(r.tag): (r.sid, r.how) for r in scheduling.assign(ended, e, sids(spark, *risk), sids(spark, *online), **o).collect()}
    assert plan([1], [1, 2]) == {b"a": (2, "moved"), b"u": (1, "kept")}
    assert plan([9], [1, 2]) == {b"a": (1, "kept"), b"u": (1, "kept")}
    assert plan([1, 2], [2]) == {b"a": (2, "moved"), b"u": (None, "unassigned")}  # all at risk: the owner that is there
    assert plan([1], [1, 2], use_history=False) == {b"a": (1, "kept"), b"u": (1, "kept")}
    for pick in ("lowest_sid", "least_loaded"):
        assert plan([1], [1, 2], pick=pick)[b"a"] == (2, "moved")
    with pytest.raises(ValueError):
        plan([1], [1, 2], pick="none")
    risk = spark.createDataFrame([(1, 1), (2, 3)], "sid long, round int")
    assert [r.sid for r in scheduling.risky(risk, 4).collect()] == [2] and scheduling.risky(risk, 5).count() == 0


def test_retention_waits_for_beats(spark):
    e = edges_of(spark, [(1, A), (2, U)])
    s = claimed(e)
    ended = rounds.reset(rounds.commit(s, s.select("tag", F.col("holder").alias("sid"), "epoch")))
    assert set(view(ended).values()) == {(FREE, None)}
    assert view(rounds.retain(ended, sids(spark, 1))) == {b"a": (HELD, 1), b"u": (FREE, None)}


def test_every_transition_of_the_machine():
    for state, holder in ((FREE, None), (HELD, 1), (HELD, 2), (DONE, 1)):
        def cell():
            e = replay.Entry()
            e.state, e.holder, e.owners = state, holder, {1, 2}
            return e

        e = cell()
        reply = e.apply("SUBMIT", 1, None)
        assert reply == ("RUN" if state == FREE or (state == HELD and holder == 1) else "PARK")
        e = cell()
        e.apply("LOST", 1, None)
        assert (e.state, e.epoch) == ((FREE, 1) if (state, holder) == (HELD, 1) else (state, 0))
        e = cell()
        assert (e.apply("UPLOAD", 1, 0) == "OK") == ((state, holder) == (HELD, 1))
        e = cell()
        assert e.apply("UPLOAD", 1, 5) == "REJECT"
        e = cell()
        e.apply("ROUND", None, None)
        assert e.state == (FREE if state == DONE else state)


def test_lanes(spark):
    e = edges_of(spark, [(1, A), (2, A), (2, U)])
    lanes = queues.route(queues.reply(e, claimed(e)))
    assert {(r.sid, bytes(r.tag)): r.lane for r in lanes.collect()} == {(1, b"a"): "active", (2, b"a"): "standby", (2, b"u"): "active"}
    moves = spark.createDataFrame([(2, A)], "sid long, tag binary")
    up = queues.promote(lanes, moves)
    assert up.where("lane = 'active'").count() == 3 and queues.demote(up, moves).where("lane = 'standby'").count() == 1
    assert invariants.lanes(lanes, e).first().asDict() == {"missing": 0, "twice": 0}
    assert queues.message(queues.reply(e, claimed(e))).count() == 2


def test_timeout_is_strict(spark):
    beats = spark.createDataFrame([(1, "2024-01-01 00:00:00", 1), (1, "2024-01-01 00:00:03", 2), (2, "2024-01-01 00:00:00", 3), (2, "2024-01-01 00:00:03.000001", 4)], "sid long, t string, beat_id long").select("sid", F.col("t").cast("timestamp").alias("ts"), "beat_id")
    got = {r.sid: r.n for r in sessions.sessions(beats, "3 SECONDS").groupBy("sid").agg(F.count("*").alias("n")).collect()}
    assert got == {1: 1, 2: 2}
    assert [r.sid for r in sessions.losses(beats, "3 SECONDS", F.lit("2024-01-01 00:00:04").cast("timestamp")).collect()] == [2]
    with pytest.raises(ValueError):
        sessions.check_beat_plan(3, 3)


def test_admission_keeps_numbers(spark):
    names = lambda *n: spark.createDataFrame([(x,) for x in n], "name string")
    first = sessions.admit(None, names("b", "a"))
    assert {r.name: r.sid for r in sessions.admit(first, names("b", "c")).collect()} == {"a": 0, "b": 1, "c": 2}


def test_versions_refuse_a_second_writer(spark, tmp_path):
    store = index.Versions(spark, f"file://{tmp_path}/state")
    assert store.latest() is None
    a = spark.createDataFrame([(1, "x"), (2, "y")], "k long, v string")
    assert store.commit(a, None) == 0 and store.commit(a.withColumn("v", F.lit("z")), 0) == 1
    with pytest.raises(RuntimeError):
        store.commit(a, 0)
    assert store.read().where("v = 'z'").count() == 2 and store.read(0).count() == 2
    assert store.changes(0, 1, "k").count() == 2 and store.compact(1) == 2


def test_two_layouts_agree(spark):
    e = edges_of(spark, [(1, A), (2, A), (2, U)])
    buckets = index.create(spark, "dedupflow_test", "t", 1000)
    index.store(e, "dedupflow_test", "t", buckets)
    by_tag, by_sid = spark.table("dedupflow_test.t_by_tag"), spark.table("dedupflow_test.t_by_sid")
    assert by_tag.count() == 3 and invariants.layouts_agree(by_tag, by_sid).first().different == 0
    assert index.locate(e.where("sid = 1"), claimed(e)).count() == 1
    assert index.slots(e, 16).where("slot < 0 OR slot > 15").count() == 0
    assert index.capacity(10_240) == 16_384
    spark.sql("DROP DATABASE dedupflow_test CASCADE")


def test_private_columns_are_found_by_name_and_by_rows(spark):
    shown = lambda *frames: invariants.private_columns(*frames).first().private_columns
    rows = spark.createDataFrame([(1, "a text", "RUN"), (2, "another", "PARK")], "sid long, note string, op string").withColumn("tag", F.unhex(F.sha2("note", 256)))
    assert shown(rows.drop("note")) == 0 and shown(rows.drop("note").limit(0)) == 0
    assert shown(rows) == 1 and shown(rows, rows.drop("note")) == 1
    assert shown(rows.select("sid", "tag", F.lit(1).alias("mask")), rows) == 2
