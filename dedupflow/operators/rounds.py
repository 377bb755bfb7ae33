"""Rounds: uploads and commits, the barrier before aggregation, reset and retention."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.storage import written
from . import claims, index, recovery, scheduling
from .index import DONE, FREE, HELD


def _valid(state: DataFrame, uploads: DataFrame) -> DataFrame:
    held = state.where(F.col("state") == HELD).select("tag", F.col("holder").alias("sid"), "epoch")
    return uploads.join(held, ["tag", "sid", "epoch"], "left_semi")


def commit(state: DataFrame, uploads: DataFrame) -> DataFrame:
    """States after uploads (sid, tag, epoch): done where the uploader holds the tag in the epoch of its claim."""
    ok = _valid(state, uploads).select("tag", F.lit(True).alias("up")).distinct()
    out = state.join(ok, "tag", "left")
    return out.select("tag", F.when(F.coalesce("up", F.lit(False)), DONE).otherwise(F.col("state")).alias("state"), "holder", "last_holder", "epoch", "n_owners")


def rejected(state: DataFrame, uploads: DataFrame) -> DataFrame:
    """Uploads without that right: of lost clients, stale epochs, or tags of others."""
    held = state.where(F.col("state") == HELD).select("tag", F.col("holder").alias("sid"), "epoch")
    return uploads.join(held, ["tag", "sid", "epoch"], "left_anti")


def ready(state: DataFrame, edges: DataFrame | None = None, online: DataFrame | None = None, strict: bool = True) -> bool:
    """Whether the round may be aggregated: nothing is held and, if strict, no free tag has an online owner who has yet to take it."""
    if state.where(F.col("state") == HELD).limit(1).count():
        return False
    if not strict or edges is None or online is None:
        return True
    free = state.where(F.col("state") == FREE).select("tag")
    return not edges.join(F.broadcast(online.select("sid")), "sid", "left_semi").join(free, "tag", "left_semi").limit(1).count()


def weights(state: DataFrame) -> DataFrame:
    """(sid, m): records that each client has really committed this round."""
    return state.where(F.col("state") == DONE).groupBy(F.col("holder").alias("sid")).agg(F.count(F.lit(1)).alias("m"))


def reset(state: DataFrame) -> DataFrame:
    """Next round: everything free, owners kept, the last trainer remembered. A projection without a shuffle."""
    done = (F.col("state") == DONE).cast("int")
    return state.select("tag", F.lit(FREE).alias("state"), F.lit(None).cast("long").alias("holder"), F.coalesce("holder", "last_holder").alias("last_holder"), (F.col("epoch") + done).alias("epoch"), "n_owners")


def retain(state: DataFrame, beats: DataFrame) -> DataFrame:
    """States after the first beats of a round: who trained a tag last holds it again, without contention.

    The right is delivered with a beat, so a client that has not beaten holds nothing yet.
    """
    alive = F.broadcast(beats.select(F.col("sid").alias("last_holder"), F.lit(True).alias("beat")).distinct())  # N clients
    out = state.join(alive, "last_holder", "left")
    back = F.coalesce("beat", F.lit(False)) & (F.col("state") == FREE)
    return out.select("tag", F.when(back, HELD).otherwise(F.col("state")).alias("state"), F.when(back, F.col("last_holder")).otherwise(F.col("holder")).alias("holder"), "last_holder", "epoch", "n_owners")


def hold(state: DataFrame, assignment: DataFrame) -> DataFrame:
    """States after the delivery of an assignment (tag, sid) to online clients."""
    out = state.join(assignment.select("tag", F.col("sid").alias("to")), "tag", "left")
    got = F.col("to").isNotNull() & (F.col("state") == FREE)
    return out.select("tag", F.when(got, HELD).otherwise(F.col("state")).alias("state"), F.when(got, F.col("to")).otherwise(F.col("holder")).alias("holder"), "last_holder", "epoch", "n_owners")


@dataclass
class Round:
    """What a round leaves: its number, states after training, allocation, takeovers so far, committed records per client, and whether it may be aggregated."""

    number: int
    state: DataFrame
    assignment: DataFrame
    log: DataFrame
    weights: DataFrame
    ready: bool


def run(edges: DataFrame, losses: dict[int, tuple[int, ...]], n_rounds: int, newcomers: dict[int, DataFrame] | None = None, use_history: bool = True, lost_at: int = 30_000, train=None):
    """Rounds one after the other, as a generator of ``Round``.

    The first round is claimed in order of arrival, the others are allocated by history. In each the clients that
    ``losses`` names go away at ``lost_at``; what they hold is released, taken over by other owners and logged; who
    trains then uploads. Clients lost in a round are back in the next, at risk for one round. ``newcomers`` are edges
    that join before a round. ``train`` (weights, state) is called when the barrier lets the round be aggregated. States
    between phases are tables in the shared folder.
    """
    spark, state, log, risk = edges.sparkSession, None, None, ()
    sids = lambda s: spark.createDataFrame([(int(x),) for x in s], "sid long")
    for number in range(1, n_rounds + 1):
        joining = (newcomers or {}).get(number)
        if joining is not None:
            state = state if state is None else index.append_state(index.add_owners(state, edges, joining), joining)
            edges = written(index.append_edges(edges, joining), "edges")
        clients = edges.select("sid").distinct()
        if state is None:
            state = claims.claim(index.append_state(None, edges), claims.requests_of(edges))
            assignment = state.select("tag", F.col("holder").alias("sid"), F.lit(scheduling.NEW).alias("how"))
        else:
            state = written(reset(state), "round")
            assignment = written(scheduling.assign(state, edges, sids(risk), clients, use_history=use_history), "assignment")
            state = hold(state, assignment)
        state = written(state, "round")
        lost = losses.get(number, ())
        online = clients.where(~F.col("sid").isin(*lost)) if lost else clients
        if lost:
            released = written(recovery.release(state, edges, sids(lost)), "released")
            taken = written(recovery.takeover(released, edges, recovery.contacts_after(online, lost_at)), "taken")
            state = written(recovery.apply_takeover(recovery.apply_release(state, released), taken), "round")
            rows = recovery.log(taken, F.lit(lost_at), number)
            log = rows if log is None else log.unionByName(rows)
        uploads = state.where(F.col("state") == HELD).select("tag", F.col("holder").alias("sid"), "epoch")
        state = written(commit(state, uploads), "round")
        done = ready(state, edges, online)
        committed = weights(state)
        if done and train is not None:
            train(committed, state)
        yield Round(number, state, assignment, log, committed, done)
        risk = lost
