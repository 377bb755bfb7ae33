"""One deterministic course of events over the documents' clients that passes through every kind of recovery.

Times are virtual milliseconds. Clients submit at their arrival. At 25,000 client 13 uploads all it holds. At 30,000
clients 0 and 18 are declared lost, and online owners take over what they can in the second after. At 35,000 client 13
is lost too: what it has done stays, what it took over is released again. At 40,000 all holders upload, and 0 and 18
try to. At 50,000 client 0 is back. At 70,000 the round ends, and the next is allocated with 0, 13 and 18 at risk and
18 away.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import sources
from ..functions.storage import written
from ..operators import claims, index, recovery, rounds, scheduling, tags
from ..operators.index import HELD

FIRST_LOST, SECOND_LOST, RETURNS, AWAY = (0, 18), 13, 0, 18


@dataclass
class Course:
    """Frames of the course: edges, states after each step, and what the steps produced."""

    edges: DataFrame
    claimed: DataFrame
    released: DataFrame
    taken: DataFrame
    after_takeover: DataFrame
    cascade: DataFrame
    cascade_taken: DataFrame
    after_cascade: DataFrame
    stale: DataFrame
    accepted: DataFrame
    uploaded: DataFrame
    rejoin_replies: DataFrame
    ended: DataFrame
    risk: DataFrame
    online: DataFrame


def _sids(spark: SparkSession, sids) -> DataFrame:
    return spark.createDataFrame([(int(s),) for s in sids], "sid long")


def edges_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Owner edges of the documents' clients, with plain tags."""
    return tags.protect(sources.documents(spark, sf_dir)).drop("copies")


def uploads_of(state: DataFrame) -> DataFrame:
    """(tag, sid, epoch): an upload of everything held."""
    return state.where(F.col("state") == HELD).select("tag", F.col("holder").alias("sid"), "epoch")


def run(spark: SparkSession, sf_dir: str) -> Course:
    """The whole course; states between phases are written, as rounds of a real job are."""
    edges = written(edges_of(spark, sf_dir), "edges")
    clients = edges.select("sid").distinct()
    state = written(claims.claim(index.append_state(None, edges), claims.requests_of(edges)), "claimed")
    early = uploads_of(state).where(F.col("sid") == SECOND_LOST)
    stale_rights = uploads_of(state).where(F.col("sid").isin(*FIRST_LOST))
    done13 = written(rounds.commit(state, early), "state")

    lost = _sids(spark, FIRST_LOST)
    online = clients.join(F.broadcast(lost), "sid", "left_anti")
    released = written(recovery.release(done13, edges, lost), "released")
    taken = written(recovery.takeover(released, edges, recovery.contacts_after(online, 30_000)), "taken")
    after_takeover = written(recovery.apply_takeover(recovery.apply_release(done13, released), taken), "state")

    lost2 = _sids(spark, (SECOND_LOST,))
    online2 = online.where(F.col("sid") != SECOND_LOST)
    cascade = written(recovery.release(after_takeover, edges, lost2), "released")
    cascade_taken = written(recovery.takeover(cascade, edges, recovery.contacts_after(online2, 35_000)), "taken")
    after_cascade = written(recovery.apply_takeover(recovery.apply_release(after_takeover, cascade), cascade_taken), "state")

    offered = uploads_of(after_cascade).unionByName(stale_rights)
    stale = rounds.rejected(after_cascade, offered)
    accepted = offered.join(stale, ["tag", "sid", "epoch"], "left_anti")
    uploaded = written(rounds.commit(after_cascade, offered), "state")

    regained, replies = recovery.rejoin_training(uploaded, edges, RETURNS)
    regained = written(regained, "state")
    ended = written(rounds.commit(regained, uploads_of(regained)), "state")
    risk = _sids(spark, (*FIRST_LOST, SECOND_LOST))
    return Course(edges, state, released, taken, after_takeover, cascade, cascade_taken, after_cascade, stale, accepted, uploaded, replies, ended, risk, clients.where(F.col("sid") != AWAY))


def next_round(c: Course, use_history: bool = True, pick: str = "rendezvous") -> DataFrame:
    """(tag, sid, how) of the second round."""
    return scheduling.assign(rounds.reset(c.ended), c.edges, c.risk, c.online, pick, use_history)
