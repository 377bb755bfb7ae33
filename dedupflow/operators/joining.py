"""Clients that join a running round: an append, without work for anybody else."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import claims, index, queues


def join_clients(state: DataFrame, edges: DataFrame, new_edges: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(next state, next edges, replies to newcomers). Entries that exist are refused early; only unseen tags are won."""
    after_edges = index.append_edges(edges, new_edges)
    created = index.append_state(index.add_owners(state, edges, new_edges), new_edges)
    after = claims.claim(created, claims.requests_of(new_edges))
    return after, after_edges, queues.reply(new_edges, after)


def touched_rows(before: DataFrame, after: DataFrame) -> DataFrame:
    """(changed): entries of the old state whose holder, state or epoch differ after a join; none should."""
    was = before.select("tag", F.struct("state", "holder", "epoch").alias("was"))
    now = after.select("tag", F.struct("state", "holder", "epoch").alias("now"))
    return was.join(now, "tag", "left").agg(F.count(F.when(~F.col("was").eqNullSafe(F.col("now")), 1)).alias("changed"))
