"""Reference semantics: one tag's events folded in order, to hold the relational operators against. For tests and small logs."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .index import DONE, FREE, HELD

#: Order of events within one instant: revocation before late uploads, then claims, then beats.
ORDER = {"LOST": 0, "UPLOAD": 1, "SUBMIT": 2, "REJOIN": 2, "BEAT": 3, "ROUND": 4}


def expand(log: DataFrame, edges: DataFrame) -> DataFrame:
    """The log per tag: events of a client as a whole (LOST, BEAT) reach every tag that it owns, rounds every tag."""
    tagged = log.where("tag IS NOT NULL")
    wide = log.where("tag IS NULL AND kind <> 'ROUND'").drop("tag").join(edges.select("sid", "tag"), "sid")
    rounds = log.where("kind = 'ROUND'").drop("tag").join(edges.select("tag").distinct())  # few rows: rounds of a test log
    cols = ["ts", "seq", "kind", "sid", "tag", "epoch"]
    return tagged.select(*cols).unionByName(wide.select(*cols)).unionByName(rounds.select(*cols))


class Entry:
    """State of one tag."""

    def __init__(self):
        self.state, self.holder, self.last, self.epoch = FREE, None, None, 0
        self.owners: set[int] = set()
        self.freed_from: int | None = None

    def apply(self, kind: str, sid: int | None, epoch: int | None) -> str | None:
        """Applies an event; returns the reply, if there is one."""
        if kind in ("SUBMIT", "REJOIN"):
            self.owners.add(sid)
            if self.state == FREE:
                self.state, self.holder = HELD, sid
                return "RUN"
            return "RUN" if self.state == HELD and self.holder == sid else "PARK"
        if kind == "BEAT":
            if self.state == FREE and self.freed_from is not None and sid in self.owners and sid != self.freed_from:
                self.state, self.holder, self.freed_from = HELD, sid, None
                return "RUN"
            if self.state == FREE and self.freed_from is None and self.last is not None:
                if sid == self.last:
                    self.state, self.holder = HELD, sid
                    return "RUN"
                return "PARK"
            return None
        if kind == "LOST":
            if self.state == HELD and self.holder == sid:
                self.state, self.holder, self.freed_from = FREE, None, sid
                self.epoch += 1
            return None
        if kind == "UPLOAD":
            if self.state == HELD and self.holder == sid and (epoch is None or epoch == self.epoch):
                self.state = DONE
                return "OK"
            return "REJECT"
        if kind == "ROUND" and self.state == DONE:
            self.last, self.state, self.holder, self.freed_from = self.holder, FREE, None, None
            self.epoch += 1
        return None


def fold(events: DataFrame) -> DataFrame:
    """(tag, state, holder, last_holder, epoch) after all events of every tag."""

    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.assign(o=pdf["kind"].map(ORDER)).sort_values(["ts", "o", "seq", "sid"], na_position="first")
        e = Entry()
        for kind, sid, epoch in zip(pdf["kind"], pdf["sid"], pdf["epoch"]):
            e.apply(kind, None if pd.isna(sid) else int(sid), None if pd.isna(epoch) else int(epoch))
        return pd.DataFrame({"tag": [key[0]], "state": [e.state], "holder": pd.array([e.holder], "Int64"), "last_holder": pd.array([e.last], "Int64"), "epoch": [e.epoch]})

    return events.groupBy("tag").applyInPandas(run, "tag binary, state int, holder long, last_holder long, epoch int")


def submissions(edges: DataFrame, sent) -> DataFrame:
    """SUBMIT events of edges."""
    return edges.select(sent.cast("long").alias("ts"), F.col("item_id").alias("seq"), F.lit("SUBMIT").alias("kind"), "sid", "tag", F.lit(None).cast("int").alias("epoch"))
