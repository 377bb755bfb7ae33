"""Local training surrogates and the weighted average of their models; the networks themselves are out of scope."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def fedavg(local: DataFrame, weights: DataFrame) -> DataFrame:
    """(dim, w): average over clients of the models (sid, w array<double>), weighted by ``weights`` (sid, m).

    With the committed counts as weights each record counts once, whoever trained it; with the counts of all local
    records it is the standard average.
    """
    parts = local.select("sid", "w").join(F.broadcast(weights.select("sid", "m")), "sid").select("m", F.posexplode("w").alias("dim", "v"))
    return parts.groupBy("dim").agg((F.sum(F.col("v") * F.col("m")) / F.sum("m")).alias("w"))


def static_weights(edges: DataFrame) -> DataFrame:
    """(sid, m): all records that a client has, parked or not."""
    return edges.groupBy("sid").agg(F.count(F.lit(1)).alias("m"))


def weighted_mean(w, m):
    """Grouped aggregate column: the weighted mean of a group's vectors ``w`` with weights ``m``; for groups of one vector per client."""

    @F.pandas_udf("array<double>")
    def mean(w: pd.Series, m: pd.Series) -> list:
        total = float(m.sum())
        out = (np.stack(w.to_numpy()) * m.to_numpy(float)[:, None]).sum(0)
        return (out / total if total else out).tolist()

    return mean(w, m)


def centroid(items: DataFrame) -> DataFrame:
    """(sid, m, w): each client's mean vector of its items (sid, embedding)."""
    parts = items.select("sid", F.posexplode("embedding").alias("dim", "v")).groupBy("sid", "dim").agg(F.avg(F.col("v").cast("double")).alias("v"), F.count(F.lit(1)).alias("m"))
    packed = parts.groupBy("sid").agg(F.max("m").alias("m"), F.array_sort(F.collect_list(F.struct("dim", "v"))).alias("p"))
    return packed.select("sid", "m", F.col("p.v").alias("w"))


def softmax_regression(items: DataFrame, classes: int, dim: int, epochs: int = 20, rate: float = 0.5, start: list[float] | None = None) -> DataFrame:
    """(sid, m, w): a softmax regression per client of (sid, embedding, label), by batches of the client's rows.

    A client's rows are what one real device holds; here they are one group, as the device's own trainer would see them.
    """

    def fit(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        x = np.stack(pdf["embedding"].to_numpy()).astype(float)
        y = np.eye(classes)[pdf["label"].to_numpy(int) % classes]
        w = np.zeros((dim, classes)) if start is None else np.array(start).reshape(dim, classes).copy()
        for _ in range(epochs):
            z = x @ w
            p = np.exp(z - z.max(1, keepdims=True))
            p /= p.sum(1, keepdims=True)
            w -= rate * x.T @ (p - y) / len(x)
        return pd.DataFrame({"sid": [key[0]], "m": [len(x)], "w": [w.ravel().tolist()]})

    return items.groupBy("sid").applyInPandas(fit, "sid long, m long, w array<double>")


#: Characters of a client's texts that are counted at a time, and code points whose pairs are counted by position.
PIECE, NEAR = 1 << 20, 256


def _pairs(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(table, rest): pairs of characters within the texts, as counts by position for code points below NEAR, and one number per other pair."""
    codes = np.frombuffer("".join(texts).encode("utf-32-le"), np.uint32)
    within = np.ones(max(len(codes) - 1, 0), bool)
    within[np.cumsum([len(t) for t in texts])[:-1] - 1] = False  # from the end of a text to the next one
    left, right = codes[:-1][within].astype(np.int64), codes[1:][within].astype(np.int64)
    near = (left < NEAR) & (right < NEAR)
    return np.bincount(left[near] * NEAR + right[near], minlength=NEAR * NEAR), (left << 21 | right)[~near]


def bigram_counts(items: DataFrame) -> DataFrame:
    """(sid, bigram, n): letter bigrams of each client's texts (sid, content): an additive text model.

    A text of one letter counts as that letter, the empty text as the empty bigram. Tasks count before anything is
    sent. Null contents give none.
    """

    def count(batches):
        tables, others, open_, size = {}, {}, {}, {}

        def close(sid):
            table, rest = _pairs(open_.pop(sid, []))
            size.pop(sid, None)
            tables[sid] = tables[sid] + table if sid in tables else table
            own = others.setdefault(sid, {})
            for key, n in zip(*(x.tolist() for x in np.unique(rest, return_counts=True))):
                word = chr(key >> 21) + chr(key & 0x1FFFFF)
                own[word] = own.get(word, 0) + n

        def counted():
            for sid in list(open_):
                close(sid)
            for sid in {**tables, **others}:
                at = np.flatnonzero(tables[sid]) if sid in tables else np.zeros(0, np.int64)
                words = [chr(i // NEAR) + chr(i % NEAR) for i in at.tolist()] + list(others.get(sid, {}))
                n = [*(tables[sid][at].tolist() if sid in tables else ()), *others.get(sid, {}).values()]
                yield pa.RecordBatch.from_arrays([pa.array([sid] * len(words), pa.int64()), pa.array(words, pa.string()), pa.array(n, pa.int64())], ["sid", "bigram", "n"])
            tables.clear(), others.clear()

        for b in batches:
            for i, sid in enumerate(b.column(0).to_pylist()):
                text = b.column(1)[i].as_py()
                if text is None:
                    continue
                if len(text) < 2:
                    own = others.setdefault(sid, {})
                    own[text] = own.get(text, 0) + 1
                for at in range(0, len(text) - 1, PIECE):  # pieces overlap by a letter
                    open_.setdefault(sid, []).append(text[at : at + PIECE + 1])
                    size[sid] = size.get(sid, 0) + len(open_[sid][-1])
                    if size[sid] >= PIECE:
                        close(sid)
                if len(open_) + len(tables) > 100 or sum(map(len, others.values())) > 500_000:
                    yield from counted()
        yield from counted()

    pairs = items.select(F.col("sid").cast("long").alias("sid"), "content").mapInArrow(count, "sid long, bigram string, n long")
    return pairs.groupBy("sid", "bigram").agg(F.sum("n").alias("n"))


def held_out_loss(items: DataFrame, w: list[float], classes: int) -> DataFrame:
    """(n, loss): mean cross-entropy of a softmax regression on held-out rows (embedding, label)."""

    @F.pandas_udf("double")
    def loss(embedding: pd.Series, label: pd.Series) -> pd.Series:
        x = np.stack(embedding.to_numpy()).astype(float)
        z = x @ np.array(w).reshape(x.shape[1], classes)
        z -= z.max(1, keepdims=True)
        return pd.Series(np.log(np.exp(z).sum(1)) - z[np.arange(len(z)), label.to_numpy(int) % classes])

    return items.select(loss("embedding", "label").alias("l")).agg(F.count(F.lit(1)).alias("n"), F.avg("l").alias("loss"))
