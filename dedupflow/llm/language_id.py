"""Language identification: per-language word frequencies first, shorter and shorter character n-grams for unseen words."""

from __future__ import annotations

import re
from array import array
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import sliced

UNKNOWN = "und"
_LETTERS = re.compile(r"[^\W\d_]+")
ORDERS = (5, 4, 3, 2, 1)


def _hashes(keys: list[str]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh3_64_intdigest, keys), np.uint64, len(keys))


def _places(known: np.ndarray, wanted: np.ndarray) -> np.ndarray:
    """Place of each hash among the sorted ones; -1 where it is not one of them."""
    if not len(known):
        return np.full(len(wanted), -1)
    at = np.minimum(np.searchsorted(known, wanted), len(known) - 1)
    return np.where(known[at] == wanted, at, -1)


@dataclass
class LanguageModel:
    """Known words and n-grams as sorted hashes, each with a row of log posteriors per language (uniform prior)."""

    languages: list[str]
    words: np.ndarray
    word_logs: np.ndarray
    grams: np.ndarray
    gram_logs: np.ndarray

    def evidence(self, words: list[str]) -> np.ndarray:
        """A row of log posteriors per word: its own, or the mean over its longest n-grams that are known, or zeros."""
        out = np.zeros((len(words), len(self.languages)))
        at = _places(self.words, _hashes(words))
        out[at >= 0] = self.word_logs[at[at >= 0]]
        left = np.flatnonzero(at < 0)
        marked = [f"^{words[i]}$" for i in left.tolist()]
        for n in ORDERS:
            if not len(left):
                break
            grams = [m[j : j + n] for m in marked for j in range(len(m) - n + 1)]
            owner = np.repeat(np.arange(len(left)), [max(0, len(m) - n + 1) for m in marked])
            at = _places(self.grams, _hashes(grams))
            owner, at = owner[at >= 0], at[at >= 0]
            hits = np.bincount(owner, minlength=len(left))
            sums = np.stack([np.bincount(owner, self.gram_logs[at, l], len(left)) for l in range(out.shape[1])], 1)
            done = hits > 0
            out[left[done]] = sums[done] / hits[done, None]
            left, marked = left[~done], [m for m, d in zip(marked, done) if not d]
        return out


def _posterior(keys: array, counts: array, languages: int, add: float, floor: float) -> tuple[np.ndarray, np.ndarray]:
    """Sorted hashes and their log posteriors from counts per language."""
    n = np.frombuffer(counts, np.int64).reshape(-1, languages) if len(counts) else np.zeros((0, languages))
    logs = np.log(n + add) - np.log(n.sum(0) + add * max(len(n), 1))
    top = logs.max(1, keepdims=True) if len(n) else logs
    logs = np.maximum(floor, logs - top - np.log(np.exp(logs - top).sum(1, keepdims=True)))
    hashes = np.frombuffer(keys, np.uint64) if len(keys) else np.zeros(0, np.uint64)
    order = np.argsort(hashes)
    return hashes[order], logs[order].astype(np.float32)


def train(labelled: DataFrame, rows_per_language: int = 1500, most_languages: int = 500, min_word: int = 4, min_gram: int = 3, add: float = 0.5, floor: float = -6.0) -> LanguageModel:
    """Fits the model on (doc_id, text, lang) rows.

    A bounded classifier whatever the corpus: about ``rows_per_language`` rows at most of each of the ``most_languages``
    languages of most rows, chosen by a hash of the id; of them whole texts and words of any length. Rows with null text
    or lang are not used; without any row, no language is known. Words seen fewer than ``min_word`` times and n-grams
    seen fewer than ``min_gram`` times are left to backoff.
    """
    rows = labelled.select("doc_id", "text", "lang").where(F.col("text").isNotNull() & F.col("lang").isNotNull())
    sizes = dict(map(tuple, rows.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "lang").limit(most_languages).collect()))
    languages = sorted(sizes)
    if not languages:
        none, logs = np.zeros(0, np.uint64), np.zeros((0, 0), np.float32)
        return LanguageModel([], none, logs, none, logs)
    share = F.create_map(*[F.lit(x) for l in languages for x in (l, int(min(1.0, rows_per_language / sizes[l]) * 1_000_000))])
    chosen = rows.where(F.pmod(F.xxhash64(F.lit("language"), "doc_id"), F.lit(1_000_000)) < share[F.col("lang")])

    def count(batches):
        by: dict[str, Counter] = {}
        for b in sliced(batches):
            for text, lang in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                by.setdefault(lang, Counter()).update(_LETTERS.findall(text.lower()))
        for lang, words in by.items():
            grams: Counter = Counter()
            for w, c in words.items():
                marked = f"^{w}$"
                for n in ORDERS:
                    for i in range(len(marked) - n + 1):
                        grams[marked[i : i + n]] += c
            for kind, table in ((0, words), (1, grams)):
                keys = list(table)
                for i in range(0, len(keys), 50_000):
                    part = keys[i : i + 50_000]
                    yield pa.RecordBatch.from_arrays([pa.array([lang] * len(part)), pa.array([kind] * len(part), pa.int32()), pa.array(part), pa.array([table[k] for k in part], pa.int64())], ["lang", "kind", "key", "n"])

    got = chosen.select("text", "lang").mapInArrow(count, "lang string, kind int, key string, n long").groupBy("lang", "kind", "key").agg(F.sum("n").alias("n"))
    total = got.groupBy("kind", "key").agg(F.sum("n").alias("all"), F.map_from_entries(F.collect_list(F.struct("lang", "n"))).alias("by")).where(F.col("all") >= F.when(F.col("kind") == 0, min_word).otherwise(min_gram))
    keys, counts = (array("Q"), array("Q")), (array("q"), array("q"))
    for kind, key, by in total.select("kind", "key", "by").toLocalIterator():  # bounded by the rows chosen
        keys[kind].append(xxhash.xxh3_64_intdigest(key))
        counts[kind].extend(by.get(l, 0) for l in languages)
    return LanguageModel(languages, *_posterior(keys[0], counts[0], len(languages), add, floor), *_posterior(keys[1], counts[1], len(languages), add, floor))


class Labeller:
    """Labels texts one after the other; tokens are remembered as rows of a table, emptied between texts only."""

    def __init__(self, model: LanguageModel, table_bytes: int = 8_000_000, chars: int = 4_000_000):
        self.model, self.width = model, len(model.languages) + 1
        self.cap, self.most, self.chars = table_bytes // (4 * self.width), chars, 0
        self.at: dict[str, int] = {}
        self.table = array("f")

    def _learn(self, tokens: list[str]) -> None:
        found = [_LETTERS.findall(t.lower()) for t in tokens]
        owner = np.repeat(np.arange(len(tokens)), [len(f) for f in found])
        own = self.model.evidence([w for f in found for w in f])
        rows = np.stack([*(np.bincount(owner, own[:, l], len(tokens)) for l in range(own.shape[1])), np.bincount(owner, minlength=len(tokens))], 1)
        self.table.frombytes(rows.astype(np.float32).tobytes())
        for t in tokens:
            self.chars += len(t)
            self.at[t] = len(self.at)

    def label(self, text: str | None) -> tuple[str, float]:
        tokens = (text or "").split()
        if not tokens or self.width == 1:
            return UNKNOWN, 0.0
        if len(self.at) > self.cap or self.chars > self.most:
            self.at, self.table, self.chars = {}, array("f"), 0
        if fresh := [t for t in dict.fromkeys(tokens) if t not in self.at]:
            self._learn(fresh)
        at = np.fromiter(map(self.at.__getitem__, tokens), np.int64, len(tokens))
        table = np.frombuffer(self.table, np.float32).reshape(-1, self.width)
        sums = sum((table[at[i : i + 100_000]].sum(0, dtype=np.float64) for i in range(0, len(at), 100_000)), np.zeros(self.width))
        words = sums[-1]
        if not words:
            return UNKNOWN, 0.0
        mean = sums[:-1] / words * min(words, 20)
        p = np.exp(mean - mean.max())
        return self.model.languages[int(p.argmax())], float(p.max() / p.sum())


def predict(docs: DataFrame, model: LanguageModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, lang_pred, score) for every row, from its whole text alone.

    Null texts and texts without a letter give ``und`` and score 0; so does every text if the model knows no language.
    The score is the posterior of the predicted language, its evidence counted for twenty words at most, so that long
    texts do not all reach 1. Ties go to the language first in the alphabet. Repeated rows each give a row, other
    columns are not read, whatever their names.
    """
    sent = docs.sparkSession.sparkContext.broadcast(model)  # bounded by rows_per_language

    def label(batches):
        own = Labeller(sent.value)
        for b in sliced(batches):
            made = [own.label(t) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([l for l, _ in made], pa.string()), pa.array([p for _, p in made], pa.float64())], ["doc_id", "lang_pred", "score"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(label, "doc_id long, lang_pred string, score double")


def accepted(docs: DataFrame, model: LanguageModel, least_score: float = 0.35) -> DataFrame:
    """The rows of ``docs`` whose text is of a known language with ``least_score`` or more, with all their columns.

    Null texts and texts without a letter go.
    """
    sent = docs.sparkSession.sparkContext.broadcast(model)  # bounded by rows_per_language

    def keep(batches):
        own = Labeller(sent.value)
        for b in sliced(batches):
            made = [own.label(t) for t in b.column("text").to_pylist()]
            yield b.filter(pa.array([l != UNKNOWN and p >= least_score for l, p in made], pa.bool_()))

    return docs.mapInArrow(keep, docs.schema)
