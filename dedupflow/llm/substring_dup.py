"""Repeated passages: suffix automata of reference contexts, over which documents stream for matching statistics.

Every window of ``width`` words is anchored at the k-word gram of smallest hash in it, so equal windows have equal
anchors and about one word in seven is one. Anchors that occur once rule their windows out. The windows of an
occurrence that share its anchor form a context; a context that has occurred before is repeated as a whole. Contexts
that differ but share an anchor are a reference shard: in order of occurrence each streams over the shard's automaton,
which gives the longest match ending at every word, and then enters it. A window is repeated where the match is at
least as long as the window. An anchor with too many contexts for a task is resolved window by window instead, summed
before the shuffle. Nothing is cut off: every window of every document is judged.
"""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import discard, mixed, sliced, small_side, window_hashes, word_hashes, written

GRAM = 8
#: Contexts of one anchor that one automaton takes.
SHARD = 4096
#: A context of more than HOT_ROWS occurrences that holds over one in HOT_SHARE of all is hot; so there are fewer than HOT_SHARE.
HOT_ROWS, HOT_SHARE = 10_000, 1000
#: Places are packed: the number of the text among those of its id above PLACE bits, the word's place below.
PLACE = 36
_PLACE = (1 << PLACE) - 1


class SuffixAutomaton:
    """Automaton of all substrings of the sequences added (integers), grown one symbol at a time."""

    def __init__(self):
        self.next: list[dict[int, int]] = [{}]
        self.link, self.length = [-1], [0]

    def add(self, sequence) -> None:
        """Adds a sequence; it shares no substring with the one before across their border."""
        nxt, link, length = self.next, self.link, self.length
        last = 0
        for c in sequence:
            q = nxt[last].get(c)
            if q is not None:
                if length[q] == length[last] + 1:
                    last = q
                    continue
                last = self._split(last, c, q)
                continue
            cur = len(nxt)
            nxt.append({})
            link.append(0)
            length.append(length[last] + 1)
            p = last
            while p != -1 and c not in nxt[p]:
                nxt[p][c] = cur
                p = link[p]
            if p != -1:
                q = nxt[p][c]
                link[cur] = q if length[q] == length[p] + 1 else self._split(p, c, q)
            last = cur

    def _split(self, p: int, c: int, q: int) -> int:
        copy = len(self.next)
        self.next.append(dict(self.next[q]))
        self.link.append(self.link[q])
        self.length.append(self.length[p] + 1)
        self.link[q] = copy
        while p != -1 and self.next[p].get(c) == q:
            self.next[p][c] = copy
            p = self.link[p]
        return copy

    def statistics(self, sequence) -> list[int]:
        """Per position the length of the longest substring ending there that was added."""
        nxt, link, length = self.next, self.link, self.length
        state, now, out = 0, 0, []
        for c in sequence:
            while state and c not in nxt[state]:
                state = link[state]
                now = length[state]
            to = nxt[state].get(c)
            if to is None:
                now = 0
            else:
                state, now = to, now + 1
            out.append(now)
        return out


def words_of(text: str | None) -> list[bytes]:
    """What ASCII white space separates, unchanged, as UTF-8."""
    return (text or "").encode("utf-8", "surrogatepass").split()


def anchors_of(h: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the grams, and the anchor position of every window (never decreasing)."""
    grams = window_hashes(h, GRAM)
    span = width - GRAM + 1
    if len(grams) < span:
        return grams, np.empty(0, np.int64)
    return grams, np.lib.stride_tricks.sliding_window_view(grams, span).argmin(1) + np.arange(len(grams) - span + 1)


_BASE = 0xD6E8FEB86659FD93
_powers = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _power(n: int) -> list[np.ndarray]:
    if len(_powers[0]) < n:
        for i, base in enumerate((_BASE, pow(_BASE, -1, 1 << 64))):
            steps = np.full(max(n, 2 * len(_powers[0])), base, np.uint64)
            steps[0] = 1
            _powers[i] = np.multiply.accumulate(steps)
    return _powers


def span_hashes(h: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Hash of the words from each start to each end."""
    up, down = _power(len(h) + 1)
    sums = np.concatenate((np.zeros(1, np.uint64), np.cumsum(h * up[: len(h)], dtype=np.uint64)))
    return mixed((sums[end] - sums[start]) * down[start] + (end - start).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))


def contexts(words: list[bytes], width: int):
    """Per anchor: position, first and last window start that it anchors, hash, hash of the context, hashes of the words."""
    h = word_hashes(words)
    grams, mins = anchors_of(h, width)
    at, low = np.unique(mins, return_index=True)
    high = np.append(low[1:], len(mins))[: len(at)] - 1
    return at, low, high, grams[at], mixed(span_hashes(h, low, high + width) + (at - low).astype(np.uint64)) if len(at) else grams[:0], h


def _free_prefix(taken) -> str:
    """A prefix that no column has."""
    prefix = "own"
    while any(t.lower().startswith(prefix) for t in taken):
        prefix = "_" + prefix
    return prefix


def _numbered(docs: DataFrame, sub: str = "sub") -> DataFrame:
    """``docs`` with ``sub``: 0, or the number of the text among the different texts that rows of its id have, in order of their digests."""
    rows = docs.where(F.col("doc_id").isNotNull() & F.col("text").isNotNull()).select("doc_id", F.md5("text").alias("digest"))
    several = written(rows.groupBy("doc_id").agg(F.min("digest").alias("a"), F.max("digest").alias("b")).where("a <> b").select("doc_id"), "several-texts")
    n = several.count()
    if not n:
        return docs.withColumn(sub, F.lit(0).cast("long"))
    texts = rows.join(small_side(several, n), "doc_id", "left_semi").distinct()
    order, p = Window.partitionBy("doc_id").orderBy("digest"), _free_prefix(docs.columns)
    numbers = written(texts.select(F.col("doc_id").alias(f"{p}_id"), F.col("digest").alias(f"{p}_digest"), (F.row_number().over(order) - 1).cast("long").alias(f"{p}_number")), "text-numbers")
    joined = docs.join(numbers, (F.col("doc_id") == F.col(f"{p}_id")) & (F.md5("text") == F.col(f"{p}_digest")), "left")
    return joined.select(*docs.columns, F.coalesce(f"{p}_number", F.lit(0)).cast("long").alias(sub))


def _anchors(docs: DataFrame, width: int) -> DataFrame:
    def emit(batches):
        for b in sliced(batches):
            parts, size = [], 0
            for doc, text, sub in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist()):
                words = words_of(text)
                if len(words) < width:
                    continue
                at, _, _, hashes, ctx, _ = contexts(words, width)
                parts.append((hashes.view(np.int64), ctx.view(np.int64), np.full(len(at), doc, np.int64), at + (sub << PLACE)))
                size += len(at)
                if size > 100_000:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*parts)], ["h", "ctx", "doc", "pos"])
                    parts, size = [], 0
            if parts:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*parts)], ["h", "ctx", "doc", "pos"])

    return docs.select("doc_id", "text", "sub").mapInArrow(emit, "h long, ctx long, doc long, pos long")


def _with_positions(docs: DataFrame, positions: DataFrame, how: str, sub: str = "sub", spots: str = "spots") -> DataFrame:
    """Documents with their ``spots``. The texts are shuffled by id and number at every size; a text's spots are bounded by its words."""
    place = F.coalesce(F.col("spot.pos"), F.col("spot.low")) if "low" in positions.schema["spot"].dataType.names else F.col("spot.pos")
    p = _free_prefix([*docs.columns, spots])
    packed = positions.groupBy(F.col("doc").alias(f"{p}_id"), F.shiftright(place, PLACE).alias(f"{p}_number")).agg(F.collect_list("spot").alias(spots))
    joined = docs.join(packed, (F.col("doc_id") == F.col(f"{p}_id")) & (F.col(sub) == F.col(f"{p}_number")), how)
    return joined.select(*docs.columns, spots)


def _texts_of(docs: DataFrame, firsts: DataFrame, width: int) -> DataFrame:
    """(h, doc, low, words, many) of the contexts (h, doc, pos, many): window starts and word hashes from the texts."""
    spots = firsts.select("doc", F.struct("pos", "many").alias("spot"))
    joined = _with_positions(docs, spots, "inner").select("doc_id", "text", "sub", F.col("spots.pos").alias("pos"), F.col("spots.many").alias("many"))

    def cut(batches):
        for b in sliced(batches):
            rows, size = [], 0
            for doc, text, sub, pos, many in zip(*(c.to_pylist() for c in b.columns)):
                words = words_of(text)
                if len(words) < width:
                    continue
                at, low, high, hashes, _, h = contexts(words, width)
                short = (h >> np.uint64(16)).astype(np.uint32)
                pos = np.array(pos, np.int64) & _PLACE
                where = np.searchsorted(at, pos)
                for i, p, m in zip(where.tolist(), pos.tolist(), many):
                    if i < len(at) and at[i] == p:
                        part = short[low[i] : high[i] + width]
                        rows.append((int(hashes[i].view(np.int64)), doc, int(low[i]) + (sub << PLACE), part.tobytes(), m))
                if len(rows) > 20_000:
                    yield _cuts(rows)
                    rows = []
            yield _cuts(rows)

    return joined.mapInArrow(cut, "h long, doc long, low long, words binary, many boolean")


def _cuts(rows: list[tuple]) -> pa.RecordBatch:
    cols = list(zip(*rows)) or [()] * 5
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.bool_()))], ["h", "doc", "low", "words", "many"])


def _by_automata(cuts: DataFrame, width: int) -> DataFrame:
    """(doc, low, high): runs of repeated window starts, from a shard's automaton; rows of a shard come in order of occurrence."""

    def stream(batches):
        key, automaton, doc_out, low_out, high_out = None, None, [], [], []
        for b in batches:
            for h, doc, low, blob in zip(*(b.column(i).to_pylist() for i in range(4))):
                if h != key:
                    key, automaton = h, SuffixAutomaton()
                own = np.frombuffer(blob, np.uint32).tolist()
                reach = automaton.statistics(own)
                start = None
                for i, n in enumerate(reach[width - 1 :] + [0]):
                    if n >= width and start is None:
                        start = i
                    elif n < width and start is not None:
                        doc_out.append(doc)
                        low_out.append(low + start)
                        high_out.append(low + i - 1)
                        start = None
                automaton.add(own)
            if len(doc_out) > 20_000:
                yield pa.RecordBatch.from_arrays([pa.array(doc_out, pa.int64()), pa.array(low_out, pa.int64()), pa.array(high_out, pa.int64())], ["doc", "low", "high"])
                doc_out, low_out, high_out = [], [], []
        yield pa.RecordBatch.from_arrays([pa.array(doc_out, pa.int64()), pa.array(low_out, pa.int64()), pa.array(high_out, pa.int64())], ["doc", "low", "high"])

    return cuts.select("h", "doc", "low", "words").repartition("h").sortWithinPartitions("h", "doc", "low").mapInArrow(stream, "doc long, low long, high long")


def _by_windows(cuts: DataFrame, width: int) -> DataFrame:
    """The same for anchors with very many contexts: windows are named by hash, and the first of each name stays."""

    def explode(batches):
        for b in batches:
            for h, doc, low, blob in zip(*(b.column(i).to_pylist() for i in range(4))):
                own = window_hashes(mixed(np.frombuffer(blob, np.uint32).astype(np.uint64) + np.uint64(1)), width)
                n = len(own)
                yield pa.RecordBatch.from_arrays([pa.array([h] * n, pa.int64()), pa.array(own.view(np.int64)), pa.array([doc] * n, pa.int64()), pa.array(np.arange(low, low + n))], ["h", "name", "doc", "low"])

    windows = written(cuts.select("h", "doc", "low", "words").mapInArrow(explode, "h long, name long, doc long, low long"), "windows")
    # written, so that the join deals both sides anew and can split a window that very many contexts share
    first = written(windows.groupBy("h", "name").agg(F.min(F.struct("doc", "low")).alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1").select("h", "name", "first"), "first-windows")
    again = windows.join(first, ["h", "name"]).where(F.struct("doc", "low") > F.col("first"))
    return again.select("doc", "low", F.col("low").alias("high"))


def _later(shared: DataFrame, first: DataFrame) -> DataFrame:
    """(doc, pos) of the occurrences of every context (h, ctx, first, n) but its first. Hot contexts, bounded in number, are sent to the rows instead."""
    limit, key, wanted = max(HOT_ROWS, shared.count() // HOT_SHARE), ["h", "ctx"], F.struct("doc", "pos") > F.col("first")
    hot = written(first.where(F.col("n") > limit).select("h", "ctx", "first"), "hot-contexts")
    if not hot.limit(1).count():
        return shared.join(first.select("h", "ctx", "first"), key).where(wanted).select("doc", "pos")
    sent = F.broadcast(hot)
    others = shared.join(sent, key, "left_anti").join(first.where(F.col("n") <= limit).select("h", "ctx", "first"), key)
    return others.where(wanted).select("doc", "pos").union(shared.join(sent, key).where(wanted).select("doc", "pos"))


def repeated(docs: DataFrame, width: int = 20) -> DataFrame:
    """(doc, pos, low, high) of rows (doc_id, text, sub): anchors all of whose windows are repeated (pos), or runs of repeated window starts (low to high)."""
    anchors = written(_anchors(docs.where(F.col("doc_id").isNotNull()), width), "anchors")
    # written, so that the join deals both sides anew and can split an anchor that very many rows share
    twice = written(anchors.groupBy("h").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("h"), "repeated-anchors")
    shared = written(anchors.join(twice, "h"), "shared-anchors")
    discard(anchors)
    first = written(shared.groupBy("h", "ctx").agg(F.min(F.struct("doc", "pos")).alias("first"), F.count(F.lit(1)).alias("n")), "contexts")
    whole = _later(shared, first).select("doc", "pos", F.lit(None).cast("long").alias("low"), F.lit(None).cast("long").alias("high"))
    several = written(first.groupBy("h").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("h", (F.col("n") > SHARD).alias("many")), "shards")
    firsts = first.drop("n").join(several, "h").select("h", F.col("first.doc").alias("doc"), F.col("first.pos").alias("pos"), "many")
    cuts = written(_texts_of(docs, firsts, width), "context-words")
    runs = _by_automata(cuts.where("NOT many"), width).unionByName(_by_windows(cuts.where("many"), width))
    return written(whole.unionByName(runs.withColumn("pos", F.lit(None).cast("long"))), "repeated")


def _coverage(words: list[bytes], spots, width: int) -> np.ndarray:
    """Which words repeated windows cover."""
    n = len(words)
    edge = np.zeros(n + 1, np.int32)
    if spots and n >= width:
        pos = np.array([s["pos"] for s in spots if s["pos"] is not None], np.int64) & _PLACE
        if len(pos):
            mins = anchors_of(word_hashes(words), width)[1]
            low, high = np.searchsorted(mins, pos, "left"), np.searchsorted(mins, pos, "right")
            ok = high > low
            np.add.at(edge, low[ok], 1)
            np.add.at(edge, high[ok] - 1 + width, -1)
        for s in spots:
            if s["pos"] is None:
                edge[s["low"] & _PLACE] += 1
                edge[(s["high"] & _PLACE) + width] -= 1
    return np.cumsum(edge[:-1]) > 0


def removal(docs: DataFrame, width: int = 20, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_words, n_removed, kept_sha256) for every row.

    A word is removed if a window of ``width`` words that covers it also starts earlier: in a document with a smaller
    id, or earlier in the same one. Null, empty and short texts lose nothing. Rows without an id lose nothing. Rows
    that repeat id and text are the same document; of rows with one id and different texts that with the smaller MD5
    digest comes first. An empty table gives no rows. Other columns are not read.
    """
    docs = _numbered(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")))

    def digest(batches):
        for b in sliced(batches):
            n, gone, sha = [], [], []
            for text, spots in zip(b.column(1).to_pylist(), b.column(2).to_pylist()):
                words = words_of(text)
                cover = _coverage(words, spots, width)
                kept = [w for w, c in zip(words, cover) if not c] if cover.any() else words
                n.append(len(words))
                gone.append(int(cover.sum()))
                sha.append(hashlib.sha256(b" ".join(kept)).hexdigest())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(sha, pa.string())], ["doc_id", "n_words", "n_removed", "kept_sha256"])

    found = repeated(docs, width).select("doc", F.struct("pos", "low", "high").alias("spot"))
    return _with_positions(docs, found, "left").select("doc_id", "text", "spots").mapInArrow(digest, "doc_id long, n_words long, n_removed long, kept_sha256 string")


_SPACED = re.compile(rb"[^\x20\x09-\x0D]+[\x20\x09-\x0D]*")


def remove_repeats(docs: DataFrame, width: int) -> DataFrame:
    """``docs`` with the repeated words cut out of ``text``, each with the white space after it; all columns and rows stay.

    Null texts stay null. Texts that lose nothing are unchanged to the byte. Rows of one id with different texts are
    different documents, as in ``removal``; further columns may have any names.
    """
    names, schema = docs.columns, docs.schema
    sub, there = (f"{_free_prefix(names)}_{x}" for x in ("sub", "spots"))
    own = _numbered(docs.withColumn("doc_id", F.col("doc_id").cast("long")), sub)
    found = repeated(own.select("doc_id", "text", F.col(sub).alias("sub")), width)
    joined = _with_positions(own, found.select("doc", F.struct("pos", "low", "high").alias("spot")), "left", sub, there)

    def cut(batches):
        for b in sliced(batches):
            out = []
            for text, spots in zip(b.column("text").to_pylist(), b.column(there).to_pylist()):
                if text is None or not spots:
                    out.append(text)
                    continue
                raw = text.encode("utf-8", "surrogatepass")
                cover = _coverage(raw.split(), spots, width)
                head = raw[: len(raw) - len(raw.lstrip())]
                out.append(text if not cover.any() else (head + b"".join(p for p, c in zip(_SPACED.findall(raw), cover) if not c)).decode("utf-8", "surrogatepass"))
            yield pa.RecordBatch.from_arrays([pa.array(out, pa.string()) if n == "text" else b.column(n) for n in names], names)

    return joined.mapInArrow(cut, schema)


def remove_known(docs: DataFrame, references: list[str], width: int) -> DataFrame:
    """(doc_id, n_words, n_removed) against a bounded list of reference texts, kept on every executor as one automaton.

    A word is removed if ``width`` or more consecutive words around it occur in a reference.
    """
    shard = SuffixAutomaton()
    for r in references:
        shard.add(word_hashes(words_of(r)).tolist())
    sent = docs.sparkSession.sparkContext.broadcast(shard)  # bounded by the list given

    def stream(batches):
        own = sent.value
        for b in batches:
            n, gone = [], []
            for text in b.column(1).to_pylist():
                words = words_of(text)
                edge = np.zeros(len(words) + 1, np.int32)
                for i, m in enumerate(own.statistics(word_hashes(words).tolist())):
                    if m >= width:
                        edge[i + 1 - m] += 1
                        edge[i + 1] -= 1
                n.append(len(words))
                gone.append(int((np.cumsum(edge[:-1]) > 0).sum()))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(gone, pa.int64())], ["doc_id", "n_words", "n_removed"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(stream, "doc_id long, n_words long, n_removed long")
