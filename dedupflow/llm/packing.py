"""Packing documents into token sequences of a fixed size by bin completion on the histogram of lengths.

Lengths are integers up to the sequence size, so the whole packing problem is a histogram of at most that many
counts, whatever the number of documents. The driver solves that histogram: around the largest remaining length it
enumerates undominated fillings, takes the least wasteful, applies it as often as the counts allow, and backtracks
within a node budget as long as the waste so far could still beat the incumbent, which starts as best fit decreasing.
Executors then place each piece by its rank among the pieces of its length.
"""

from __future__ import annotations

import array
import re
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import Memo, sliced, written

#: The file of ranks that holds the same vocabulary as the tokenizers file; words are encoded with it, several times faster.
RANKS = "byte_bpe_50k.tiktoken"
SPECIAL = "<|endoftext|>"
_PAIR = re.compile(r" \s|\s |^\s")
_CUT = re.compile(r"(?<=\S) (?=\S)")


class Encoder:
    """Ids of a text as little-endian 32-bit bytes; encodes word by word through a bounded memo.

    A space between two characters that are not white space begins a new pre-token, so texts are cut there and the
    ids of the parts follow each other unchanged.
    """

    def __init__(self, vocabulary: str, ranks: str, pattern: str):
        import base64

        import tiktoken
        from tokenizers import Tokenizer

        with open(ranks, "rb") as lines:
            table = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
        self._fast = tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=table, special_tokens={})
        self._full = Tokenizer.from_file(vocabulary)
        self._memo = Memo(self.part)

    def part(self, text: str) -> bytes:
        ids = self._full.encode(text, add_special_tokens=False).ids if SPECIAL in text else self._fast.encode_ordinary(text)
        return array.array("I", ids).tobytes()

    def encode(self, text: str) -> bytes:
        if not text:
            return b""
        parts = _CUT.split(text) if _PAIR.search(text) else text.split(" ")
        return self.part(parts[0]) + b"".join(map(self._memo.__getitem__, [" " + p for p in parts[1:]]))


@lru_cache(maxsize=2)
def encoder(vocabulary: str, ranks: str, pattern: str) -> Encoder:
    return Encoder(vocabulary, ranks, pattern)


# ---------------------------------------------------------------- the histogram problem


def lower_bound(counts: np.ndarray) -> int:
    """Sequences that any packing needs: the total, and the bound that sets large lengths apart from those that fit beside them."""
    size = len(counts) - 1
    lengths = np.arange(size + 1)
    number, total = np.cumsum(counts), np.cumsum(counts * lengths)
    best = -(-int(total[-1]) // size)
    half = size // 2
    for small in range(half + 1):
        big = int(number[size] - number[size - small])
        middle_n = int(number[size - small] - number[half])
        middle = int(total[size - small] - total[half])
        rest = int(total[half] - (total[small - 1] if small else 0))
        best = max(best, big + middle_n + max(0, -(-(rest - (middle_n * size - middle)) // size)))
    return best


def fillings(counts: np.ndarray, room: int, keep: int, nodes: int) -> list[list[tuple[int, int]]]:
    """Up to ``keep`` undominated fillings of ``room``, least waste first.

    A filling is dominated if a length that is left over fits into its gap, or may take the place of a shorter one in it.
    """
    found: dict[tuple, int] = {}
    have = np.flatnonzero(counts[: room + 1])[::-1]
    budget = [nodes]
    picked: list[list[int]] = []

    def undominated(gap: int) -> bool:
        used = {l: m for l, m in picked}
        free = lambda l: counts[l] - used.get(l, 0) > 0
        if gap and any(free(l) for l in range(1, gap + 1)):
            return False
        return not any(free(x) for l, _ in picked for x in range(l + 1, min(l + gap, room) + 1))

    def go(at: int, gap: int) -> bool:
        budget[0] -= 1
        if gap == 0 or budget[0] <= 0:
            if gap == 0 or undominated(gap):
                found.setdefault(tuple((l, m) for l, m in picked), gap)
            return sum(g == 0 for g in found.values()) >= keep or budget[0] <= 0
        # longest first; an exact fit by one length comes before the rest
        at = int(np.searchsorted(-have, -gap, "left")) if at < len(have) and have[at] > gap else at
        below = False
        for i in range(at, len(have)):
            l = int(have[i])
            m = min(int(counts[l]), gap // l)
            if m <= 0:
                continue
            below = True
            for use in range(m, 0, -1):
                picked.append([l, use])
                stop = go(i + 1, gap - l * use)
                picked.pop()
                if stop:
                    return True
        if not below and undominated(gap):
            found.setdefault(tuple((l, m) for l, m in picked), gap)
        return False

    go(0, room)
    if not found:
        found[()] = room
    return [list(f) for f, _ in sorted(found.items(), key=lambda x: (x[1], len(x[0])))[:keep]]


def best_fit(counts: np.ndarray) -> list[tuple[int, list[tuple[int, int]]]]:
    """Best fit decreasing, by runs of equal sequences."""
    size = len(counts) - 1
    left, out = counts.copy(), []
    while (have := np.flatnonzero(left)).size:
        longest = int(have[-1])
        items, gap = {}, size
        l = longest
        own = left.copy()
        while True:
            m = min(int(own[l]), gap // l)
            if m:
                items[l] = m
                gap -= m * l
                own[l] -= m
            fit = np.flatnonzero(own[: min(gap, l - 1) + 1])
            if not fit.size:
                break
            l = int(fit[-1])
        times = min(int(left[l]) // m for l, m in items.items())
        for l, m in items.items():
            left[l] -= times * m
        out.append((times, list(items.items())))
    return out


def complete(counts: np.ndarray, keep: int = 2, nodes: int = 400, dives: int = 200) -> list[tuple[int, list[tuple[int, int]]]]:
    """Runs (times, [(length, number)]) that use up ``counts`` (index = length) in few sequences.

    ``keep`` fillings are tried per step, each searched within ``nodes`` steps; ``dives`` bounds how many steps beyond
    the first descent are spent on better packings. The result is never worse than best fit decreasing.
    """
    counts = np.asarray(counts, np.int64).copy()
    size = len(counts) - 1
    total, bound = int((counts * np.arange(size + 1)).sum()), lower_bound(counts)
    best = best_fit(counts)
    best_n = sum(t for t, _ in best)
    spare = [None, dives]

    def descend(left: np.ndarray, runs: list, used: int, waste: int, first: bool) -> bool:
        nonlocal best, best_n
        left, depth = left.copy(), len(runs)
        stack = []
        while True:
            have = np.flatnonzero(left)
            if not have.size:
                if used < best_n:
                    best, best_n = list(runs), used
            elif waste <= (best_n - 1) * size - total:
                longest = int(have[-1])
                left[longest] -= 1
                options = fillings(left, size - longest, keep, nodes)
                left[longest] += 1
                stack.append((left, len(runs), used, waste, longest, iter(options)))
            if best_n <= bound:
                return True
            while stack:
                at, n, u, w, longest, options = stack[-1]
                option = next(options, None)
                if option is None:
                    stack.pop()
                    continue
                if spare[0] is not None:
                    spare[1] -= 1
                    if spare[1] < 0:
                        return False
                items = dict(option)
                items[longest] = items.get(longest, 0) + 1
                times = min(int(at[l]) // m for l, m in items.items())
                gap = size - sum(l * m for l, m in items.items())
                left = at.copy()
                for l, m in items.items():
                    left[l] -= times * m
                del runs[n:]
                runs.append((times, sorted(items.items(), reverse=True)))
                used, waste = u + times, w + gap * times
                break
            else:
                return False
            if not np.any(left):
                spare[0] = True  # the first descent is over; from here steps count

    if best_n > bound:
        descend(counts, [], 0, 0, True)
    return best


# ---------------------------------------------------------------- pieces and places


def pieces(docs: DataFrame, vocabulary: str, ranks: str, pattern: str, size: int = 2048, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece, with its task and its rank there among pieces of its length. Materialise before use: ranks belong to one run."""

    def cut(batches):
        own, task, seen = encoder(vocabulary, ranks, pattern), TaskContext.get().partitionId(), [0] * (size + 1)
        for b in sliced(batches):
            cols = ([], [], [], [], [], [])
            for doc, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                ids = own.encode(text or "") + b"\0\0\0\0"
                n = len(ids) // 4
                start, k = 0, 0
                end = n % size or min(n, size)
                while start < n:
                    length = end - start
                    for c, v in zip(cols, (doc, k, start, length, zlib.crc32(ids[4 * start : 4 * end]), seen[length])):
                        c.append(v)
                    seen[length] += 1
                    start, end, k = end, end + size, k + 1
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int32()), *(pa.array(c, pa.int64()) for c in cols[2:]), pa.array([task] * len(cols[0]), pa.int64())], ["doc_id", "piece", "start", "length", "ids_crc32", "nth", "task"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(cut, "doc_id long, piece int, start long, length long, ids_crc32 long, nth long, task long")


def places(runs: list[tuple[int, list[tuple[int, int]]]]) -> dict[str, np.ndarray]:
    """The runs as a sorted table: per (length, first rank) the first sequence, pieces per sequence and offset."""
    rows, next_rank, sequence = [], {}, 0
    for times, items in runs:
        offset = 0
        for l, m in items:
            r = next_rank.get(l, 0)
            rows.append((l, r, sequence, m, offset))
            next_rank[l] = r + times * m
            offset += l * m
        sequence += times
    t = np.array(sorted(rows), np.int64).reshape(-1, 5)
    return {"length": t[:, 0], "rank": t[:, 1], "sequence": t[:, 2], "each": t[:, 3], "offset": t[:, 4]}


def pack(docs: DataFrame, vocabulary: str, ranks: str, pattern: str, size: int = 2048) -> DataFrame:
    """Every document's pieces with their sequence and offset.

    A null or empty text is one piece of the closing id alone. Repeated rows are packed each. An empty table gives no
    rows. Only the histogram of lengths (at most ``size`` rows) and the counts by task reach the driver or are joined.
    """
    cut = written(pieces(docs, vocabulary, ranks, pattern, size), "pieces")
    by_task = cut.groupBy("length", "task").agg(F.count(F.lit(1)).alias("n"))
    counts = np.zeros(size + 1, np.int64)
    for length, n in by_task.groupBy("length").agg(F.sum("n")).collect():  # at most `size` rows
        counts[length] = n
    table = places(complete(counts))
    key = table["length"] << 44 | table["rank"]
    before = by_task.withColumn("first", F.sum("n").over(Window.partitionBy("length").orderBy("task").rowsBetween(Window.unboundedPreceding, -1))).select("length", "task", F.coalesce("first", F.lit(0)).alias("first"))

    def put(batches):
        for b in batches:
            length, rank = (b.column(i).to_numpy(zero_copy_only=False) for i in (3, 5))
            at = np.searchsorted(key, length << 44 | rank, "right") - 1
            into, each = rank - table["rank"][at], table["each"][at]
            yield pa.RecordBatch.from_arrays([*b.columns[:5], pa.array(table["sequence"][at] + into // each), pa.array(table["offset"][at] + into % each * length)], ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    ranked = cut.join(before, ["length", "task"]).select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("first") + F.col("nth")).alias("rank"))
    return ranked.mapInArrow(put, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
