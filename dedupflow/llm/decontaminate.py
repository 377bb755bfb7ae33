"""Benchmark decontamination by templates: numbers, names and units become typed placeholders, windows are hash-joined.

A word is canonical if lower-cased and stripped of punctuation; a number (also in words), a unit and a capitalised word
become a placeholder of their kind, so a question asked again with other values has the same template. Case decides
what a name is, so windows are compared in two more forms: with names as casefolded literals, and with all words so
(copies in capitals or lower case, and verbatim windows of few literals). A document matches an item where a window of
a form equals one of the item's; along one alignment of the two, every slot value of the item must stand for one value
in the document and the other way round, else the match is chance.
"""

from __future__ import annotations

import re
import unicodedata
from array import array

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import sliced, window_hashes

NUMBER, NAME, UNIT = "<number>", "<name>", "<unit>"
#: Number words and units that become placeholders.
NUMBER_WORDS = frozenset("zero one two three four five six seven eight nine ten eleven twelve thirteen fourteen fifteen sixteen seventeen eighteen nineteen twenty thirty forty fifty sixty seventy eighty ninety hundred thousand million billion half third quarter dozen".split())
UNITS = frozenset("mm cm m km inch inches foot feet ft yard yards mile miles mg g kg gram grams kilogram kilograms pound pounds lb lbs ounce ounces oz ton tons ml l litre litres liter liters gallon gallons second seconds sec minute minutes min hour hours day days week weeks month months year years dollar dollars cent cents euro euros percent degrees degree kmh mph watt watts volt volts meter meters metre metres kilometer kilometers kilometre kilometres".split())
_NUMBER = re.compile(r"[$€£]?[-+]?\d[\d.,:/]*(?:e[-+]?\d+)?%?(?:st|nd|rd|th)?")
#: Windows of a block of benchmark items, which every task holds; larger benchmarks are matched block by block.
BLOCK_WINDOWS = 2_000_000


def forms(word: str) -> tuple[str, str, str] | None:
    """Template, template that is blind to case and plain form of a white-space-separated word; None if it is punctuation only."""
    letters = word.isascii() and word.isalpha()
    bare = word if letters else word.strip("".join(c for c in set(word) if not c.isalnum() and c not in "$€£%"))
    if not letters and not any(c.isalnum() for c in bare):
        return None
    low = word.lower() if letters else unicodedata.normalize("NFKC", bare).casefold()
    if low in NUMBER_WORDS or not letters and _NUMBER.fullmatch(low):
        return NUMBER, NUMBER, low
    if low in UNITS:
        return UNIT, UNIT, low
    return NAME if bare[0].isupper() else low, low, low


def canonical(word: str) -> str:
    """Template form of a white-space-separated word; empty if it is punctuation only."""
    return (forms(word) or ("",))[0]


_SLOT_OF = {s: xxhash.xxh3_64_intdigest(s) for s in (NUMBER, NAME, UNIT)}
_SLOT_HASHES = np.array(sorted(_SLOT_OF.values()), np.uint64)


class WordForms(dict):
    """Bounded memo of words as places in ``hashes`` (three forms each, zeros for punctuation); emptied between texts only."""

    def __init__(self, cap: int = 400_000, chars: int = 16_000_000):
        super().__init__()
        self.cap, self.most, self.chars, self.hashes = cap, chars, 0, array("Q")

    def __missing__(self, word: str) -> int:
        own = forms(word)
        if own:
            typed, blind, plain = own
            z = xxhash.xxh3_64_intdigest(plain)
            y = z if blind is plain else _SLOT_OF[blind]
            self.hashes.extend((z if typed is plain else _SLOT_OF[typed], y, z))
        else:
            self.hashes.extend((0, 0, 0))
        self.chars += len(word)
        self[word] = at = len(self)
        return at

    def of(self, words: list[str]) -> np.ndarray:
        """Hashes of the words, a row per form."""
        if not words:
            return np.zeros((3, 0), np.uint64)
        if len(self) > self.cap or self.chars > self.most:
            self.clear()
            self.chars, self.hashes = 0, array("Q")
        at = np.fromiter(map(self.__getitem__, words), np.int64, len(words))
        return np.ascontiguousarray(np.frombuffer(self.hashes, np.uint64).reshape(-1, 3)[at].T)


def template(text: str | None, memo: WordForms) -> tuple[list[str], np.ndarray]:
    """The words that are not punctuation only, and the hashes of their forms."""
    words = (text or "").split()
    h = memo.of(words)
    if (h[0] == 0).any():
        words = [w for w, x in zip(words, h[0]) if x]
        h = h[:, h[0] != 0]
    return words, h


def _bare(word: str) -> str:
    return re.sub(r"^\W+|\W+$", "", word).casefold()


def item_windows(items: list[tuple[int, str]], width: int, literals: int, shortest: int) -> dict:
    """Sorted window hashes of all items with (item, start); items of fewer than ``width`` words give one window each.

    Each window is there in its three forms where they differ. Template windows need ``literals`` words that are not
    placeholders (in shorter items the same share of them), plain ones do not. Forms share one table: a hash of one form
    equals that of another only where the words do.
    """
    memo, rows, texts = WordForms(), {}, {}
    for k, (_, text) in enumerate(items):
        words, h = template(text, memo)
        if h.shape[1] < shortest:
            continue
        texts[k] = (words, h[0])
        w = min(width, h.shape[1])
        seen = []
        for f, form in enumerate(h):
            own = window_hashes(form, w)
            take = np.convolve(~np.isin(form, _SLOT_HASHES), np.ones(w, int), "valid") >= literals * w / width
            if f == len(h) - 1:
                take[:] = True
            for other, there in seen:
                take &= ~(there & (own == other))
            seen.append((own, take))
            at = np.flatnonzero(take)
            rows.setdefault(w, []).append((own[at], np.full(len(at), k), at, np.full(len(at), f == 0)))
    lengths = {}
    for w, parts in sorted(rows.items()):
        hashes, item, start, typed = (np.concatenate(c) for c in zip(*parts))
        order = np.lexsort((start, item, hashes))
        hashes, bits = hashes[order], np.uint64(64 - min(24, max(16, len(order).bit_length() + 3)))
        filled = np.zeros(1 << (64 - int(bits)), bool)
        filled[hashes >> bits] = True
        lengths[w] = (hashes, item[order], start[order], typed[order], filled, bits)
    return {"lengths": lengths, "texts": texts, "ids": [i for i, _ in items]}


def consistent(item: list[str], doc: list[str], slots: np.ndarray) -> bool:
    """Whether slot values of the item and of the document stand for each other one to one."""
    there, back = {}, {}
    for a, b, s in zip(item, doc, slots):
        if s:
            a, b = _bare(a), _bare(b)
            if there.setdefault(a, b) != b or back.setdefault(b, a) != a:
                return False
    return True


def _stretches(run: list[int], w: int, words: list[str], shift: int, item: tuple) -> int:
    """Windows of a run that contradicts itself which lie in consistent stretches of twice ``w`` words or more.

    A run is cut where a slot value contradicts those before it; shorter stretches are taken for chance.
    """
    theirs, theirs_h = item
    slots = np.isin(theirs_h, _SLOT_HASHES)
    total, first, at = 0, 0, 1
    while first < len(run):
        there, back, upto = {}, {}, run[first]
        for at in range(first, len(run) + 1):
            if at == len(run):
                break
            clash = False
            for p in range(max(upto, run[at]), run[at] + w):
                if slots[p - shift]:
                    a, b = _bare(theirs[p - shift]), _bare(words[p])
                    if there.setdefault(a, b) != b or back.setdefault(b, a) != a:
                        clash = True
                        break
            if clash:
                break
            upto = run[at] + w
        if at > first and upto - run[first] >= 2 * w:
            total += at - first
        # the next stretch begins past the value that clashed
        past = p + 1 if at < len(run) else run[-1] + 1
        first = next((i for i in range(max(at, first + 1), len(run)) if run[i] >= past), len(run)) if at < len(run) else len(run)
    return total


def _judged(spots: list[int], w: int, words: list[str], shift: int, item: tuple, typed: dict[int, bool] | None) -> int:
    """Windows of one alignment in consistent runs; windows that touch each other are judged together.

    Where a run of all forms is not consistent, its template windows are judged on their own, and what is left of long
    runs that contradict themselves counts in consistent stretches.
    """
    theirs, theirs_h = item
    n = 0
    for run in np.split(np.array(spots), np.flatnonzero(np.diff(spots) > w) + 1):
        low, high = int(run[0]), int(run[-1]) + w
        if consistent(theirs[low - shift : high - shift], words[low:high], np.isin(theirs_h[low - shift : high - shift], _SLOT_HASHES)):
            n += len(run)
        else:
            own = [p for p in run.tolist() if typed[p]] if typed else []
            alone = _judged(own, w, words, shift, item, None) if 0 < len(own) < len(run) else 0
            n += alone or _stretches(run.tolist(), w, words, shift, item)
    return n


def matches(text: str | None, table: dict, memo: WordForms) -> dict[int, int]:
    """Item number -> windows matched, with consistent slots."""
    words, h = template(text, memo)
    found: dict[int, int] = {}
    for w, (hashes, item, start, typed, filled, bits) in table["lengths"].items():
        if h.shape[1] < w or not len(hashes):
            continue
        lines: dict[tuple[int, int], dict[int, bool]] = {}
        for f, form in enumerate(h):
            own = window_hashes(form, w)
            spots = np.flatnonzero(filled[own >> bits])
            own = own[spots]
            at = np.minimum(np.searchsorted(hashes, own), len(hashes) - 1)
            for j in np.flatnonzero(hashes[at] == own).tolist():
                i, p = int(at[j]), int(spots[j])
                while i < len(hashes) and hashes[i] == own[j]:
                    hit = lines.setdefault((int(item[i]), p - int(start[i])), {})
                    hit[p] = hit.get(p, False) or bool(f == 0 and typed[i])
                    i += 1
        for (k, shift), hit in lines.items():
            n = _judged(sorted(hit), w, words, shift, table["texts"][k], hit)
            if n:
                found[k] = found.get(k, 0) + n
    return found


def _blocks(benchmark: DataFrame, width: int, literals: int, shortest: int):
    """The benchmark in blocks that one task can hold; usually one."""
    block, size = [], 0
    for r in benchmark.select(F.col("item_id").cast("long").alias("item_id"), "text").where("text IS NOT NULL AND item_id IS NOT NULL").distinct().toLocalIterator():
        block.append((r.item_id, r.text))
        size += len(r.text.split())
        if size >= BLOCK_WINDOWS:
            yield item_windows(block, width, literals, shortest)
            block, size = [], 0
    if block:
        yield item_windows(block, width, literals, shortest)


def contaminated(docs: DataFrame, benchmark: DataFrame, width: int = 10, literals: int = 5, shortest: int = 6) -> DataFrame:
    """(doc_id, item_id, n_windows) for every document and item that match; whole texts, one pass per benchmark block.

    Null and empty texts match nothing; items of fewer than ``shortest`` words are not searched for, items of fewer
    than ``width`` words as one window. Repeated documents each give their rows, repeated items count once. An empty
    benchmark or table gives no rows.
    """
    spark, out = docs.sparkSession, None
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    for table in _blocks(benchmark, width, literals, shortest):
        sent = spark.sparkContext.broadcast(table)  # BLOCK_WINDOWS at most

        def find(batches, sent=sent):
            table, memo = sent.value, WordForms()
            for b in sliced(batches):
                rows = [(d, table["ids"][k], n) for d, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist()) for k, n in matches(t, table, memo).items()]
                cols = list(zip(*rows)) or [(), (), ()]
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], ["doc_id", "item_id", "n_windows"])

        part = docs.mapInArrow(find, "doc_id long, item_id long, n_windows long")
        out = part if out is None else out.union(part)
    return spark.createDataFrame([], "doc_id long, item_id long, n_windows long") if out is None else out


def clean(docs: DataFrame, benchmark: DataFrame, width: int = 10, literals: int = 5, shortest: int = 6) -> DataFrame:
    """The rows of ``docs`` whose text matches no item, with all their columns; null texts stay."""
    for table in _blocks(benchmark, width, literals, shortest):
        sent = docs.sparkSession.sparkContext.broadcast(table)  # BLOCK_WINDOWS at most

        def keep(batches, sent=sent):
            table, memo = sent.value, WordForms()
            for b in sliced(batches):
                yield b.filter(pa.array([not matches(t, table, memo) for t in b.column("text").to_pylist()], pa.bool_()))

        docs = docs.mapInArrow(keep, docs.schema)
    return docs
