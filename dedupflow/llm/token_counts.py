"""Exact token counts at every prefix of a text, by dynamic programming over its words.

The count of a prefix that ends with a word is the count of the prefix before it plus the tokens of that word; a
prefix that ends inside a word adds the tokens of the cut word. Words are what white space separates, which no token
of the vocabulary in use crosses, so the table is exact and a question re-encodes one word at most.
"""

from __future__ import annotations

import re
from bisect import bisect_right
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Memo, sliced

#: Control characters that Python's split() takes for white space and the tokenizer's pattern does not.
_ODD = re.compile("[\x1c-\x1f]")


class PrefixCounter:
    """Counts tokens with a tokenizers file whose pre-tokenizer drops white space."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self._tok = Tokenizer.from_file(path)
        self._tok.no_truncation()
        self._tok.no_padding()
        self._memo = Memo(self.whole)

    def whole(self, text: str) -> int:
        return len(self._tok.encode(text, add_special_tokens=False).ids)

    def word_counts(self, words: list[str]) -> np.ndarray:
        return np.fromiter(map(self._memo.__getitem__, words), np.int64, len(words))

    def table(self, text: str) -> tuple[np.ndarray, np.ndarray]:
        """Ends of the words (character offsets) and the tokens up to each end."""
        pattern = re.compile(r"[^\s]+") if not _ODD.search(text) else re.compile("(?:[^\\s]|[\x1c-\x1f])+")
        spans = [m.span() for m in pattern.finditer(text)]
        ends = np.fromiter((e for _, e in spans), np.int64, len(spans))
        return ends, np.cumsum(self.word_counts([text[a:b] for a, b in spans]))

    def count_at(self, text: str, chars: int, table=None) -> int:
        """Tokens of ``text[:chars]``."""
        ends, upto = table or self.table(text)
        k = bisect_right(ends, chars)
        before, start = (int(upto[k - 1]), int(ends[k - 1])) if k else (0, 0)
        cut = text[start:chars].strip() if not _ODD.search(text) else text[start:chars]
        return before + (self.whole(cut) if cut else 0)

    def longest_prefix(self, text: str, budget: int, table=None) -> int:
        """Characters of the longest prefix that ends with a word and has at most ``budget`` tokens."""
        ends, upto = table or self.table(text)
        k = int(np.searchsorted(upto, budget, "right"))
        return int(ends[k - 1]) if k else 0


@lru_cache(maxsize=4)
def counter(path: str) -> PrefixCounter:
    return PrefixCounter(path)


def token_counts(docs: DataFrame, vocabulary: str, limit: int = 2048, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: id, bytes, tokens, whether over ``limit``, from the last entry of the text's prefix table.

    A null text counts as empty: 0 bytes, 0 tokens. Repeated rows each give a row; other columns are not read. One
    pass, no shuffle; memory is one Arrow batch and a bounded memo of words.
    """

    def count(batches):
        own = counter(vocabulary)
        for b in sliced(batches):
            texts = [t or "" for t in b.column(1).to_pylist()]
            n = [int(upto[-1]) if len(upto) else 0 for _, upto in map(own.table, texts)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([len(t.encode()) for t in texts], pa.int64()), pa.array(n, pa.int64()), pa.array([x > limit for x in n], pa.bool_())], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(count, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")


def prefix_tables(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row the stored table: ends of words and tokens up to each, as arrays. A null or blank text has empty arrays."""

    def tables(batches):
        own = counter(vocabulary)
        for b in sliced(batches):
            made = [own.table(t or "") for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([e for e, _ in made], pa.list_(pa.int64())), pa.array([c for _, c in made], pa.list_(pa.int64()))], ["doc_id", "ends", "tokens"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(tables, "doc_id long, ends array<long>, tokens array<long>")


def fits(tables: DataFrame, budget: int) -> DataFrame:
    """From stored tables, without encoding: the longest prefix within ``budget`` tokens (characters, tokens)."""
    k = F.size(F.filter("tokens", lambda x: x <= budget))
    pick = lambda c: F.when(k > 0, F.try_element_at(c, k)).otherwise(F.lit(0)).cast("long")
    return tables.select("doc_id", pick(F.col("ends")).alias("fit_chars"), pick(F.col("tokens")).alias("fit_tokens"))
