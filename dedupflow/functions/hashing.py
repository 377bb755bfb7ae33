"""Column functions: content hashes, 64-bit FNV-1a, claim order keys, arithmetic of the toy group."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from .groups import TOY_P, TOY_Q

#: Fixed values of 64-bit FNV-1a.
FNV_OFFSET, FNV_PRIME = 0xCBF29CE484222325, 0x100000001B3


def normalized(content: Column, normalize: str = "none") -> Column:
    """Canonical form of a record: ``none`` (bytewise), ``trim``, ``space`` (white space collapsed) or ``case`` (collapsed, lower case)."""
    if normalize == "none":
        return content
    if normalize == "trim":
        return F.trim(content)
    spaced = F.trim(F.regexp_replace(content, "[ \\t\\r\\n]+", " "))
    if normalize == "space":
        return spaced
    if normalize == "case":
        return F.lower(spaced)
    raise ValueError(f"no normalisation named {normalize}")


def content_hash(content: Column, normalize: str = "none") -> Column:
    """32-byte hash of a record; null stays null."""
    return F.unhex(F.sha2(normalized(content, normalize), 256))


def tag_key(tag: Column) -> Column:
    """64-bit partitioning key of a tag; equality is always decided on the tag itself."""
    return F.xxhash64(tag)


def fnv1a64_of(values: pd.Series) -> pd.Series:
    """FNV-1a of each string's or binary's bytes, as signed 64-bit; vectorised over the rows of a batch."""
    raw = [b"" if v is None else v.encode() if isinstance(v, str) else bytes(v) for v in values]
    length = np.array([len(r) for r in raw], np.int64)
    width = int(length.max()) if len(raw) else 0
    data = np.frombuffer(b"".join(r.ljust(width, b"\0") for r in raw), np.uint8).reshape(len(raw), width) if width else np.zeros((len(raw), 0), np.uint8)
    h = np.full(len(raw), FNV_OFFSET, np.uint64)
    for i in range(width):
        live = i < length
        h[live] = (h[live] ^ data[live, i]) * np.uint64(FNV_PRIME)
    return pd.Series(h.view(np.int64)).where(pd.Series([v is not None for v in values]))


def fnv1a64_udf():
    """The Arrow function over a session that is there (a module must import on executors without one)."""

    @F.pandas_udf("long")
    def fnv(values: pd.Series) -> pd.Series:
        return fnv1a64_of(values)

    return fnv


def fnv1a64(value: Column | str) -> Column:
    return fnv1a64_udf()(value)


def arrival_ms(sid: Column) -> Column:
    """Deterministic arrival of a client within the first 20 virtual seconds."""
    return F.pmod(sid * 7919 + 17, F.lit(20000))


def contact_ms(sid: Column, after: int) -> Column:
    """Deterministic first contact of an online client within the second after ``after``."""
    return F.lit(after + 1) + F.pmod(sid * 137 + 11, F.lit(1000))


def order_key(sent: Column, seq: Column, sid: Column, seqs: int = 10**9, sids: int = 1000) -> Column:
    """Total order (sent, seq, sid) as one BIGINT, so that the first claim is a hash aggregate without a sort.

    ``sent`` is in milliseconds since the start of the round; ``seqs`` and ``sids`` bound the other two. Bounds that
    would leave less than 90 virtual minutes are refused, and so are rows beyond the bounds, when they are computed;
    ``wide_order_key`` has none in practice.
    """
    if seqs * sids * 5_400_000 >= 2**63:
        raise ValueError("the parts do not fit 63 bits; use wide_order_key")
    fits = (seq >= 0) & (seq < seqs) & (sid >= 0) & (sid < sids)
    return F.when(fits, sent.cast("long") * (seqs * sids) + seq * sids + sid).otherwise(F.raise_error(F.lit("a number is beyond the bounds of the order key")).cast("long"))


def wide_order_key(sent: Column, seq: Column, sid: Column) -> Column:
    """The same order for milliseconds since the epoch, 12-digit sequence numbers and 9-digit clients, as DECIMAL(38, 0)."""
    big, mid = F.lit("1" + "0" * 21).cast("decimal(22,0)"), F.lit("1" + "0" * 9).cast("decimal(10,0)")
    return (sent.cast("decimal(15,0)") * big + seq.cast("decimal(12,0)") * mid + sid.cast("decimal(9,0)")).cast("decimal(38,0)")


def toy_power(base: Column, exponent: Column, p: int = TOY_P) -> Column:
    """base ^ exponent mod p by 31 squarings, as one expression (fits BIGINT)."""
    steps = F.aggregate(
        F.sequence(F.lit(0), F.lit(30)),
        F.struct(F.lit(1).cast("long").alias("out"), base.cast("long").alias("square"), exponent.cast("long").alias("left")),
        lambda s, _: F.struct(
            F.when(s["left"] % 2 == 1, s["out"] * s["square"] % p).otherwise(s["out"]).alias("out"),
            (s["square"] * s["square"] % p).alias("square"),
            F.shiftright(s["left"], 1).alias("left"),
        ),
    )
    return steps["out"]


def toy_hash(content: Column) -> Column:
    """A square of the toy group from the first 15 hex digits of the content's hash."""
    root = F.conv(F.substring(F.sha2(content, 256), 1, 15), 16, 10).cast("long") % (TOY_P - 3) + 2
    return root * root % TOY_P


def toy_inverse(mask: Column) -> Column:
    """Inverse of a mask modulo the prime group order."""
    return toy_power(mask, F.lit(TOY_Q - 2), TOY_Q)


def register(spark: SparkSession) -> None:
    """SQL names: protected_tag(content), claim_order(sent, seq, sid), fnv1a64(text)."""
    spark.udf.register("fnv1a64", fnv1a64_udf())
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION protected_tag(content STRING) RETURNS STRING RETURN sha2(content, 256)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION claim_order(sent BIGINT, seq BIGINT, sid BIGINT) RETURNS BIGINT RETURN sent * 1000000000000 + seq * 1000 + sid")
