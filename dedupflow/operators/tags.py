"""Protected tags: equal contents get equal tags, and nobody but the key's holder can make one from a content.

Of the oblivious schemes the client masks the content's hash, the authority raises the masked value to its key, and
the client takes the mask off: tag = hash ^ key, whatever the mask. Masks are drawn, used and dropped within one task,
so a retried task may draw others without any effect on tags.
"""

from __future__ import annotations

import hashlib
import hmac
import secrets
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.groups import group
from ..functions.hashing import content_hash

OBLIVIOUS = ("modp2048", "ristretto", "toy31")
SCHEMES = (*OBLIVIOUS, "keyed", "plain")


@dataclass(frozen=True)
class Authority:
    """Holder of the secret. It never appears in a column or a plan: tasks get it with the function they run."""

    scheme: str
    _secret: bytes = field(repr=False)
    epoch: int = 0

    @classmethod
    def create(cls, scheme: str = "keyed", bits: int = 256, seed: int | None = None, epoch: int = 0) -> Authority:
        """A fresh secret of ``bits`` bits (128 at least), or one derived from ``seed`` for tests."""
        if scheme not in SCHEMES:
            raise ValueError(f"scheme {scheme} is none of {SCHEMES}")
        if bits < 128:
            raise ValueError("a secret has 128 bits or more")
        size = -(-bits // 8)
        secret = secrets.token_bytes(size) if seed is None else hashlib.shake_256(b"seed %d" % seed).digest(size)
        return cls(scheme, secret, epoch)

    def at(self, epoch: int) -> Authority:
        """The same authority with the key of another epoch; tags of different epochs never meet."""
        return Authority(self.scheme, self._secret, epoch)

    def _key(self) -> bytes:
        return hmac.new(self._secret, b"epoch %d" % self.epoch, hashlib.sha512).digest()

    def exponent(self) -> int:
        own = group(self.scheme)
        bits = own.mask_bits or own.q.bit_length()
        return int.from_bytes(self._key()[: bits // 8], "big") % (own.q - 1) + 1


def mask(own) -> int:
    """A random exponent in [1, q - 1]; of groups with short masks one of that many bits."""
    return secrets.randbelow((1 << own.mask_bits) - 1 if own.mask_bits else own.q - 1) + 1


def blind(hashed: bytes, own) -> tuple[bytes, int]:
    """The client's first step: what is sent, and the mask that stays."""
    r = mask(own)
    return own.encode(own.power(own.hash_to(hashed), r)), r


def evaluate(blinded: bytes, authority: Authority) -> bytes:
    """The authority's step; it sees a masked value only."""
    own = group(authority.scheme)
    return own.encode(own.power(own.decode(blinded), authority.exponent()))


def unblind(evaluated: bytes, r: int, own) -> bytes:
    """The client's last step."""
    return own.encode(own.power(own.decode(evaluated), pow(r, -1, own.q)))


def direct(hashed: bytes, authority: Authority) -> bytes:
    """hash ^ key at once: what the three steps must give."""
    own = group(authority.scheme)
    return own.encode(own.power(own.hash_to(hashed), authority.exponent()))


def local_distinct(items: DataFrame, normalize: str = "none") -> DataFrame:
    """(sid, hash, item_id, copies): one row per client and content, with the smallest item and the number of copies.

    Goes before any exponentiation; null contents give no row.
    """
    hashed = items.select("sid", "item_id", content_hash(F.col("content"), normalize).alias("hash")).where("hash IS NOT NULL")
    return hashed.groupBy("sid", "hash").agg(F.min("item_id").alias("item_id"), F.count(F.lit(1)).alias("copies"))


def protect(items: DataFrame, authority: Authority | None = None, normalize: str = "none") -> DataFrame:
    """(sid, tag, item_id, copies): the tags of every client's set of records.

    ``plain`` (also without an authority) and ``keyed`` hashes stay in the JVM or need one keyed hash per row; the
    oblivious schemes run all three steps per distinct client and content in one pass.
    """
    rows = local_distinct(items, normalize)
    if authority is None or authority.scheme == "plain":
        return rows.select("sid", F.col("hash").alias("tag"), "item_id", "copies")

    def run(batches):
        oblivious = authority.scheme in OBLIVIOUS
        own, key = group(authority.scheme) if oblivious else None, authority._key()
        for b in batches:
            out = []
            for h in b.column(1).to_pylist():
                if oblivious:
                    sent, r = blind(h, own)
                    out.append(unblind(evaluate(sent, authority), r, own))
                else:
                    out.append(hmac.new(key, h, hashlib.sha256).digest())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.binary()), b.column(2), b.column(3)], ["sid", "tag", "item_id", "copies"])

    if authority.scheme in OBLIVIOUS:  # costly per row, so spread over all cores whatever the input's size
        rows = rows.repartition(max(rows.sparkSession.sparkContext.defaultParallelism, 1), "sid", "hash")
    return rows.mapInArrow(run, "sid long, tag binary, item_id long, copies long")


def check_protocol(items: DataFrame, authority: Authority) -> DataFrame:
    """(tag, direct, blinded) per distinct content: the protocol's tag next to the power taken at once, and what was sent."""
    rows = items.select(content_hash(F.col("content")).alias("hash")).where("hash IS NOT NULL").distinct()

    def run(batches):
        own = group(authority.scheme)
        for b in batches:
            out = []
            for h in b.column(0).to_pylist():
                sent, r = blind(h, own)
                out.append((unblind(evaluate(sent, authority), r, own), direct(h, authority), sent))
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.binary()) for c in (list(zip(*out)) or [(), (), ()])], ["tag", "direct", "blinded"])

    return rows.repartition(rows.sparkSession.sparkContext.defaultParallelism, "hash").mapInArrow(run, "tag binary, direct binary, blinded binary")
