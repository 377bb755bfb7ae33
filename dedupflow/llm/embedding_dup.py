"""Near-duplicate embeddings: binary codes of randomly rotated vectors with a stored correction factor each.

A unit vector o is rotated and kept as the signs of its coordinates, a corner c of the cube scaled to unit length, with
the factor <c, o>. For a unit query q the quotient <c, q> / <c, o> estimates <o, q> without bias, and its error is at
most ``confidence`` * sqrt((1 - f^2) / f^2) * sqrt(1 - <o, q>^2) / sqrt(dim - 1) but for a share of cases that shrinks as a Gaussian tail. Pairs
whose upper bound stays below the threshold are dropped; all others are recomputed from the vectors in double precision.

Rows meet in blocks: within a label, and where that compares fewer pairs within buckets of code bits over several
tables, as many as the recall asks for. A pair that shares several buckets counts in the first alone. Blocks are large
and meet in rounds, so that a row's copies on disk do not grow with its label.
"""

from __future__ import annotations

import math
from functools import lru_cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import mixed, reclaim, scratch, written
from ..operators.components import components

#: Rows and values of a block at most.
BLOCK, BLOCK_VALUES = 32_768, 1 << 21
#: Tables of a bucket plan that are compared at a time.
TABLES_AT_ONCE = 2
#: Tables of a bucket plan at most.
MOST_TABLES = 4096


@lru_cache(maxsize=8)
def rotation(dim: int, seed: int = 4) -> np.ndarray:
    """A random orthogonal matrix, the same on every executor."""
    q, r = np.linalg.qr(np.random.default_rng(seed).standard_normal((dim, dim)))
    return q * np.sign(np.diag(r))


def encode(unit: np.ndarray, rotate: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Packed sign bits of the rotated unit vectors, and the correction factors."""
    y = unit @ rotate.T
    bits = y >= 0
    return np.packbits(bits, axis=1), np.abs(y).sum(1) / math.sqrt(unit.shape[1])


def estimate(codes: np.ndarray, factor: np.ndarray, unit: np.ndarray, rotate: np.ndarray) -> np.ndarray:
    """Unbiased estimates of the inner products of coded vectors (rows) with unit vectors (columns)."""
    return _estimates(codes, factor, (unit @ rotate.T).T.astype(np.float32))


def _estimates(codes: np.ndarray, factor: np.ndarray, rotated: np.ndarray) -> np.ndarray:
    """The same for unit vectors that are rotated already, one per column."""
    dim = len(rotated)
    corner = np.unpackbits(codes, axis=1, count=dim).astype(np.float32) * 2 - 1
    return (corner / (math.sqrt(dim) * factor[:, None].astype(np.float32))) @ rotated


def least_estimate(threshold: float, factor: np.ndarray, dim: int, confidence: float) -> np.ndarray:
    """Estimates below this rule out an inner product of ``threshold`` or more, per coded vector."""
    spread = np.sqrt(np.maximum(1 / factor**2 - 1, 0) / max(dim - 1, 1))
    return threshold - confidence * spread * math.sqrt(1 - threshold**2) - 1e-5


def bucket_plan(n: int, dim: int, threshold: float, direct: int, miss: float) -> tuple[int, int]:
    """(bits, tables) for a label of n vectors: buckets of about ``direct`` rows, and tables enough to miss a share of ``miss`` at most.

    Where the buckets of all tables hold as many pairs as the label, it is one bucket and misses none.

    Tables draw their bits from the same code, so the share is taken over the number of bits that a pair at the threshold
    has in common (as of independent bits), not as of independent tables.
    """
    if n <= direct:
        return 0, 1
    bits = min(dim, max(1, math.ceil(math.log2(n / direct))))
    tables = _tables(bits, dim, threshold, miss)
    return (bits, tables) if tables < 2**bits else (0, 1)


@lru_cache(maxsize=256)
def _tables(bits: int, dim: int, threshold: float, miss: float) -> int:
    agree = 1 - math.acos(threshold) / math.pi
    chance = np.array([math.comb(dim, a) * agree**a * (1 - agree) ** (dim - a) for a in range(dim + 1)])
    meet = np.array([math.comb(a, bits) / math.comb(dim, bits) for a in range(dim + 1)])
    # pairs with fewer common bits than a table has meet nowhere, whatever their number
    low, high = 1, 1
    target = max(miss, 2 * float(chance[meet == 0].sum()))
    while float(chance @ (1 - meet) ** high) > target and high < MOST_TABLES:
        low, high = high, 2 * high
    while low < high:
        middle = (low + high) // 2
        low, high = (low, middle) if float(chance @ (1 - meet) ** middle) <= target else (middle + 1, high)
    return high


def _distinct(vectors: DataFrame) -> DataFrame:
    """(vec_id, label, digest, vector, code, factor, dim): vectors that may link, as the bytes of their values, with code and factor; others have null digest."""

    def prepare(batches):
        for b in batches:
            column = b.column(2)
            start, end = np.asarray(column.offsets[:-1]), np.asarray(column.offsets[1:])
            values = column.values.to_numpy(zero_copy_only=False)  # nulls as NaN
            length = np.where(column.is_valid().to_numpy(zero_copy_only=False), end - start, 0)
            digest, vector, code, factor = ([None] * len(length) for _ in range(4))
            for size in map(int, np.unique(length[length > 0])):
                at = np.flatnonzero(length == size)
                v = values[start[at][:, None] + np.arange(size)]
                ok = np.isfinite(v).all(1) & v.any(1)
                at, v = at[ok], v[ok]
                wide = v.astype(np.float64)
                bits, factors = encode(wide / np.linalg.norm(wide, axis=1)[:, None], rotation(size))
                for i, x, c, f in zip(at, v, bits, factors):
                    vector[i], code[i], factor[i] = x.tobytes(), c.tobytes(), float(f)
                    digest[i] = xxhash.xxh3_128_digest(vector[i])
            yield pa.RecordBatch.from_arrays(
                [b.column(0), b.column(1), pa.array(digest, pa.binary()), pa.array(vector, pa.binary()), pa.array(code, pa.binary()), pa.array(factor, pa.float64()), pa.array(length, pa.int32())],
                ["vec_id", "label", "digest", "vector", "code", "factor", "dim"],
            )

    return vectors.mapInArrow(prepare, "vec_id long, label long, digest binary, vector binary, code binary, factor double, dim int")


def near_vectors(vectors: DataFrame, threshold: float = 0.93, confidence: float = 6.0, direct: int = 32_768, miss: float = 1e-7) -> DataFrame:
    """(vec_id, n_links, component_id, kept) for every row of (vec_id, embedding, label).

    Rows link if their labels are equal and not null and their cosine is ``threshold`` or more, in double precision.
    Null or zero vectors, and those with null or non-finite components, link with nothing; so do rows with a null id or vectors of
    different dimension. Equal vectors of a label are compared once and counted as often as they occur. Rows that
    repeat an id count as further vectors. An empty table gives no rows.
    """
    spark = vectors.sparkSession
    kind = vectors.schema["embedding"].dataType.simpleString()
    kind, dtype = (kind, np.float32) if kind == "array<float>" else ("array<double>", np.float64)
    # the vectors are not written beside their distinct ones: ids and digests are read from the input again at the end
    rows = _distinct(vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("label").cast("long").alias("label"), F.col("embedding").cast(kind).alias("embedding")))
    usable = rows.where(F.col("digest").isNotNull() & F.col("label").isNotNull() & F.col("vec_id").isNotNull())
    once = usable.groupBy("label", "digest").agg(F.min("vec_id").alias("least"), F.count(F.lit(1)).alias("times"), *[F.first(c).alias(c) for c in ("vector", "code", "factor", "dim")])
    reps = written(once.withColumn("rep", F.xxhash64("label", "digest")), "distinct-vectors")
    reclaim(spark)
    sized = reps.join(reps.groupBy("label", "dim").agg(F.count(F.lit(1)).alias("peers")), ["label", "dim"])
    plan_of = lambda n, dim: bucket_plan(n, dim, threshold, direct, miss)
    sizes = reps.groupBy("label", "dim").agg(F.count(F.lit(1)).alias("peers")).groupBy("dim").agg(F.max("peers").alias("peers")).collect()  # a row per dimension
    tables = max((plan_of(r.peers, r.dim)[1] for r in sizes), default=1)

    def placed(first: int, *columns: str) -> DataFrame:
        """Rows with their buckets in tables from ``first`` on, TABLES_AT_ONCE at most."""

        def place(batches):
            for b in batches:
                dims, peers, packed = b.column(1).to_pylist(), b.column(2).to_pylist(), b.column(3).to_pylist()
                keys = [(d, plan_of(n, d)) for d, n in zip(dims, peers)]
                for key in sorted(set(keys)):
                    at = [i for i, k in enumerate(keys) if k == key]
                    tabs = range(first, min(first + TABLES_AT_ONCE, key[1][1]))
                    if not len(tabs):
                        continue
                    own = buckets(np.frombuffer(b"".join(packed[i] for i in at), np.uint8).reshape(len(at), -1), key[0], key[1], tabs)
                    for i, t in enumerate(tabs):
                        yield pa.RecordBatch.from_arrays([*b.take(pa.array(at)).columns, pa.array(own[:, i].view(np.int64)), pa.array([t] * len(at), pa.int32())], [*b.schema.names, "bucket", "tab"])

        taken = sized.select("label", "dim", "peers", "code", *columns)
        out = taken.mapInArrow(place, ", ".join([*(f"{f.name} {f.dataType.simpleString()}" for f in taken.schema), "bucket long", "tab int"]))
        return out.withColumn("bucket", F.xxhash64("label", "bucket", "dim"))

    where, kinds = scratch(spark, "meetings"), "u long, v long, n long"
    rows_of_block = F.least(F.lit(BLOCK), F.greatest(F.lit(256), F.floor(F.lit(BLOCK_VALUES) / F.col("dim"))))
    spark.createDataFrame([], kinds).write.mode("append").parquet(where)
    for first in range(0, tables, TABLES_AT_ONCE):
        sized_buckets = placed(first).groupBy("bucket", "dim").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
        many = written(sized_buckets.select("bucket", F.ceil(F.col("n") / rows_of_block).cast("int").alias("blocks")), "buckets")
        most = many.agg(F.max("blocks")).first()[0]
        for steps in _rounds(most or 0):
            split = placed(first, "rep", "times", "vector", "factor").join(many, "bucket").withColumn("own", F.pmod(F.xxhash64(F.lit(7), "rep"), F.col("blocks")).cast("int"))
            split = split.withColumn("to", F.explode(_meetings(steps))).select("bucket", "to.step", "to.a", "to.second", "rep", "times", "vector", "code", "factor", "peers", "tab")
            split.groupBy("bucket", "step", "a").applyInArrow(_meet(threshold, confidence, plan_of, dtype), kinds).write.mode("append").parquet(where)
            del split
            reclaim(spark)
    found = spark.read.schema(kinds).parquet(where)
    counts = found.where(F.col("v").isNull()).groupBy(F.col("u").alias("rep")).agg(F.sum("n").alias("links"))
    comps = components(found.where(F.col("v").isNotNull()).select("u", "v"))
    named = comps.withColumnRenamed("node", "rep").join(reps.select("rep", "least"), "rep")
    comps = named.join(named.groupBy("comp").agg(F.min("least").alias("component")), "comp").select("rep", "component")
    per = reps.join(counts, "rep", "left").join(comps, "rep", "left").select("label", "digest", (F.coalesce("links", F.lit(0)) + F.col("times") - 1).alias("n_links"), F.coalesce("component", "least").alias("component"))
    keyed = rows.select("vec_id", F.when(F.col("vec_id").isNotNull(), F.col("label")).alias("label"), "digest")
    out = keyed.join(written(per, "vector-links"), ["label", "digest"], "left")
    component = F.coalesce("component", "vec_id")
    return out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.lit(False)).alias("kept"))


def buckets(code: np.ndarray, dim: int, plan: tuple[int, int], tabs: range) -> np.ndarray:
    """(rows, tables): hashed bucket of each row in each of the tables ``tabs``."""
    rng = np.random.default_rng([dim, plan[0]])
    picks = [rng.permutation(dim)[: plan[0]] for _ in range(tabs.stop)]
    bits = np.unpackbits(code, axis=1, count=dim).astype(np.uint64)
    out = [(bits[:, picks[t]] << np.arange(plan[0], dtype=np.uint64)[None, :]).sum(1, dtype=np.uint64) + np.uint64((t + 1) << 40) for t in tabs]
    return np.stack([mixed(o) for o in out], 1) if out else np.zeros((len(code), 0), np.uint64)


def _rounds(most: int) -> list[list[int]]:
    """Which blocks meet in each round, by the distance between them around the circle of a bucket's blocks: a row has three copies in a round at most."""
    return [[0, 1], *([d] for d in range(2, most // 2 + 1))] if most > 1 else [[0]] * (most == 1)


def _meetings(steps: list[int]):
    """Groups (step, a, second) that a row of block ``own`` goes to: block a meets itself (step 0) or block a + step, every two blocks once."""
    own, blocks, to = F.col("own"), F.col("blocks"), []
    for d in steps:
        group = lambda a, second: F.struct(F.lit(d).alias("step"), a.cast("int").alias("a"), F.lit(second).alias("second"))  # noqa: E731, B023
        if not d:
            to.append(group(own, False))
            continue
        to.append(F.when((blocks > 2 * d) | ((blocks == 2 * d) & (own < d)), group(own, False)))
        to.append(F.when((blocks > 2 * d) | ((blocks == 2 * d) & (own >= d)), group(F.pmod(own - d, blocks), True)))
    return F.array_compact(F.array(*to))


def _matrix(column, dtype, rows: int) -> np.ndarray:
    """The rows' bytes, all of one length, as a matrix."""
    return np.frombuffer(b"".join(column.to_pylist()), dtype).reshape(rows, -1)


def _meet(threshold, confidence, plan_of, dtype):
    """Per pair of blocks: links counted per row (v null), and links that connect the components (u, v)."""

    def meet(table: pa.Table) -> pa.Table:
        rep = table.column("rep").to_numpy()
        times = table.column("times").to_numpy()
        peers, tab = table.column("peers")[0].as_py(), table.column("tab")[0].as_py()
        v = _matrix(table.column("vector"), dtype, len(rep)).astype(np.float64)
        dim, norm = v.shape[1], np.linalg.norm(v, axis=1)
        code = _matrix(table.column("code"), np.uint8, len(rep))
        factor = table.column("factor").to_numpy()
        same = table.column("step")[0].as_py() == 0
        second = table.column("second").to_numpy().astype(bool)
        # in a pair of different blocks every row of one meets every row of the other
        left, right = (np.arange(len(rep)),) * 2 if same else (np.flatnonzero(~second), np.flatnonzero(second))
        earlier = buckets(code, dim, plan_of(peers, dim), range(tab)) if tab else None
        least = least_estimate(threshold, factor, dim, confidence).astype(np.float32)
        rotated = ((v[right] / norm[right][:, None]) @ rotation(dim).T).T.astype(np.float32)
        count, comp = np.zeros(len(rep), np.int64), np.arange(len(rep))
        u, w = [], []
        chunk = max(16, (1 << 20) // max(len(right), 1))
        for i in range(0, len(left), chunk):
            rows = left[i : i + chunk]
            begin = i if same else 0  # of a block with itself only the later rows
            x, y = np.nonzero(_estimates(code[rows], factor[rows], rotated[:, begin:]) >= least[rows][:, None])
            x, y = rows[x], right[begin + y]
            if same:
                x, y = x[x < y], y[x < y]
            for j in range(0, len(x), 50_000):
                p, q = x[j : j + 50_000], y[j : j + 50_000]
                ok = np.einsum("ij,ij->i", v[p], v[q]) / (norm[p] * norm[q]) >= threshold
                p, q = p[ok], q[ok]
                if earlier is not None:
                    fresh = ~(earlier[p] == earlier[q]).any(1)
                    p, q = p[fresh], q[fresh]
                np.add.at(count, p, times[q])
                np.add.at(count, q, times[p])
                while len(p):  # one edge per merge
                    a, b = comp[p[0]], comp[q[0]]
                    if a != b:
                        u.append(rep[p[0]])
                        w.append(rep[q[0]])
                        comp[comp == max(a, b)] = min(a, b)
                    apart = comp[p] != comp[q]
                    p, q = p[apart], q[apart]
        some = np.flatnonzero(count)
        return pa.table([pa.array([*u, *rep[some]], pa.int64()), pa.array([*w, *[None] * len(some)], pa.int64()), pa.array([*[None] * len(u), *count[some]], pa.int64())], ["u", "v", "n"])

    return meet
