"""Connected components of an edge table, by minimum labels with pointer jumping; also union-find for one task's rows."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..functions.storage import discard, written

#: Edges that a task merges at a time.
CHUNK = 1_000_000
#: Edges, after each task has merged its own, up to which one task resolves the rest (a chunk at most); more go by rounds of joins.
FEW = CHUNK


class Forest:
    """Union-find over small integers; the smallest member is the root."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def root(self, i: int) -> int:
        up = self.up
        while up[i] != i:
            up[i] = up[up[i]]
            i = up[i]
        return i

    def join(self, i: int, j: int) -> bool:
        i, j = self.root(i), self.root(j)
        if i == j:
            return False
        self.up[max(i, j)] = min(i, j)
        return True


def smallest_reachable(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Nodes of the edges in order, and the smallest node that each reaches: roots go under the smallest root they meet."""
    nodes, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b = at[: len(u)], at[len(u) :]
    up = np.arange(len(nodes))
    while True:
        a, b = up[a], up[b]
        apart = a != b
        if not apart.any():
            return nodes, nodes[up]
        a, b = a[apart], b[apart]
        np.minimum.at(up, np.maximum(a, b), np.minimum(a, b))
        while (up[up] != up).any():
            up = up[up]


def _merged(batches):
    """(u, v): every node of the edges with the smallest one it reaches, a chunk of edges at a time; loops and null ends are dropped."""
    held, size = [], 0

    def rows():
        node, comp = smallest_reachable(*(np.concatenate(x) for x in zip(*held)))
        for i in range(0, len(node), 50_000):
            yield pa.RecordBatch.from_arrays([pa.array(x[i : i + 50_000], pa.int64()) for x in (node, comp)], ["u", "v"])

    for b in batches:
        if b.num_rows:
            held.append([c.to_numpy(zero_copy_only=False) for c in b.columns])
            size += b.num_rows
        if size >= CHUNK:
            yield from rows()
            held, size = [], 0
    if held:
        yield from rows()


def components(edges: DataFrame) -> DataFrame:
    """(node, comp) for every node of the edges (u, v): comp is the smallest node reachable.

    Tasks first merge what their own edges connect. If few edges are left, one task merges these in a single pass over
    a bounded number of rows; else they are resolved by rounds of joins. There each round takes the minimum over neighbours and then the label's own label, so the rounds grow with the logarithm
    of the longest path. Every round is written to the shared folder; nothing is collected. Sums by node are combined
    before the shuffle, and a node with very many edges is split by the adaptive skew join. Null ends and loops are
    dropped; without edges the result is empty.
    """
    left = Observation()
    own = edges.where("u != v").select(F.col("u").cast("long"), F.col("v").cast("long")).mapInArrow(_merged, "u long, v long").where("u != v")
    edges = written(own.observe(left, F.count(F.lit(1)).alias("n")), "merged-edges")
    if left.get["n"] <= FEW:
        labels = written(edges.coalesce(1).mapInArrow(_merged, "u long, v long").toDF("node", "comp"), "labels")
        discard(edges)
        return labels
    # many edges name the same small node: each node keeps its smallest neighbour, and the others meet that one
    down = written(edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
    discard(edges)
    least = down.groupBy("u").agg(F.min("v").alias("m"))
    others = down.join(written(least, "least"), "u").where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    both = least.select("u", F.col("m").alias("v")).union(others.distinct())
    both = written(both.union(both.select(F.col("v"), F.col("u"))).distinct(), "edges")
    labels = written(both.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("m")).select("node", F.least("node", "m").alias("comp")), "labels")
    while True:
        near = both.join(labels.select(F.col("node").alias("v"), "comp"), "v").groupBy(F.col("u").alias("node")).agg(F.min("comp").alias("m"))
        step = labels.join(near, "node").select("node", F.col("comp").alias("old"), F.least("comp", "m").alias("comp"))
        jump = step.select(F.col("node").alias("comp"), F.col("comp").alias("further"))
        moved = Observation()
        after = step.join(jump, "comp").select("node", "old", F.col("further").alias("comp"))
        after = written(after.observe(moved, F.count(F.when(F.col("comp") < F.col("old"), 1)).alias("n")), "labels")
        discard(labels)
        labels = after.select("node", "comp")
        if not moved.get["n"]:
            discard(both)
            return labels
