"""Near-duplicate documents: chosen-path set similarity join on word shingles, links confirmed on full sets.

1. Documents with the same shingle set are one class. Each class has a signature of independent minwise tokens.
2. In every tree a class starts at the node named by its first selected token. Nodes of up to ``leaf`` classes compare
   them exhaustively by signature; larger ones branch on further selected tokens (two at a time at first, so that a
   similar pair keeps meeting), down to a last level. Trees are independent; their number sets the recall.
3. What comparisons leave are groups of possibly linked classes. Within a group links are confirmed on the full sets,
   a pair only until its ends are connected. Groups too large for one task are resolved by pivots: every member is
   compared with a few pivots at a time, and members outside the group's main component become pivots in turn, so no
   link between different components can be missed and no pair of the main component need be listed.

A similar pair at the threshold shares a token of a level with probability ``similarity``. A tree finds it with that
probability if the first node is small and with 0.61 if it takes all levels, so twelve trees miss one pair in 2 * 10^8
and one in 80,000; closer pairs far fewer.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import BROADCAST_ROWS, discard, mixed, sliced, small_side, window_hashes, word_hashes, written
from ..operators.components import Forest, components

TREES = 12
#: Tokens selected per level; level 1 names a tree's first node.
BRANCH = (1, 2, 1, 1)
#: Independent minwise tokens per signature: one for every selection of every tree, the rest only for comparisons.
SLOTS = 84
PATHS = TREES * sum(BRANCH)
LEAF, LAST_LEAF = 1024, 4096
GROUP_DOCS, GROUP_SHINGLES = 400, 2_000_000
#: Signatures agree in at least this share of slots if the similarity is 0.8 (5.5 standard errors below).
SLACK = 5.5

_rng = np.random.default_rng(20)
_XOR = _rng.integers(0, 2**63, SLOTS, np.int64).astype(np.uint64)
_MULT = _rng.integers(0, 2**63, SLOTS, np.int64).astype(np.uint64) * np.uint64(2) + np.uint64(1)


def shingles(text: str | None, k: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the text's k-word shingles; a text of fewer words is one shingle, an empty one none."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.empty(0, np.uint64)
    h = word_hashes(words)
    return np.unique(window_hashes(h, k)) if len(h) >= k else mixed(np.array([xxhash.xxh3_64_intdigest(h.tobytes())], np.uint64))


def signature(s: np.ndarray) -> np.ndarray:
    """32 bits of the minwise token of each slot."""
    low = np.full(SLOTS, np.iinfo(np.uint64).max, np.uint64)
    for i in range(0, len(s), 2048):
        low = np.minimum(low, ((s[None, i : i + 2048] ^ _XOR[:, None]) * _MULT[:, None]).min(1))
    return (low >> np.uint64(12)).astype(np.uint32)


def _features(docs: DataFrame, k: int) -> DataFrame:
    """(doc_id, n, d1, d2, sig, short): set size, digest, tokens for paths, and a byte of every minwise token for comparisons."""

    def make(batches):
        for b in sliced(batches):
            n, d1, d2, sig, short = [], [], [], [], []
            for text in b.column(1).to_pylist():
                s = shingles(text, k)
                d = xxhash.xxh3_128_intdigest(s.tobytes())
                n.append(len(s))
                d1.append((d >> 64) - (1 << 63))
                d2.append((d & (1 << 64) - 1) - (1 << 63))
                own = signature(s) if len(s) else np.empty(0, np.uint32)
                sig.append(own[:PATHS].tobytes())
                short.append(own.astype(np.uint8).tobytes())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(d1, pa.int64()), pa.array(d2, pa.int64()), pa.array(sig, pa.binary()), pa.array(short, pa.binary())], ["doc_id", "n", "d1", "d2", "sig", "short"])

    return docs.mapInArrow(make, "doc_id long, n long, d1 long, d2 long, sig binary, short binary")


def _paths(sig: np.ndarray, level: int) -> np.ndarray:
    """Keys of the nodes at ``level`` for rows of signatures: (rows, trees * branches)."""
    starts = np.cumsum((0,) + BRANCH)
    per = sum(BRANCH)
    keys = []
    for t in range(TREES):
        nodes = [np.full(len(sig), t + 1, np.uint64)]
        for l in range(level):
            nodes = [mixed(k ^ mixed(sig[:, t * per + starts[l] + j].astype(np.uint64) + np.uint64(l << 40 | j << 36))) for k in nodes for j in range(BRANCH[l])]
        keys += nodes
    return np.stack(keys, 1)


def _nodes(reps: DataFrame, level: int) -> DataFrame:
    """(node, rep): each class at its nodes of ``level``, of those below the large nodes ``up`` that it was at (all at level 1)."""

    def expand(batches):
        for b in batches:
            if not b.num_rows:
                continue
            sig = np.stack([np.frombuffer(x, np.uint32) for x in b.column(1).to_pylist()])
            keys = _paths(sig, level).view(np.int64)
            rep = np.repeat(b.column(0).to_numpy(zero_copy_only=False), keys.shape[1])
            keys = keys.ravel()
            if level > 1:
                up = np.repeat(_paths(sig, level - 1).view(np.int64), BRANCH[level - 1], 1)
                below = np.concatenate([np.isin(u, x) for u, x in zip(up, b.column(2).to_pylist())])
                keys, rep = keys[below], rep[below]
            for i in range(0, len(rep), 50_000):
                yield pa.RecordBatch.from_arrays([pa.array(keys[i : i + 50_000]), pa.array(rep[i : i + 50_000])], ["node", "rep"])

    return reps.mapInArrow(expand, "node long, rep long")


def runs_of(batches, width: int):
    """Consecutive rows with equal first column, as lists of columns; rows come sorted by it."""
    held = None
    for b in batches:
        if not b.num_rows:
            continue
        key = b.column(0).to_numpy(zero_copy_only=False)
        cols = [b.column(i).to_numpy(zero_copy_only=False) for i in range(width)]
        cuts = np.flatnonzero(key[1:] != key[:-1]) + 1
        bounds = [0, *cuts.tolist(), len(key)]
        for i, j in zip(bounds, bounds[1:]):
            part = [c[i:j] for c in cols]
            if held is not None and held[0][0] == part[0][0]:
                held = [np.concatenate(x) for x in zip(held, part)]
            else:
                if held is not None:
                    yield held
                held = part
    if held is not None:
        yield held


def _compare(sized: DataFrame, least: float, similarity: float) -> DataFrame:
    """Edges that connect what a node's classes may link, compared exhaustively by signature; at most one per merge."""

    agree = int(np.ceil(least * SLOTS))

    def compare(batches):
        u, v = [], []
        for _, rep, n, sig in runs_of(batches, 4):
            if len(rep) < 2:
                continue
            s = np.stack([np.frombuffer(x, np.uint8) for x in sig])
            comp = np.arange(len(rep))
            for i in range(len(rep) - 1):
                # later rows that are not yet in this one's component
                rest = np.flatnonzero(comp[i + 1 :] != comp[i]) + i + 1
                if len(rest):
                    close = ((s[rest] == s[i]).sum(1) >= agree) & (np.minimum(n[rest], n[i]) >= similarity * np.maximum(n[rest], n[i]))
                    found, first = np.unique(comp[rest[close]], return_index=True)
                    for c, j in zip(found, rest[close][first]):
                        u.append(rep[i])
                        v.append(rep[j])
                        comp[comp == c] = comp[i]
            if len(u) > 20_000:
                yield pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], ["u", "v"])
                u, v = [], []
        yield pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], ["u", "v"])

    return sized.repartition("node").sortWithinPartitions("node").mapInArrow(compare, "u long, v long")


def _candidates(reps: DataFrame, similarity: float) -> DataFrame:
    """Edges between classes that may be linked, from all trees and levels."""
    least = similarity - SLACK * (similarity * (1 - similarity) / SLOTS) ** 0.5
    out, base = [], reps.select("rep", "sig")
    for level in range(1, len(BRANCH) + 1):
        leaf = LAST_LEAF if level == len(BRANCH) else LEAF
        nodes = written(_nodes(base, level), "nodes")
        # written, so that the join deals both sides anew and can split a node that very many classes share
        sizes = written(nodes.groupBy("node").agg(F.count(F.lit(1)).alias("size")).where("size > 1"), "sizes")
        sized = written(nodes.join(sizes, "node"), "sized")
        discard(nodes)
        small = sized.where(F.col("size") <= leaf).join(reps.select("rep", "n", "short"), "rep").select("node", "rep", "n", "short")
        out.append(written(_compare(small, least, similarity), "candidates"))
        large = sized.where(F.col("size") > leaf).select("node", "rep")
        if not large.limit(1).count():
            break
        # a class is at TREES * branches nodes of a level at most
        base = reps.select("rep", "sig").join(large.groupBy("rep").agg(F.collect_list("node").alias("up")), "rep")
    else:
        # what still shares a node of the last level in such numbers is joined as one group; full sets decide within it
        star = written(large.groupBy("node").agg(F.min("rep").alias("u")), "stars")
        out.append(written(large.join(star, "node").where("rep != u").select("u", F.col("rep").alias("v")), "candidates"))
    edges = out[0]
    for e in out[1:]:
        edges = edges.union(e)
    return edges


def _linked(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    """Whether 100 * |a & b| >= percent * |a | b|, on sorted distinct values."""
    if len(a) > len(b):
        a, b = b, a
    if 100 * len(a) < percent * len(b):
        return False
    at = np.searchsorted(b, a)
    at[at == len(b)] = 0
    both = int((b[at] == a).sum())
    return 100 * both >= percent * (len(a) + len(b) - both)


def _small_groups(sets: DataFrame, percent: int) -> DataFrame:
    """(rep, comp): true components of the groups, each group within one task."""

    def resolve(batches):
        for _, rep, _, blob in runs_of(batches, 4):
            rep, first = np.unique(rep, return_index=True)
            own = [np.frombuffer(x, np.uint64) for x in blob[first]]
            forest = Forest(len(rep))
            for i in range(1, len(rep)):
                for j in range(i):
                    if forest.root(i) != forest.root(j) and _linked(own[i], own[j], percent):
                        forest.join(i, j)
            yield pa.RecordBatch.from_arrays([pa.array(rep), pa.array(rep[[forest.root(i) for i in range(len(rep))]])], ["rep", "comp"])

    return sets.repartition("grp").sortWithinPartitions("grp").select("grp", "rep", "n", "set").mapInArrow(resolve, "rep long, comp long")


def _large_groups(sets: DataFrame, percent: int, pivot_shingles: int = 4_000_000) -> DataFrame:
    """(rep, comp): true components of groups too large for a task, by rounds of pivots.

    A pivot is compared with all members of its group not yet in its component. A group is done when every member
    outside its largest component has been a pivot. Signatures rule most pivots out for a member before any set is
    compared. Pivots of a round are bounded in number and bytes; groups that do not fit wait for a later round.
    """
    similarity = percent / 100
    agree = int(np.ceil((similarity - SLACK * (similarity * (1 - similarity) / SLOTS) ** 0.5) * SLOTS))
    spark, edges, done, each = sets.sparkSession, None, None, 16
    comps = sets.select("grp", "rep", F.col("rep").alias("comp"))
    while True:
        sizes = comps.groupBy("grp", "comp").agg(F.count(F.lit(1)).alias("size"))
        main = sizes.groupBy("grp").agg(F.max_by("comp", F.struct("size", "comp")).alias("main"))
        todo = comps.join(main, "grp")
        todo = todo if edges is None else todo.where("comp != main")
        todo = todo if done is None else todo.join(done, "rep", "left_anti")
        ranked = todo.withColumn("r", F.row_number().over(Window.partitionBy("grp").orderBy(F.xxhash64("rep"), "rep"))).where(F.col("r") <= each)
        chosen = written(ranked.join(sets.select("rep", "n"), "rep").select("grp", "rep", "comp", "n", "r"), "pivots")
        # the cheapest ranks first, until the bound on what is sent to every task
        taken, total = [], 0
        for row in chosen.orderBy("r", "n").select("grp", "rep", "n").toLocalIterator():
            if taken and total + row.n > pivot_shingles or len(taken) >= 20_000:
                break
            taken.append(row.rep)
            total += row.n
        if not taken:
            discard(chosen)
            return comps.select("rep", "comp")
        picked = spark.createDataFrame([(r,) for r in taken], "rep long")
        table: dict[int, list] = {}
        for row in sets.join(F.broadcast(picked), "rep", "left_semi").toLocalIterator():  # at most pivot_shingles
            table.setdefault(row.grp, []).append((row.rep, bytes(row.short), bytes(row.set)))
        sent = spark.sparkContext.broadcast(table)

        def compare(batches):
            own = {}
            for g, p in sent.value.items():
                kept = {r: (short, x) for r, short, x in p}
                own[g] = (list(kept), np.stack([np.frombuffer(short, np.uint8) for short, _ in kept.values()]), [np.frombuffer(x, np.uint64) for _, x in kept.values()])
            told = set()  # pairs of pivots that a member has connected: said once per task
            for b in batches:
                u, v = [], []
                for g, rep, short, blob in zip(*(b.column(i).to_pylist() for i in range(4))):
                    if g not in own:
                        continue
                    pivots, marks, parts = own[g]
                    s = np.frombuffer(blob, np.uint64)
                    close = np.flatnonzero((marks == np.frombuffer(short, np.uint8)).sum(1) >= agree)
                    near = [pivots[i] for i in close if pivots[i] == rep or _linked(s, parts[i], percent)]
                    for p, q in [(rep, p) for p in near[:1]] + [(near[0], p) for p in near[1:] if (near[0], p) not in told]:
                        if p != q:
                            u.append(p)
                            v.append(q)
                            told.add((p, q)) if p != rep else None
                yield pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], ["u", "v"])

        new = written(sets.select("grp", "rep", "short", "set").mapInArrow(compare, "u long, v long"), "links")
        edges = new if edges is None else edges.union(new)
        done = picked if done is None else done.union(picked)
        found = components(edges)
        comps = written(sets.select("grp", "rep").join(found.withColumnRenamed("node", "rep"), "rep", "left").select("grp", "rep", F.coalesce("comp", "rep").alias("comp")), "comps")
        discard(chosen)
        each = min(4096, each * 16)


def near_duplicates(docs: DataFrame, k: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for every row.

    Documents are linked if their sets of k-word shingles have a Jaccard similarity of percent / 100 or more; components
    are closed under links, and the smallest id of each is kept. Null, empty and blank texts have an empty set and link
    with nothing; texts of fewer than k words are one shingle. Rows without an id link with nothing and have a null
    component. Rows that repeat an id are told apart by their sets. Other columns are not read.
    """
    docs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    similarity = percent / 100
    features = written(_features(docs, k), "shingles")
    usable = features.where("n > 0 AND doc_id IS NOT NULL")
    # a class is named by half of its set's digest
    reps = written(usable.groupBy("d1", "d2").agg(F.min("doc_id").alias("doc_id"), F.min("n").alias("n"), F.first("sig").alias("sig"), F.first("short").alias("short")).withColumn("rep", F.col("d1")), "classes")
    groups = components(_candidates(reps, similarity)).select(F.col("node").alias("rep"), F.col("comp").alias("grp"))
    members = written(reps.select("rep", "doc_id", "d2", "short").join(groups, "rep"), "members")
    again = docs.join(small_side(members, members.count(), BROADCAST_ROWS // 4), "doc_id")

    def full(batches):
        for b in sliced(batches):
            rows = []
            for text, grp, rep, d2, short in zip(*(c.to_pylist() for c in b.columns)):
                s = shingles(text, k)
                if xxhash.xxh3_128_intdigest(s.tobytes()) == (rep + (1 << 63)) << 64 | d2 + (1 << 63):
                    rows.append((grp, rep, len(s), s.tobytes(), short))
            cols = list(zip(*rows)) or [()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary()))], ["grp", "rep", "n", "set", "short"])

    sets = written(again.select("text", "grp", "rep", "d2", "short").mapInArrow(full, "grp long, rep long, n long, set binary, short binary"), "sets")
    sizes = sets.groupBy("grp").agg(F.count(F.lit(1)).alias("docs"), F.sum("n").alias("total"))
    sizes = written(sizes.select("grp", ((F.col("docs") > GROUP_DOCS) | (F.col("total") > GROUP_SHINGLES)).alias("large")), "group-sizes")
    found = _small_groups(sets.join(sizes.where("NOT large"), "grp"), percent)
    if sizes.where("large").limit(1).count():
        big = written(sets.join(sizes.where("large"), "grp").select("grp", "rep", "n", "set", "short").dropDuplicates(["grp", "rep"]), "large-groups")
        found = found.union(_large_groups(big, percent))
    found = written(found.join(reps.select("rep", "doc_id"), "rep"), "linked")
    least = found.groupBy("comp").agg(F.min("doc_id").alias("least"))
    found = found.join(least, "comp").select("rep", "least")
    comps = reps.select("d1", "d2", "rep", "doc_id").join(found, "rep", "left").select("d1", "d2", F.coalesce("least", "doc_id").alias("component_id"))
    usable_row = (F.col("n") > 0) & F.col("doc_id").isNotNull()
    out = features.select("doc_id", F.col("n").alias("n_shingles"), F.when(usable_row, F.col("d1")).alias("d1"), F.when(usable_row, F.col("d2")).alias("d2")).join(written(comps, "components"), ["d1", "d2"], "left")
    component = F.coalesce("component_id", "doc_id")
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(False)).alias("kept"))
