"""The training-data operators: edge cases, brute force, round trips, held-out accuracy."""

import hashlib
import math
import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import dedupflow.llm.queries as queries
from dedupflow.llm import decontaminate, embedding_dup, language_id, license_scan, near_dup, packing, substring_dup, token_counts, toxicity, warc
from dedupflow.operators import components

DOC = "doc_id long, text string"
VOCAB, RANKS, PATTERN = queries.tokenizer_path("byte_bpe_50k.json"), queries.tokenizer_path(packing.RANKS), queries.pre_token_pattern()
WORDS = queries.tokenizer_path("word_bpe_49k.json")
EDGES = [(1, None), (2, ""), (3, " \n\t "), (4, "word"), (5, "a b"), (6, "a b"), (6, "a b"), (7, "é ß 日本 \x1c x"), (None, "a b"), (8, "x " * 5000)]


def frame(spark, rows, schema=DOC):
    return spark.createDataFrame(rows, schema)


def clash(df):
    """The same rows with further columns that operators use as names of their own."""
    for c in ("n", "spots", "rep", "comp", "label", "tag", "score", "n_shingles", "h", "pos"):
        df = df.withColumn(c, F.lit("other"))
    return df


def rows_of(df, *cols):
    return sorted((tuple(r) for r in df.select(*cols).collect()), key=repr)


# ---------------------------------------------------------------- 9 and 1


def hf(path):
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


TEXTS = ["", "Hello  World", "it's <|endoftext|> here", "<|startoftext|>x", "a\x1cb c", "é́ ẞ İ ǅ", "x" * 300 + " y", "tab\tnew\nline  end ", "数字 123 456", " nb sp"]


def test_token_counts_equal_the_library(spark):
    tok = hf(WORDS)
    got = {r.doc_id: r for r in token_counts.token_counts(frame(spark, list(enumerate(TEXTS)) + [(99, None)]), WORDS).collect()}
    for i, t in enumerate(TEXTS):
        assert got[i].n_tokens == len(tok.encode(t, add_special_tokens=False).ids), t
        assert got[i].n_bytes == len(t.encode())
    assert (got[99].n_bytes, got[99].n_tokens, got[99].over_limit) == (0, 0, False)


def test_prefix_counts_are_exact_at_every_character():
    tok, own = hf(WORDS), token_counts.counter(WORDS)
    for t in TEXTS:
        table = own.table(t)
        for n in range(len(t) + 1):
            assert own.count_at(t, n, table) == len(tok.encode(t[:n], add_special_tokens=False).ids), (t, n)
    text = "some words to be counted here, twice: some words"
    cut = own.longest_prefix(text, 5)
    assert own.whole(text[:cut]) <= 5 < own.whole(text)


def test_budget_questions_from_stored_tables(spark):
    stored = token_counts.prefix_tables(frame(spark, [(1, "one two three four"), (2, None), (3, "")]), WORDS)
    got = {r.doc_id: (r.fit_chars, r.fit_tokens) for r in token_counts.fits(stored, 2).collect()}
    assert got == {1: (7, 2), 2: (0, 0), 3: (0, 0)}


def test_encoder_equals_the_library(spark, sf):
    tok, own = hf(VOCAB), packing.encoder(VOCAB, RANKS, PATTERN)
    docs = [r.text for r in spark.read.parquet(f"{sf}/documents.parquet").select("text").collect()]
    for t in TEXTS + docs:
        assert np.frombuffer(own.encode(t), "<u4").tolist() == tok.encode(t, add_special_tokens=False).ids, t[:50]


def check_packing(rows, texts, size=2048):
    tok = hf(VOCAB)
    by_doc, bins = {}, {}
    for r in rows:
        by_doc.setdefault(r.doc_id, []).append(r)
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for doc, text in texts.items():
        ids = np.array(tok.encode(text or "", add_special_tokens=False).ids + [0], "<u4")
        parts = sorted(by_doc[doc], key=lambda r: r.piece)
        assert [p.piece for p in parts] == list(range(len(parts))) and sum(p.length for p in parts) == len(ids)
        assert len(parts) == -(-len(ids) // size) and all(p.length == size for p in parts[1:])
        for p in parts:
            assert p.ids_crc32 == zlib.crc32(ids[p.start : p.start + p.length].tobytes())
    for parts in bins.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= size
    return len(bins)


def test_packing_whole_table(spark, sf):
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()}
    rows = queries.op1_best_fit_packing(spark, sf).collect()
    total = sum(r.length for r in rows)
    assert check_packing(rows, texts) <= -(-total // 2048) + 1


def test_packing_edges(spark):
    rows = [(i, t) for i, t in EDGES if i not in (6, None)]
    check_packing(packing.pack(clash(frame(spark, rows)), VOCAB, RANKS, PATTERN).collect(), dict(rows))
    assert packing.pack(frame(spark, EDGES), VOCAB, RANKS, PATTERN).count() >= len(EDGES)
    assert packing.pack(frame(spark, []), VOCAB, RANKS, PATTERN).count() == 0


def test_bin_completion_finds_optima():
    rng = random.Random(3)
    for _ in range(60):
        size = 20
        lengths = [rng.randint(1, size) for _ in range(rng.randint(1, 9))]
        counts = np.bincount(lengths, minlength=size + 1)
        runs = packing.complete(counts)
        used = np.zeros(size + 1, int)
        for times, items in runs:
            assert sum(l * m for l, m in items) <= size
            for l, m in items:
                used[l] += times * m
        assert (used == counts).all()
        best = len(lengths)

        def place(i, bins):
            nonlocal best
            if len(bins) >= best:
                return
            if i == len(lengths):
                best = len(bins)
                return
            for b in range(len(bins)):
                if bins[b] + lengths[i] <= size:
                    bins[b] += lengths[i]
                    place(i + 1, bins)
                    bins[b] -= lengths[i]
            place(i + 1, bins + [lengths[i]])

        lengths.sort(reverse=True)
        place(0, [])
        assert packing.lower_bound(counts) <= best == sum(t for t, _ in runs)


def test_completion_beats_best_fit():
    counts = np.zeros(101, np.int64)
    for l, n in ((55, 40), (45, 20), (30, 20), (25, 40), (15, 20), (20, 60)):
        counts[l] = n
    assert packing.lower_bound(counts) <= sum(t for t, _ in packing.complete(counts)) <= sum(t for t, _ in packing.best_fit(counts))


# ---------------------------------------------------------------- 3


def brute_components(ids, linked):
    up = {i: i for i in ids}

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in ids:
        for j in ids:
            if i < j and linked(i, j):
                a, b = sorted((root(i), root(j)))
                up[b] = a
    return {i: min(j for j in ids if root(j) == root(i)) for i in ids}


def noisy_documents(seed=5):
    rng = random.Random(seed)
    vocabulary = [f"w{i}" for i in range(400)]
    texts = []
    for _ in range(12):
        base = [rng.choice(vocabulary) for _ in range(rng.randint(20, 120))]
        texts.append(" ".join(base))
        for _ in range(rng.randint(0, 8)):
            copy = [rng.choice(vocabulary) if rng.random() < 0.05 else w for w in base]
            texts.append(" ".join(copy).upper() if rng.random() < 0.3 else " ".join(copy))
    return {i: t for i, t in enumerate(texts)}


@pytest.mark.parametrize("k", [2, 5])
def test_near_duplicates_equal_brute_force(spark, k):
    docs = noisy_documents()
    sets = {}
    for i, t in docs.items():
        w = t.lower().split()
        sets[i] = {tuple(w[j : j + k]) for j in range(len(w) - k + 1)}
    expected = brute_components(list(docs), lambda a, b: 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]))
    got = near_dup.near_duplicates(frame(spark, list(docs.items())), k).collect()
    assert {r.doc_id: r.component_id for r in got} == expected
    assert {r.doc_id: r.n_shingles for r in got} == {i: len(s) for i, s in sets.items()}


def test_large_groups_by_pivots(spark, monkeypatch):
    monkeypatch.setattr(near_dup, "GROUP_DOCS", 3)
    docs = noisy_documents(9)
    sets = {i: {tuple(t.lower().split()[j : j + 2]) for j in range(len(t.split()) - 1)} for i, t in docs.items()}
    expected = brute_components(list(docs), lambda a, b: 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]))
    assert {r.doc_id: r.component_id for r in near_dup.near_duplicates(frame(spark, list(docs.items())), 2).collect()} == expected


def test_tree_levels_below_the_first(spark, monkeypatch):
    monkeypatch.setattr(near_dup, "LEAF", 2)
    monkeypatch.setattr(near_dup, "LAST_LEAF", 3)
    docs = noisy_documents(11)
    sets = {i: {tuple(t.lower().split()[j : j + 2]) for j in range(len(t.split()) - 1)} for i, t in docs.items()}
    expected = brute_components(list(docs), lambda a, b: 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]))
    assert {r.doc_id: r.component_id for r in near_dup.near_duplicates(frame(spark, list(docs.items())), 2).collect()} == expected


def test_near_duplicate_edges(spark):
    got = rows_of(near_dup.near_duplicates(clash(frame(spark, EDGES)), 2), "doc_id", "n_shingles", "component_id", "kept")
    assert got == sorted([(1, 0, 1, True), (2, 0, 2, True), (3, 0, 3, True), (4, 1, 4, True), (5, 1, 5, True), (6, 1, 5, False), (6, 1, 5, False), (7, 4, 7, True), (None, 1, None, False), (8, 1, 8, True)], key=repr)
    assert near_dup.near_duplicates(frame(spark, []), 2).count() == 0


def test_components(spark):
    edges = [(i, i + 1) for i in range(0, 40)] + [(100, 101), (7, 7), (None, 3)]
    got = {r.node: r.comp for r in components.components(frame(spark, edges, "u long, v long")).collect()}
    assert got == {**{i: 0 for i in range(41)}, 100: 100, 101: 100}
    assert components.components(frame(spark, [], "u long, v long")).count() == 0


@pytest.mark.parametrize("few", [components.FEW, 0])
def test_components_take_few_tasks_where_few_edges_are_left(spark, monkeypatch, few):
    monkeypatch.setattr(components, "FEW", few)
    made = []
    monkeypatch.setattr(components, "written", lambda df, what, f=components.written: made.append(what) or f(df, what))
    rng = np.random.default_rng(3)
    edges = [(int(a) - 300, int(b) - 300) for a, b in rng.integers(0, 600, (400, 2))] + [(5, 5), (900, None)]
    expected = brute_components({x for e in edges[:400] if e[0] != e[1] for x in e}, lambda a, b: (a, b) in edges or (b, a) in edges)
    got = components.components(frame(spark, edges, "u long, v long").repartition(7)).collect()
    assert len(got) == len(expected) and {r.node: r.comp for r in got} == expected
    assert len(made) == 2 if few else len(made) > 4


# ---------------------------------------------------------------- 4


def brute_vectors(rows, threshold=0.93):
    ok = {}
    for i, v, l in rows:
        a = np.array([np.nan if x is None else x for x in v], float) if v is not None else np.array([])
        if l is not None and i is not None and len(a) and np.isfinite(a).all() and a.any():
            ok[i] = (a, l)

    def linked(i, j):
        (a, k), (b, l) = ok[i], ok[j]
        return k == l and len(a) == len(b) and a @ b / (np.linalg.norm(a) * np.linalg.norm(b)) >= threshold

    comp = brute_components(sorted(ok), linked)
    return {i: (sum(linked(i, j) for j in ok if j != i) if i in ok else 0, comp.get(i, i)) for i, _, _ in rows}


def vectors(n=240, dim=16, seed=1):
    rng = np.random.default_rng(seed)
    out, base = [], rng.standard_normal((30, dim))
    for i in range(n):
        v = base[i % 30] + rng.standard_normal(dim) * (0.1 + 0.25 * (i % 3))
        out.append((i, [float(x) for x in np.float32(v)], int(i % 2)))
    out += [(1000, out[0][1], 0), (1001, out[0][1], 0), (1002, None, 0), (1003, [0.0] * dim, 0), (1004, [float("nan")] * dim, 0), (1005, [None] + [1.0] * (dim - 1), 0), (1006, out[0][1], None), (1007, [1.0, 2.0], 0), (1008, [2.0, 4.0], 0), (1009, [], 0), (1010, [float("inf")] * dim, 1)]
    return out


@pytest.mark.parametrize("direct,block", [(32768, 1024), (32768, 32), (8, 1024)])
def test_vectors_equal_brute_force(spark, monkeypatch, direct, block):
    monkeypatch.setattr(embedding_dup, "BLOCK", block)
    rows = vectors()
    df = frame(spark, rows, "vec_id long, embedding array<float>, label int")
    got = {r.vec_id: (r.n_links, r.component_id) for r in embedding_dup.near_vectors(df, direct=direct).collect()}
    assert got == brute_vectors(rows)


def test_vector_edges(spark):
    schema = "vec_id long, embedding array<float>, label int"
    assert embedding_dup.near_vectors(frame(spark, [], schema)).count() == 0
    got = rows_of(embedding_dup.near_vectors(frame(spark, [(None, [1.0, 0.0], 1), (1, [1.0, 0.0], 1)], schema).withColumn("rep", F.lit(1))), "vec_id", "n_links", "component_id", "kept")
    assert got == sorted([(None, 0, None, False), (1, 0, 1, True)], key=repr)


def test_estimates_are_unbiased_and_bounded():
    rng = np.random.default_rng(0)
    o = rng.standard_normal((2000, 64))
    q = o * 0.9 + rng.standard_normal(o.shape) * 0.35
    o, q = (x / np.linalg.norm(x, axis=1)[:, None] for x in (o, q))
    rotate = embedding_dup.rotation(64)
    assert np.allclose(rotate @ rotate.T, np.eye(64))
    codes, factor = embedding_dup.encode(o, rotate)
    guess = np.array([embedding_dup.estimate(codes[i : i + 1], factor[i : i + 1], q[i : i + 1], rotate)[0, 0] for i in range(len(o))])
    real = (o * q).sum(1)
    assert abs((guess - real).mean()) < 0.005
    near = real >= 0.93
    assert near.any() and (guess[near] >= embedding_dup.least_estimate(0.93, factor[near], 64, 6.0)).all()


@pytest.mark.parametrize("n", [10**5, 10**6, 10**7])
def test_bucket_plan_misses_few_pairs(n):
    rng, rotate = np.random.default_rng(2), embedding_dup.rotation(64)
    a, b = rng.standard_normal((2, 60_000, 64))
    a /= np.linalg.norm(a, axis=1)[:, None]
    b -= (a * b).sum(1)[:, None] * a
    b = 0.93 * a + np.sqrt(1 - 0.93**2) * b / np.linalg.norm(b, axis=1)[:, None]
    common = ((a @ rotate.T >= 0) == (b @ rotate.T >= 0)).sum(1)
    bits, tables = embedding_dup.bucket_plan(n, 64, 0.93, 32_768, 1e-7)
    meet = np.array([math.comb(int(c), bits) / math.comb(64, bits) for c in range(65)])
    assert ((1 - meet[common]) ** tables).mean() <= 2e-7


@pytest.mark.parametrize("n", [10**5, 10**6, 10**7])
def test_buckets_never_hold_more_pairs_than_the_label(n):
    bits, tables = embedding_dup.bucket_plan(n, 64, 0.93, 32_768, 1e-7)
    assert tables <= 2**bits


@pytest.mark.parametrize("blocks", [1, 2, 3, 4, 7, 10])
def test_blocks_meet_once_and_rows_are_copied_little(spark, blocks):
    rows, met = spark.createDataFrame([(i, blocks) for i in range(blocks)], "own int, blocks int"), []
    for steps in embedding_dup._rounds(blocks):
        sent = [(r.own, *r.to) for r in rows.select("own", F.explode(embedding_dup._meetings(steps)).alias("to")).collect()]
        assert max(sum(x[0] == i for x in sent) for i in range(blocks)) <= 3
        groups = {}
        for own, step, a, _ in sent:
            groups.setdefault((step, a), []).append(own)
        met += [tuple(sorted(g)) if step else (g[0], g[0]) for (step, _), g in groups.items()]
        assert all(len(g) == (2 if step else 1) for (step, _), g in groups.items())
    assert sorted(met) == [(i, j) for i in range(blocks) for j in range(i, blocks)]


def test_buckets_find_links_once(spark):
    rows = vectors(400, 64, 5)
    df = frame(spark, rows, "vec_id long, embedding array<double>, label int")
    assert embedding_dup.bucket_plan(200, 64, 0.93, 2, 0.05)[1] > 2
    links = {r.vec_id: r.n_links for r in embedding_dup.near_vectors(df, direct=2, miss=0.05).collect()}
    real = {i: n for i, (n, _) in brute_vectors(rows).items()}
    assert all(links[i] <= real[i] for i in real) and sum(links.values()) >= 0.9 * sum(real.values()) > 0


# ---------------------------------------------------------------- 5


def brute_removal(docs, width):
    first, words = {}, {}
    for i in sorted(docs):
        words[i] = (docs[i] or "").encode().split()
        for s in range(len(words[i]) - width + 1):
            first.setdefault(tuple(words[i][s : s + width]), (i, s))
    out = {}
    for i, w in words.items():
        gone = {p for s in range(len(w) - width + 1) if first[tuple(w[s : s + width])] < (i, s) for p in range(s, s + width)}
        out[i] = (len(w), len(gone), hashlib.sha256(b" ".join(x for p, x in enumerate(w) if p not in gone)).hexdigest())
    return out


def passages(seed=2):
    rng = random.Random(seed)
    shared = [" ".join(rng.choice("abcdefgh") + str(rng.randint(0, 50)) for _ in range(n)) for n in (19, 20, 21, 45, 80)]
    docs = {}
    for i in range(60):
        parts = []
        for _ in range(rng.randint(1, 5)):
            parts.append(rng.choice(shared) if rng.random() < 0.6 else " ".join(str(rng.randint(0, 10**6)) for _ in range(rng.randint(1, 30))))
        docs[i] = rng.choice([" ", "\n", "\t "]).join(parts)
    docs |= {100: "same " * 70, 101: "x y " * 40, 102: "x y " * 30 + "z", 103: docs[3], 104: None, 105: "", 106: "a b"}
    return docs


@pytest.mark.parametrize("shard, hot", [(4096, 10_000), (1, 10_000), (4096, 1), (1, 1)])
def test_removal_equals_brute_force(spark, monkeypatch, shard, hot):
    monkeypatch.setattr(substring_dup, "SHARD", shard)
    monkeypatch.setattr(substring_dup, "HOT_ROWS", hot)
    docs = passages()
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in substring_dup.removal(clash(frame(spark, list(docs.items()))), 20).collect()}
    assert got == brute_removal(docs, 20)


def test_cut_text_and_edges(spark):
    passage = " ".join(f"p{i}" for i in range(60))
    docs = clash(frame(spark, [(1, f"first {passage} end"), (2, f"  second\n{passage}\tfin "), (3, None), (4, "short"), (4, "short"), (None, passage)]))
    out = substring_dup.remove_repeats(docs, 40)
    assert out.columns == docs.columns
    assert rows_of(out, "doc_id", "text") == sorted([(1, f"first {passage} end"), (2, "  second\nfin "), (3, None), (4, "short"), (4, "short"), (None, passage)], key=repr)
    assert substring_dup.removal(frame(spark, []), 20).count() == 0
    known = substring_dup.remove_known(docs, [passage], 20)
    assert {r.doc_id: r.n_removed for r in known.where("doc_id IS NOT NULL").collect()} == {1: 60, 2: 60, 3: 0, 4: 0}


def test_automaton_statistics_equal_brute_force():
    rng = random.Random(1)
    for _ in range(40):
        refs = [[rng.randint(0, 3) for _ in range(rng.randint(0, 12))] for _ in range(3)]
        a = substring_dup.SuffixAutomaton()
        for r in refs:
            a.add(r)
        q = [rng.randint(0, 3) for _ in range(15)]
        known = {tuple(r[i:j]) for r in refs for i in range(len(r)) for j in range(i + 1, len(r) + 1)}
        assert a.statistics(q) == [max([n for n in range(1, i + 2) if tuple(q[i + 1 - n : i + 1]) in known], default=0) for i in range(len(q))]


def test_substring_ids_with_several_texts(spark):
    rng = random.Random(5)
    a, b = (" ".join(f"{p}{rng.randint(0, 999)}" for _ in range(60)) for p in "ab")
    rows = [(1, a), (2, a), (2, b), (2, a), (3, "x " + b), (4, None), (None, a)]
    got = [(r.doc_id, r.n_words, r.n_removed) for r in substring_dup.removal(frame(spark, rows), 20).collect()]
    assert sorted(got, key=repr) == sorted([(1, 60, 0), (2, 60, 60), (2, 60, 60), (2, 60, 0), (3, 61, 60), (4, 0, 0), (None, 60, 0)], key=repr)
    clashing = frame(spark, rows).withColumns({c: F.lit(c) for c in ("spots", "_spots", "sub", "their_id", "digest", "pos")})
    kept = substring_dup.remove_repeats(clashing, 20)
    assert kept.columns == clashing.columns
    assert rows_of(kept, "doc_id", "text", "_spots") == sorted([(1, a, "_spots"), (2, "", "_spots"), (2, "", "_spots"), (2, b, "_spots"), (3, "x ", "_spots"), (4, None, "_spots"), (None, a, "_spots")], key=repr)


def test_decontamination_keeps_what_is_consistent_around_a_conflict(spark):
    item = "If Anna walks 12 km in 3 hours then how far does Anna walk in 9 hours when the road stays flat and the weather is fine and nothing else slows her down on the way home before 5"
    changed = item.replace("Anna walks", "Boris walks").replace("does Anna", "does Boris").replace("12 km", "14 km").replace("before 5", "before 14")
    table = decontaminate.item_windows([(1, item)], 10, 5, 6)
    count = lambda text: decontaminate.matches(text, table, decontaminate.WordForms()).get(0, 0)
    whole = count(changed.replace("before 14", "before 7"))
    assert 10 < count(changed) <= whole <= count(item)


# ---------------------------------------------------------------- 6 and 7


def test_language_held_out(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = queries.op6_language_id(spark, sf).join(docs.select("doc_id", "lang"), "doc_id").where("held_out")
    n, right = got.agg(F.count("*"), F.count(F.when(F.col("lang") == F.col("lang_pred"), 1))).first()
    assert n > 20 and right / n >= 0.95
    assert queries.op6_language_id(spark, sf).count() == docs.count()


def test_language_equals_plain_dictionaries(spark, sf):
    """The whole query against counts, posteriors and backoff in plain dictionaries (all labelled rows are in the sample)."""
    import re
    from collections import Counter

    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "lang").collect()
    held = lambda d: zlib.crc32(str(d).encode()) % 5 == 0
    find = re.compile(r"[^\W\d_]+").findall
    counts = {}
    for r in docs:
        if not held(r.doc_id) and r.text is not None and r.lang is not None:
            for w in find(r.text.lower()):
                marked = f"^{w}$"
                grams = [marked[i : i + n] for n in range(1, 6) for i in range(len(marked) - n + 1)]
                for kind, key in [(0, w), *((1, g) for g in grams)]:
                    counts.setdefault((kind, key), Counter())[r.lang] += 1
    langs = sorted({r.lang for r in docs if r.lang is not None and r.text is not None and not held(r.doc_id)})
    known = {k: c for k, c in counts.items() if sum(c.values()) >= (4, 3)[k[0]]}
    totals = [{l: sum(c[l] for k, c in known.items() if k[0] == kind) + 0.5 * sum(k[0] == kind for k in known) for l in langs} for kind in (0, 1)]

    def logs(kind, key):
        x = [math.log((known[kind, key][l] + 0.5) / totals[kind][l]) for l in langs]
        norm = math.log(sum(map(math.exp, x)))
        return [max(-6.0, v - norm) for v in x]

    def word(w):
        if (0, w) in known:
            return logs(0, w)
        marked = f"^{w}$"
        for n in (5, 4, 3, 2, 1):
            hits = [logs(1, g) for i in range(len(marked) - n + 1) if (1, g := marked[i : i + n]) in known]
            if hits:
                return [sum(x) / len(hits) for x in zip(*hits)]
        return [0.0] * len(langs)

    got = {r.doc_id: r for r in queries.op6_language_id(spark, sf).collect()}
    assert len(got) == len(docs)
    for r in docs:
        words = [w for t in (r.text or "").split() for w in find(t.lower())]
        own = got[r.doc_id]
        assert own.held_out == held(r.doc_id)
        if not words:
            assert (own.lang_pred, own.score) == ("und", 0.0)
            continue
        mean = [sum(x) / len(words) * min(len(words), 20) for x in zip(*map(word, words))]
        p = [math.exp(m - max(mean)) for m in mean]
        assert own.lang_pred == langs[p.index(max(p))] and abs(own.score - max(p) / sum(p)) < 1e-4


def test_language_learns_long_words(spark):
    long = {"a": "kala" * 40, "b": "mori" * 40}
    model = language_id.train(frame(spark, [(i, long["ab"[i % 2]], "ab"[i % 2]) for i in range(20)], "doc_id long, text string, lang string"))
    got = language_id.predict(frame(spark, [(1, "x" * 60 + "mori" * 9), (2, long["a"])]), model).collect()
    assert {r.doc_id: r.lang_pred for r in got} == {1: "b", 2: "a"}


def test_language_edges(spark):
    train = [(i, "the cat and the dog" if i % 2 else "der hund und die katze", "en" if i % 2 else "de") for i in range(40)] + [(50, None, "en"), (51, "x", None)]
    model = language_id.train(frame(spark, train, "doc_id long, text string, lang string"))
    got = {r.doc_id: (r.lang_pred, r.score) for r in language_id.predict(clash(frame(spark, EDGES[:4] + [(10, "the dog"), (11, "hunde"), (12, "12 34 !!")])), model).collect()}
    assert all(got[i] == ("und", 0.0) for i in (1, 2, 3, 12))
    assert got[10][0] == "en" and got[11][0] == "de" and 0 <= got[10][1] <= 1
    none = language_id.train(frame(spark, [], "doc_id long, text string, lang string"))
    assert language_id.predict(frame(spark, [(1, "abc")]), none).first().lang_pred == "und"
    kept = language_id.accepted(clash(frame(spark, EDGES)), model)
    assert kept.where("doc_id IN (1, 2, 3)").count() == 0


def test_toxicity_held_out(spark):
    d = "/root/testdata/sf0.1"  # the smaller tables hold fewer than 15 toxic documents to judge by
    got = queries.op7_toxicity(spark, d).join(spark.read.parquet(f"{d}/labels.parquet").select("doc_id", "toxic"), "doc_id").where("held_out").select("score", "toxic").collect()
    pairs = [(a.score > b.score) + 0.5 * (a.score == b.score) for a in got if a.toxic == 1 for b in got if b.toxic == 0]
    assert sum(pairs) / len(pairs) > 0.94


TOXIC = [(i, "you idiot and clown so rare" if i % 3 == 0 else "a nice day, and you -- too", int(i % 3 == 0)) for i in range(90)] + [(200, None, 1), (201, "x", None)]


def _toxic_frames(spark, rows, more=()):
    return frame(spark, [r[:2] for r in rows] + list(more)), frame(spark, [(r[0], r[2]) for r in rows], "doc_id long, toxic int")


def test_toxicity_edges(spark):
    docs, labels = _toxic_frames(spark, TOXIC)
    model = toxicity.train(clash(docs), clash(labels))
    got = {r.doc_id: r for r in toxicity.score(clash(frame(spark, EDGES + [(20, "such an idiot clown"), (21, "a nice day"), (22, "... !!")])), model).collect()}
    assert got[20].score > got[21].score and got[20].predicted == 1 and got[21].predicted == 0
    assert all(0 <= r.score <= 1 for r in got.values()) and got[1].score == got[2].score == got[22].score
    assert toxicity.score(frame(spark, EDGES), model).count() == len(EDGES)
    for part, predicted in ((TOXIC[1:3], 0), (TOXIC[:1], 1)):
        one = toxicity.train(*_toxic_frames(spark, part))
        assert toxicity.score(frame(spark, [(1, "x")]), one).first().predicted == predicted
    none = toxicity.train(frame(spark, []), frame(spark, [], "doc_id long, toxic int"))
    assert toxicity.score(frame(spark, []), none).count() == 0


def test_toxicity_models_are_probabilities_and_equal_plain_dictionaries(spark):
    """Counts, discounts and backoff again in dictionaries; every context's distribution sums to one."""
    from collections import Counter, defaultdict

    more = [(300, "an unlabelled idiot walks so rare a nice clown"), (301, None), (302, "and and and")]
    docs, labels = _toxic_frames(spark, TOXIC, more)
    model = toxicity.train(docs, labels)
    curve = {r.doc_id for r in docs.where(F.pmod(F.xxhash64(F.lit("curve"), "doc_id"), F.lit(4)) == 0).collect()}
    words_of = lambda t: [w for x in t.split() if (w := toxicity._word(x))]
    uni, bi, before = (Counter(), Counter()), (Counter(), Counter()), defaultdict(set)
    for _, text, *_ in [*TOXIC, *more]:
        for a, b in zip(words_of(text or ""), words_of(text or "")[1:]):
            before[b].add(a)
    for i, text, y in TOXIC:
        if text is not None and y is not None and i not in curve:
            uni[y].update(words_of(text))
            bi[y].update(zip(words_of(text), words_of(text)[1:]))
    known = sorted({*uni[0], *uni[1]})
    bit = lambda w: int(toxicity.left_bit(np.array([toxicity._hashed(w)], np.uint64))[0])
    follows = {w: float(toxicity.contexts_from(np.array([len({bit(v) for v in before[w]})]))[0]) for w in known}
    assert all(abs(n - len({bit(v) for v in before[w]})) < 0.1 for w, n in follows.items())
    unknown = sum(w not in known for _, text, *_ in [*TOXIC, *more] for w in words_of(text or "")[1:])
    every = sum(follows.values()) + unknown + 0.5 * (len(known) + 1)
    shared = lambda w: (follows.get(w, 0) + 0.5) / every
    outside = unknown / every

    def alone(y, w):
        t = sum(uni[y].values())
        return max(uni[y][w] - 0.75, 0) / t + 0.75 * len(uni[y]) / t * shared(w)

    def given(y, v, w):
        n = sum(c for (a, _), c in bi[y].items() if a == v)
        if not n:
            return alone(y, w)
        return max(bi[y][v, w] - 0.75, 0) / n + 0.75 * sum(a == v for a, _ in bi[y]) / n * alone(y, w)

    for y in (0, 1):
        rest = 0.75 * len(uni[y]) / sum(uni[y].values()) * outside  # unknown words beyond the class of their own
        assert abs(sum(alone(y, w) for w in [*known, "?"]) + rest - 1) < 1e-9
        for v in known:
            n = sum(c for (a, _), c in bi[y].items() if a == v)
            own = rest * (0.75 * sum(a == v for a, _ in bi[y]) / n if n else 1)
            assert abs(sum(given(y, v, w) for w in [*known, "?"]) + own - 1) < 1e-9
    text = "so rare an idiot, and a nice clown you see -- and you too"
    a, g = model.differences(model.numbers(np.array([toxicity._hashed(t) for t in text.split()], np.uint64)))
    words = words_of(text)
    assert np.allclose(a, [math.log(alone(1, w) / alone(0, w)) for w in words], atol=1e-5)
    assert np.allclose(g[1:], [math.log(given(1, v, w) / given(0, v, w)) for v, w in zip(words, words[1:])], atol=1e-5)


def test_toxicity_words_are_hashed_without_splitting(monkeypatch):
    """The words of ``split``, in order; one hash per word wherever it stands, also where a text is cut or texts share a call."""
    rng, seen = random.Random(7), {}
    odd = "aaB.'\"-( \u03a3\u0130\u00a0\u3000\u2014\x85\x1c\u00df\U0001f600\n\t "
    for piece in (1 << 17, 11, 1):
        monkeypatch.setattr(toxicity, "PIECE", piece)
        for _ in range(400):
            texts = [None, *("".join(rng.choice(odd) for _ in range(rng.randint(0, 50))) for _ in range(rng.randint(0, 3))), "Day, -- day"]
            for text, hashes in zip(texts, toxicity.hashed_words(texts), strict=True):
                words = [w for x in (text or "").split() if (w := toxicity._word(x))]
                assert len(words) == len(hashes)
                assert all(seen.setdefault(w, h) == h for w, h in zip(words, hashes.tolist()))
    assert len(set(seen.values())) == len(seen) > 1000 and 0 not in seen.values()
    assert toxicity._hashed("(Day)") == seen["day"] and toxicity._hashed("--") == 0


def test_toxicity_learns_from_every_labelled_row(spark):
    n = 10_000
    docs = spark.range(n).select(F.col("id").alias("doc_id"), F.concat(F.lit("own"), "id", F.lit(" common "), F.when(F.col("id") % 2 == 0, "idiot").otherwise("day")).alias("text"))
    model = toxicity.train(docs, docs.select("doc_id", (F.col("doc_id") % 2 == 0).cast("int").alias("toxic")))
    counted = [r.doc_id for r in docs.where(F.pmod(F.xxhash64(F.lit("curve"), "doc_id"), F.lit(4)) != 0).collect()]
    own = model.numbers(np.array([toxicity._hashed(f"own{i}") for i in counted], np.uint64))
    assert (own > 0).all() and len(model.words) > 0.95 * len(counted)
    got = {r.doc_id: r.predicted for r in toxicity.score(docs.limit(50), model).collect()}
    assert all(p == (i % 2 == 0) for i, p in got.items())


# ---------------------------------------------------------------- 8


def test_warc_round_trip(spark, tmp_path):
    rows = [(3, "http://a", "<p>é</p>"), (1, "http://b", "<p>é</p>"), (2, None, None), (4, "http://c", ""), (5, "http://d\r\nX: y", "big" * 10000), (1, "http://b", "<p>é</p>"), (None, "http://e", "z")]
    df = frame(spark, rows, "page_id long, url string, html string")
    folder = f"file://{tmp_path}/warc"
    (tmp_path / "warc").mkdir()
    index = warc.write(clash(df), folder, 0, roll=200)
    got = warc.read(index)
    by = {(r.page_id, r.record_type): r for r in got.collect()}
    assert by[(3, "revisit")].refers_to == 1 and by[(4, "revisit")].refers_to == 2 and by[(1, "response")].payload == "<p>é</p>".encode()
    assert got.count() == 7 and by[(5, "response")].payload_bytes == 30000 and by[(2, "response")].payload_bytes == 0
    assert by[(2, "response")].payload_digest == "3I42H3S6NNFQ2MSVX7XZKYAYSCX5QBYJ"
    some = warc.read(index.where("page_id = 5"))
    assert [r.page_id for r in some.collect()] == [5]
    assert warc.round_trip(df, 9).where("record_type = 'revisit'").count() == 1  # the empty ones are too small to refer
    assert warc.round_trip(df.limit(0)).count() == 0


# ---------------------------------------------------------------- 2


ITEM = "If Anna walks 12 km in 3 hours then how many km does Anna walk in 5 hours on the same road"


def test_templates_catch_other_values(spark):
    bench = frame(spark, [(7, ITEM), (8, None), (9, "short one")], "item_id long, text string")
    other = ITEM.replace("Anna", "Boris").replace("12", "40").replace("3 ", "8 ")
    broken = ITEM.replace("Anna", "Boris", 1).replace("in 3 hours then", "in 3 hours then")
    docs = [(1, f"Intro. {ITEM} End."), (2, f"Intro: {other}"), (3, "nothing of that kind at all here, only other words in a row"), (4, broken), (5, None), (6, ""), (6, ITEM.lower().replace("anna", "Anna"))]
    got = {(r.doc_id, r.item_id) for r in decontaminate.contaminated(clash(frame(spark, docs)), bench).collect()}
    assert {(1, 7), (2, 7), (6, 7)} <= got and not {d for d, _ in got} & {3, 4, 5}
    left = decontaminate.clean(clash(frame(spark, docs)), bench)
    assert sorted(r.doc_id for r in left.collect()) == [3, 4, 5, 6] and left.columns == clash(frame(spark, docs)).columns
    assert decontaminate.contaminated(frame(spark, docs), bench.limit(0)).count() == 0 and decontaminate.contaminated(frame(spark, []), bench).count() == 0


def test_decontamination_equals_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()
    items = spark.read.parquet(f"{sf}/benchmark.parquet").select("item_id", "text").collect()
    planted = {(d.doc_id, i.item_id) for d in docs for i in items if i.text in d.text}
    got = {(r.doc_id, r.item_id) for r in queries.op2_decontamination(spark, sf).collect()}
    assert planted <= got
    form = lambda t: [c for w in t.split() if (c := decontaminate.canonical(w))]
    for doc, item in got - planted:  # anything more shares ten words of template
        a, b = (form(next(x.text for x in xs if x[0] == k)) for xs, k in ((docs, doc), (items, item)))
        assert {tuple(a[i : i + 10]) for i in range(len(a) - 9)} & {tuple(b[i : i + 10]) for i in range(len(b) - 9)}


def test_copies_in_other_case_equal_brute_force(spark, sf):
    fold = lambda t: [x for w in t.casefold().split() if (x := w.strip(".,;:!?()\"'")) and any(map(str.isalnum, x))]
    grams = lambda w: {tuple(w[i : i + 10]) for i in range(len(w) - 9)}
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").select("item_id", "text").limit(40).collect()]
    docs = []
    for i, (_, t) in enumerate(items):
        w = t.split()
        docs += [(4 * i, f"before {t.upper()} after"), (4 * i + 1, f"before {t.lower()} after"), (4 * i + 2, " ".join(w[:11]).swapcase()), (4 * i + 3, f"before {t.lower()} {' '.join(w[:8])}")]
    have = {i: grams(fold(t)) for i, t in items}
    expected = {(d, i) for d, t in docs for i, g in have.items() if g & grams(fold(t))}
    assert expected >= {(4 * k + j, i) for k, (i, t) in enumerate(items) if len(fold(t)) >= 10 for j in (0, 1, 3)}
    bench = frame(spark, items, "item_id long, text string")
    got = {(r.doc_id, r.item_id) for r in decontaminate.contaminated(frame(spark, docs), bench).collect()}
    assert expected <= got
    assert not {d for d, _ in expected} & {r.doc_id for r in decontaminate.clean(frame(spark, docs), bench).collect()}


def test_lower_case_with_other_values_and_few_literals(spark):
    bench = frame(spark, [(7, ITEM), (8, "Anna Bell Carl Dora Emil Fred 12 14 15 17 Gus")], "item_id long, text string")
    docs = [(1, ITEM.lower().replace("12", "40")), (2, ITEM.upper().replace("12", "40")), (3, "anna bell carl dora emil fred 12 14 15 17 gus"), (4, "Ina Bo Cy Di Ed Flo 1 2 3 4 Gil")]
    assert rows_of(decontaminate.contaminated(frame(spark, docs), bench), "doc_id", "item_id") == [(1, 7), (2, 7), (3, 8)]


def test_blocks_of_a_large_benchmark(spark, sf, monkeypatch):
    whole = rows_of(queries.op2_decontamination(spark, sf), "doc_id", "item_id", "n_windows")
    monkeypatch.setattr(decontaminate, "BLOCK_WINDOWS", 300)
    assert rows_of(queries.op2_decontamination(spark, sf), "doc_id", "item_id", "n_windows") == whole


# ---------------------------------------------------------------- 10


def test_license_edges(spark):
    mit = license_scan.TEMPLATES["MIT"][1]
    docs = EDGES + [(20, f"code\n\n{mit[:200]}\n{mit[200:]}\n\nmore"), (21, "x\nReleased under the MIT license!\ny"), (22, "Released under no license")]
    got = rows_of(license_scan.scan(clash(frame(spark, docs))), "doc_id", "license")
    assert got == [(20, "MIT"), (21, "MIT")]
    assert license_scan.scan(frame(spark, [])).count() == 0


def test_licenses_inside_lines_and_whole_texts(spark):
    full = {name: texts[0] for name, texts in license_scan.FULL_TEXTS.items()}
    w = full["MIT"].split()
    header = "\n#\n".join("# " + " ".join(w[i : i + 9]) for i in range(0, len(w), 9))
    notice = license_scan.TEMPLATES["Apache-2.0"][0].split()
    docs = [(1, "This text may be reused. Licensed under CC BY 4.0."), (2, full["MIT"]), (3, f"/* x\n *\n{header}\n#\n# code */"), (4, f"of lines {' '.join(notice[:4])}\n{' '.join(notice[4:])} and more words"), (5, "licensed or under no licence by the 4.0 rule of CC, the public may copy")]
    docs += [(10 + i, f"some words before {t} and some after") for i, t in enumerate(full.values())]
    got = {}
    for r in license_scan.scan(frame(spark, docs)).collect():
        got.setdefault(r.doc_id, {})[r.license] = r.dice
    assert got[1] == {"CC-BY-4.0": 1.0} and got[2] == got[3] == {"MIT": 1.0} and got[4] == {"Apache-2.0": 1.0} and 5 not in got
    assert all(got[10 + i][name] == 1.0 for i, name in enumerate(full))


def test_license_windows_equal_brute_force():
    rng = random.Random(4)
    templates = (("x", "a b c d e"), ("y", "b c d e f g h i"), ("y", "a a b"), ("z", "c d"))
    for _ in range(200):
        words = [rng.choice("abcdefghi") if rng.random() < 0.4 else "abcdefghi"[i % 9] for i in range(rng.randint(0, 30))]
        want = {}
        for name, t in templates:
            n, g = len(t.split()), license_scan.bigrams(t)
            for i in range(max(len(words) - n, 0) + 1):
                o = license_scan.bigrams(" ".join(words[i : i + n])) if len(words) > 1 else frozenset()
                if o and 2 * len(o & g) / (len(o) + len(g)) >= 0.8:
                    want[name] = max(want.get(name, 0), 2 * len(o & g) / (len(o) + len(g)))
        assert license_scan.window_matches("\n".join(words), templates, 0.8) == want


# ---------------------------------------------------------------- queries against SQL, and the pipeline


@pytest.mark.parametrize("name", sorted(queries.ORACLE_SQL))
def test_query_equals_sql(name, spark, sf, duck):
    from rowcheck import same_rows

    same_rows(queries.QUERIES[name](spark, sf), duck, queries.ORACLE_SQL[name])


def test_pipeline_stages(spark, sf):
    import corpus_pipeline as p

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    extra = docs.limit(1).select(F.lit(10**9).cast("long").alias("doc_id"), F.lit("123 456").alias("text"), "lang", "source", "n_chars")
    now = docs.unionByName(extra).cache()
    names = [n for n, _ in p.STAGES]
    assert names == ["language_id", "near_duplicates", "substring_dedup", "decontamination", "packing"]
    a = p.keep_known_languages(spark, now, sf).cache()
    assert a.columns == now.columns and a.where("doc_id = 1000000000").count() == 0 and a.count() >= docs.count() - 2
    b = p.keep_one_of_each(spark, a, sf).cache()
    texts = {r.doc_id: r.text for r in a.collect()}
    sets = {i: {tuple(t.lower().split()[j : j + 5]) for j in range(len(t.split()) - 4)} or {t} for i, t in texts.items()}
    comp = brute_components(list(texts), lambda x, y: 100 * len(sets[x] & sets[y]) >= 80 * len(sets[x] | sets[y]))
    assert {r.doc_id for r in b.collect()} == set(comp.values())
    c = p.cut_repeated_passages(spark, b, sf).cache()
    kept = {r.doc_id: r.text for r in b.collect()}
    brute = brute_removal(kept, p.PASSAGE)
    for r in c.collect():
        w = r.text.encode().split()
        assert hashlib.sha256(b" ".join(w)).hexdigest() == brute[r.doc_id][2]
    e = p.keep_clean_of_benchmarks(spark, c, sf)
    items = [r.text for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    assert not [r for r in e.collect() if any(i in r.text for i in items)]
    assert e.columns == docs.columns and e.count() > 0.8 * c.count()
    check_packing(p.pack_sequences(spark, e, sf).collect(), {r.doc_id: r.text for r in e.collect()})
    doubled = p.keep_one_of_each(spark, b.union(b), sf)
    assert doubled.count() == b.count()
