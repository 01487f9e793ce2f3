import re
from collections import defaultdict

import numpy as np
from lexfold.llm import ngram_join as J

SCHEMA = "doc_id long, text string, n string, id string"


def brute(rows, width=4, percent=85):
    """(n_shingles, component) by doc_id over all pairs that share a shingle."""
    sets = {}
    for d, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        sets[d] = {tuple(w[i : i + width]) for i in range(len(w) - width + 1)} if len(w) >= width else ({tuple(w)} if w else set())
    index = defaultdict(set)
    for d, s in sets.items():
        for x in s:
            index[x].add(d)
    up = {d: d for d in sets}

    def top(d):
        while up[d] != d:
            d = up[d]
        return d

    for d, s in sets.items():
        for e in set().union(*(index[x] for x in s)) if s else ():
            if e > d and 100 * len(s & sets[e]) >= percent * len(s | sets[e]):
                a, b = sorted((top(d), top(e)))
                up[b] = a
    return {d: (len(s), top(d)) for d, s in sets.items()}


def near_copies(text, times, rng, start):
    words = text.split(" ")
    for k in range(times):
        w = list(words)
        for i in rng.integers(0, len(w), 1 + k % 4):
            w[i] = f"neu{k % 7}"
        yield start + k, " ".join(w)


def run(spark, rows):
    df = spark.createDataFrame([(d, t, "x", "y") for d, t in rows], SCHEMA).repartition(3)
    return {r.doc_id: (r.n_shingles, r.component_id) for r in J.jaccard_groups(df).collect()}


def test_against_all_pairs(spark, sf):
    rng = np.random.default_rng(5)
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    longest = max(rows, key=lambda r: len(r[1]))[1]
    rows += near_copies(longest, 12, rng, 10_000)
    middle = sorted((r[1] for r in rows), key=len)[len(rows) // 2]
    rows += near_copies(middle[:400], 80, rng, 20_000)
    rows += [(30_000 + i, f"one shared passage that many texts hold word by word again and again {i} " + " ".join(f"w{i}x{j}" for j in range(20))) for i in range(60)]
    rows += [(-5, "Just Three\twords"), (-4, "just three words"), (-3, "just  three\nwords"), (-2, ""), (-1, None), (40_000, " \n"), (40_001, "Ärger Mit Dem")]
    assert run(spark, rows) == brute(rows)


def test_empty_and_null_ids(spark):
    assert run(spark, []) == {}
    df = spark.createDataFrame([(None, "a b c d e"), (3, "a b c d e"), (3, "a b c d e"), (2, "a b c d e")], "doc_id long, text string")
    got = sorted(((r.doc_id, r.component_id) for r in J.jaccard_groups(df).collect()), key=str)
    assert got == [(2, 2), (3, 2), (3, 2), (None, None)]


def test_tree_bound_loses_nothing():
    rng = np.random.default_rng(1)
    base = rng.integers(0, 2**63, 300, dtype=np.uint64)
    sets = [np.unique(np.concatenate((base[rng.random(300) < 0.96], rng.integers(0, 2**63, 9, dtype=np.uint64)))) for _ in range(150)]
    vectors = [J.vector_of(J.count_vector(s), len(s)) for s in sets]
    sizes = np.array([len(s) for s in sets])
    ids = np.arange(150)
    got = {tuple(x) for found in J.block_pairs(ids, ids, sizes, np.ones(150, bool), vectors, 85) for x in found.tolist()}
    for i in range(150):
        for j in range(i + 1, 150):
            shared = len(np.intersect1d(sets[i], sets[j]))
            if 100 * shared >= 85 * (len(sets[i]) + len(sets[j]) - shared):
                assert (i, j) in got


def test_random_sets_are_pruned():
    rng = np.random.default_rng(2)
    sets = [np.unique(rng.integers(0, 2**63, 400, dtype=np.uint64)) for _ in range(100)]
    ids = np.arange(100)
    assert not list(J.block_pairs(ids, ids, np.array([len(s) for s in sets]), np.ones(100, bool), [J.vector_of(J.count_vector(s), len(s)) for s in sets], 85))


def test_one_id_with_different_texts(spark, monkeypatch):
    """Of each group a document stays, and a text is never lost to another text of its doc_id."""
    monkeypatch.setattr(J, "CHUNK", 2)
    text = lambda k, end="": " ".join(f"{k}w{i}" for i in range(120)) + end
    rows = [(5, text("a")), (5, text("b")), (3, text("b", " x")), (7, text("c")), (None, text("b")), *((20 + k, text("b", f" y{k}")) for k in range(9))]
    df = spark.createDataFrame([(d, t, "v", 1) for d, t in rows], "doc_id long, text string, shingles string, id int").repartition(3)
    got = J.one_of_each_group(df)
    assert got.columns == df.columns
    assert {(r.doc_id, r.text) for r in got.collect()} == {(5, text("a")), (3, text("b", " x")), (7, text("c")), (None, text("b"))}


def test_links_are_all_counted(spark, sf, monkeypatch):
    rng = np.random.default_rng(7)
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    middle = sorted((r[1] for r in rows), key=len)[len(rows) // 2]
    rows += near_copies(middle[:500], 90, rng, 20_000)
    rows += [(30_000 + i, t) for i, t in enumerate([rows[0][1]] * 3)] + [rows[0], (None, rows[0][1])]
    sets = {d: J.shingle_sets([(t or "").encode()], 4).__next__() for d, t in rows if d is not None}
    want = dict.fromkeys(sets, 0)
    for a in sets:
        for b in sets:
            shared = len(np.intersect1d(sets[a], sets[b], assume_unique=True)) if a != b else 0
            want[a] += shared > 0 and 100 * shared >= 85 * (len(sets[a]) + len(sets[b]) - shared)
    assert max(want.values()) > 20
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    for tile in (J.TILE_SHINGLES, 1_000):
        monkeypatch.setattr(J, "TILE_SHINGLES", tile)
        got = J.jaccard_groups(df).collect()
        assert {r.doc_id: r.n_links for r in got if r.doc_id is not None} == want
        assert [r.n_links for r in got if r.doc_id is None] == [0]
    # Three texts that link pairwise have two links each.
    three = [(i, " ".join(f"w{k}" for k in range(200)) + f" end{i}") for i in range(3)]
    assert [r.n_links for r in J.jaccard_groups(spark.createDataFrame(three, "doc_id long, text string")).collect()] == [2, 2, 2]
