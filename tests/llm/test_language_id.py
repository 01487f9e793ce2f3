from collections import Counter, defaultdict
from math import log2

import numpy as np
from lexfold.llm import language_id as L


def tree_bits(learn, text, order):
    """Code length by walking a context tree, longest context first."""
    tree = defaultdict(Counter)
    for t in learn:
        for i, c in enumerate(t):
            for k in range(order + 1):
                ctx = tuple(t[j] if j >= 0 else None for j in range(i - k, i))
                tree[ctx][c] += 1
    total = 0.0
    for i, c in enumerate(text):
        for k in range(order, -1, -1):
            node = tree.get(tuple(text[j] if j >= 0 else None for j in range(i - k, i)))
            if not node:
                continue
            n, kinds = sum(node.values()), len(node)
            if c in node:
                total -= log2(node[c] / (n + kinds))
                break
            total -= log2(kinds / (n + kinds))
        else:
            total += 8
    return total


def test_tables_equal_tree_walk():
    samples = {"b": [b"abracadabra", b"aab bc"], "a": ["zéro ça".encode(), b"zzz", b"x"]}
    for order in (0, 1, 2, 3):
        t = L.ContextTables({n: L.counts_of(x, order) for n, x in samples.items()})
        texts = [b"", b"abra", b"zz\xff\x00q", "ça va".encode(), b"b" * 50]
        got = t.code_lengths(texts)
        for text, row in zip(texts, got, strict=True):
            assert np.allclose(row, [tree_bits(samples[n], text, order) for n in t.names], rtol=1e-5)


def test_learning_reads_all_rows_and_is_bounded(spark):
    rows = [(i, x, n) for i, (n, x) in enumerate([("b", "abracadabra"), ("a", "zéro ça\x00"), ("b", "y" * 70_000 + "tail"), (None, "no"), ("a", None), ("c", "")] * 6)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string").repartition(3)
    learn = {n: [r.text.encode() for r in df.where(~L.held_out()).where("lang = '%s'" % n).collect() if r.text] for n in "ab"}
    got, want = L.learned(df), L.ContextTables({n: L.counts_of(x, L.ORDER) for n, x in learn.items()})
    texts = [b"abra tail", "ça".encode(), b"\xff\x00y"]
    assert got.names == ["a", "b"] and np.allclose(got.code_lengths(texts), want.code_lengths(texts))
    assert np.allclose(got.code_lengths(texts), [[tree_bits(learn[n], t, L.ORDER) for n in "ab"] for t in texts], rtol=1e-5)
    # Under a bound, what is left is a tree whose nodes have all their suffixes.
    small = L.learned(df, most_cells=got.size * 2 * 6)
    assert small.lengths.shape == (6 * small.size, 2)
    assert L.learned(df.limit(0)) is None


def test_held_out_accuracy(spark):
    d = L.op8_language_id(spark, "/root/testdata/sf0.01").join(spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), "doc_id")
    rows = d.where("held_out").select("lang", "lang_pred", "score").collect()
    assert sum(r.lang == r.lang_pred for r in rows) >= 0.97 * len(rows)
    assert all(0 <= r.score <= 1 for r in rows)


def test_cases(spark):
    docs = spark.createDataFrame([(1, None), (2, ""), (3, "12 34 --"), (None, "el perro"), (4, "x" * 100_000)], "doc_id long, text string").selectExpr("*", "'zz' as lang_pred")
    t = L.ContextTables({"en": L.counts_of([b"the dog and the cat"], 3), "es": L.counts_of([b"el perro y el gato"], 3)})
    got = {r.doc_id: r.lang_pred for r in L.identify(docs, t).collect()}
    assert got[1] == got[2] == got[3] == "und" and got[None] == "es"
    assert {r.lang_pred for r in L.identify(docs, None).collect()} == {"und"}
    assert L.identify(docs.limit(0), t).count() == 0


def test_bounded_tables_leave_nothing_out(spark):
    """Contexts beyond the tables' bound still count: code lengths are those of the whole tree."""
    rng = np.random.default_rng(5)
    words = ["ab", "abra", "ça", "dog", "perro", "zz9", "el", "the"]
    rows = [(i, " ".join(rng.choice(words, 12)), "abc"[i % 3]) for i in range(90)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    learn = {n: [r.text.encode() for r in df.where(~L.held_out()).where("lang = '%s'" % n).collect()] for n in "abc"}
    whole = L.learned(df)
    texts = [b"", b"abra cadabra", "el ça dog\xff".encode(), b"zz9 zz8 the\x00", b"qq"]
    want = [[tree_bits(learn[n], t, L.ORDER) for n in "abc"] for t in texts]
    assert np.allclose(whole.code_lengths(texts), want, rtol=1e-5)
    for rows_kept in (1, 2, 10, 40):
        small = L.learned(df, most_cells=whole.size * 3 * rows_kept)
        assert len(small.lengths) == rows_kept * small.size < len(whole.lengths)
        assert np.allclose(small.code_lengths(texts), want, rtol=1e-5)
