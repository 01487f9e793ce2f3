import random

import pytest
from lexfold.functions import measures as M
from lexfold.functions import text as T
from lexfold.operators.prompts import NoisyReader
from pyspark.sql import functions as F


def slow(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


def test_edit_distance():
    assert M.edit_distance("kitten", "sitting") == 3
    rng = random.Random(1)
    for _ in range(300):
        a, b = ("".join(rng.choice("abé") for _ in range(rng.randrange(12))) for _ in range(2))
        assert M.edit_distance(a, b) == slow(a, b)


def test_common_subsequence():
    assert M.common_subsequence("a b c d".split(), "a c d".split()) == 3
    assert M.common_subsequence([], ["a"]) == M.common_subsequence(["a"], []) == 0


PAIRS = [("kitten", "sitting", 1 - 3 / 7), ("", "", 1.0), ("abc", "", 0.0), ("é", "e", 0.0)]


@pytest.mark.parametrize(("r", "h", "want"), PAIRS)
def test_levenshtein(spark, r, h, want):
    d = spark.createDataFrame([(r, h)], "r string, h string")
    assert d.select(M.lev_sim("r", "h"), M.lev_sim_long("r", "h")).first() == pytest.approx((want, want))


def test_rouge_and_bleu(spark):
    d = spark.createDataFrame([(1, "a b c d", "a c d"), (2, "", ""), (3, "a b", "a b"), (4, "x", "")], "k int, ref string, hyp string")
    r = {x.k: x for x in M.rouge_n(d, ["k"]).collect()}
    assert (r[1].recall, r[1].precision, r[2].recall, r[3].f1, r[4].recall) == (0.75, 1.0, 1.0, 1.0, 0.0)
    b = {x.k: x.bleu for x in M.bleu(d, ["k"]).collect()}
    assert b[2] == 1 and b[3] == pytest.approx(1) and b[4] == 0 and 0 < b[1] < 1
    assert d.select(M.rouge_l("ref", "hyp").alias("v")).where("v = 0.75").count() == 1


def test_measures_of_shards_equal_those_of_rows(spark):
    rng = random.Random(4)
    words = lambda: " ".join(rng.choice("abcdé") for _ in range(rng.randrange(9)))
    d = spark.createDataFrame([(i, words(), words()) for i in range(120)], "k int, ref string, hyp string")
    rows = {x.k: (x.recall, y.bleu) for x, y in zip(M.rouge_n(d, ["k"]).orderBy("k").collect(), M.bleu(d, ["k"]).orderBy("k").collect(), strict=True)}
    for x in d.select("k", M.rouge_1_long("ref", "hyp").alias("r"), M.bleu_long("ref", "hyp").alias("b")).collect():
        assert (x.r, x.b) == pytest.approx(rows[x.k]), x


def test_prose_around_markers(spark):
    d = spark.createDataFrame([("s", "c", ["so", "<M1>", "word,", "12", "<M2>", "<M1>", "x9"])], "shard_id string, corpus string, folded array<string>")
    assert M.prose_around_markers(d).select("n_around", "n_prose").first() == (4, 2)


def test_cluster_and_shape(spark):
    d = spark.createDataFrame([("a", 3, 0.1), ("a", 4, 0.3), ("a", 5, 0.2), ("b", 3, 0.1), ("b", 4, 0.5), ("b", 5, 0.5)], "corpus string, l_max int, cr_input double")
    r = {x.corpus: x for x in M.best_lmax(d).collect()}
    assert (r["a"].best_l_max, r["a"].shape, r["b"].best_l_max, r["b"].shape, r["b"].plateau_at) == (4, "peak then decline", 4, "plateau", 4)
    got = [x[0] for x in spark.createDataFrame([(0.05,), (0.15,), (0.3,), (0.55,), (0.7,)], "v double").select(M.cluster("v")).collect()]
    assert got == ["low?", "low", "medium", "medium?", "high"]


def test_exact_whitespace(spark):
    texts = ["", " ", "a", "  a\t b \n", "a  b\n\nc d", "\f", "x y z"]
    d = spark.createDataFrame([(t,) for t in texts], "t string").select("t", T.units("t").alias("u"), T.gaps("t").alias("g"))
    assert all(r.t == r.v for r in d.select("t", T.rejoin("u", "g").alias("v")).collect())


def test_noisy_reader_is_seeded():
    system = "x\n\f\n".join(["", "<M1> = a b", "<M2> = a c"])
    one, two = NoisyReader(1, 0.5, 0.1, 0.1), NoisyReader(1, 0.5, 0.1, 0.1)
    assert one.read(system, "<M1> q <M2>") == two.read(system, "<M1> q <M2>")


def test_vocabulary_costs(spark):
    ranks = {b"a": 0, b"b": 1, b"ab": 2, b"abab": 3}
    d = spark.createDataFrame([("abab",), ("aab",), ("abab",)], "unit string")
    assert {r.unit: r.cost for r in T.vocab_costs(d, ranks).collect()} == {"abab": 1, "aab": 2}


def test_saving(spark):
    r = spark.range(1).select(T.pays_off(F.lit(3), F.lit(2), F.lit(1)).alias("a"), T.pays_off(F.lit(4), F.lit(2), F.lit(1)).alias("b"), T.break_even(F.lit(2), F.lit(1)).alias("c"), T.break_even(F.lit(1), F.lit(1)).alias("d")).first()
    assert (r.a, r.b, r.c, r.d) == (False, True, 4, None)


def test_few_differences_are_searched_from_both_texts():
    """Long texts that differ little are measured from what differs, with the same numbers."""
    import random
    from unittest import mock

    from lexfold.functions import measures as M

    rng = random.Random(4)
    kinds = [f"u{i}" for i in range(30)] + ["é", "a\xa0b", "\U0010ffff", "\U0010fffe"]
    found = []
    for n in (1, 4, 25, 90, 400):
        a = rng.choices(kinds, k=rng.randint(500, 700))
        b = list(a)
        for _ in range(n):
            i = rng.randrange(len(b))
            b[i : i + rng.randint(0, 3)] = rng.choices(kinds, k=rng.randint(0, 3))
        x, y = " ".join(a), " ".join(b)
        got = M.measures(x, y)
        assert M._few_edits(x, y, 2000) == M.edit_distance(x, y) == M._edits(x, y)
        if (kept := M._common(a, b, 2000)) is not None:
            assert sum(n for _, _, n in kept) == M.common_subsequence(a, b)
            assert all(a[i : i + n] == b[j : j + n] for i, j, n in kept)
        with mock.patch.object(M, "FEW_EDITS", -1), mock.patch.object(M, "_common", lambda *_: None):
            assert got == M.measures(x, y)
        found.append(kept is not None)
    assert any(found)
