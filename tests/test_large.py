"""What keeps the folding queries within reach of large tables: spread numbering, one pass, no needless work."""

from pyspark.sql import functions as F

from lexfold.operators import shards as S
from lexfold.operators.kernel import Options, Shard
from lexfold.plans import catalog, catalog_text, workloads
from lexfold.sources import corpora as C


def plan(df):
    return df._jdf.queryExecution().optimizedPlan().toString()


def test_numbers_of_records_are_spread(spark, sf):
    """No task sorts the whole of lineitem."""
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    try:
        d = C.lineitem_records(spark, sf).groupBy(F.spark_partition_id().alias("p")).agg(F.count("*").alias("n"), F.collect_list("rec_id").alias("r")).collect()
    finally:
        spark.conf.unset("spark.sql.adaptive.coalescePartitions.enabled")
    ids = sorted(x for r in d for x in r.r)
    assert ids == list(range(1, len(ids) + 1))
    assert max(r.n for r in d) < 0.9 * len(ids)


def test_numbers_follow_ties_and_nulls(spark):
    rows = [(k, j) for k in (None, 1, 1, 2, 7, 7, 7, 9) for j in (2, 1)]
    d = C.numbered(spark.createDataFrame(rows, "a long, b int"), ("a", "b"), "n")
    assert [tuple(r)[:2] for r in d.select("a", "b", "n").orderBy("n").collect()] == sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1]))


def test_parts_of_numbered_corpora(spark):
    """Shards in parts are the same whether numbers are known to be 1, 2, 3 … or are counted."""
    d = spark.range(1, 1004).select(F.lit("lineitem").alias("corpus"), F.col("id").alias("rec_id"), F.lit("a").alias("text"))
    a = S.assign_shards_count(S.parts(d, 16), 10).select("rec_id", "shard_id")
    b = S.assign_shards_count(S.parts(d, 16, C.NUMBERED), 10, C.NUMBERED).select("rec_id", "shard_id")
    assert sorted(a.collect()) == sorted(b.collect())


def test_sizes_need_no_folded_units():
    s = Shard("a b c d a b c d a b c d".split())
    whole, sizes = s.fold(Options()), s.fold(Options(), full=False)
    assert whole.folded and not sizes.folded
    assert (whole.n_tok_folded, whole.n_tok_legend, len(whole.legend)) == (sizes.n_tok_folded, sizes.n_tok_legend, len(sizes.legend))


def test_ablations_fold_in_one_pass(spark, sf):
    for name in ("direction", "f_min", "order", "saving_test", "single_length"):
        assert plan(catalog.QUERIES[f"ablate_{name}"](spark, sf)).count("MapInArrow") == 1


def test_one_length_alone(spark):
    """`4 alone` folds runs of four, not of four to ten."""
    d = spark.createDataFrame([("s", "c", "a b c d e f g h " * 9)], "shard_id string, corpus string, text string")
    r = catalog_text.fold_variants(d, [("4 alone", Options(l_min=4, l_max=4, cost="unit"))], full=True).first()
    assert r.legend and {e["len"] for e in r.legend} == {4}


def test_ratios_segment_no_text_in_the_engine(spark, sf):
    assert "regexp_extract_all" not in plan(workloads.w1_ratio(spark, sf))


def test_costs_fold_shards_once(spark, sf):
    assert plan(workloads.w11_cost(spark, sf)).count("collect_list") == 1


def test_template_sizes_join_no_records(spark):
    rows = [("c", "at 1 go"), ("c", "at 22 go"), ("c", "at # go"), ("c", "once only 5"), ("c", "x"), ("c", "x"), ("c", None)]
    d = spark.createDataFrame(rows, "corpus string, text string").withColumn("rec_id", F.monotonically_increasing_id())
    r = workloads.template_sizes(d).first()
    # masks: `at # go` thrice (one text has the sign itself), `x` twice; markers cost 4
    assert (r.n_tok, r.n_tok_folded, r.n_tok_legend) == (3 + 3 + 3 + 3 + 1 + 1, 2 * (4 + 1) + 3 + 3 + 2 * 4, (4 + 3) + (4 + 1))


def test_exact_reader_counts_no_tokens_of_prompts(spark, sf):
    assert "regexp_count" not in plan(workloads.aligned_exact(spark, sf, ("customer", "lineitem")))


def test_one_legend_takes_texts(spark):
    """The baseline segments texts itself, and every shard's saving is that of the entries it uses."""
    from lexfold.operators.fold import fold_global

    rows = [("s1", "c", "a b c d e f g h i"), ("s2", "c", "x a b c d e f g h i a b c d e f g h i"), ("s3", "c", "y z"), ("s4", "c", ""), ("t1", "d", "q")]
    got = {r.shard_id: r for r in fold_global(spark.createDataFrame(rows, "shard_id string, corpus string, text string")).collect()}
    # one entry of nine units under a marker of four tokens (`<`, `M`, `1`, `>`)
    assert {k: (r.n_tok, r.n_tok_folded, r.n_tok_legend) for k, r in got.items()} == {"s1": (9, 4, 13), "s2": (19, 9, 13), "s3": (2, 2, 13), "s4": (0, 0, 13), "t1": (1, 1, 0)}


def test_codes_of_runs_are_closed_up():
    s = Shard("a b c a b d a b c e f".split())
    for n in (2, 3):
        starts, codes = s.level(n, 2)
        assert sorted(set(codes.tolist())) == list(range(len(set(codes.tolist()))))
        assert len({(c, tuple(s.units[i : i + n])) for i, c in zip(starts.tolist(), codes.tolist(), strict=True)}) == len(set(codes.tolist()))


def test_starts_stay_in_order_within_a_code(monkeypatch):
    """Runs are put in the order of codes by one sort of numbers; a stable sort of places is not needed."""
    import numpy as np

    monkeypatch.setattr(np, "argsort", None)
    s = Shard(("a b c a b d a b c e f " * 5).split())
    for n in (1, 2, 3, 7):
        starts, codes = s.level(n, 2)
        want = sorted(zip(codes.tolist(), starts.tolist(), strict=True))
        got = s.grouped(n, 2)
        assert list(zip(got[1].tolist(), got[0].tolist(), strict=True)) == want
