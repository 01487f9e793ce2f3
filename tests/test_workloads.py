"""Workloads read whole corpora."""

import re
from collections import Counter

from lexfold.plans import catalog
from lexfold.plans import workloads as W
from lexfold.sources import corpora as C
from pyspark.sql import functions as F


def test_no_record_is_left_out(spark, sf):
    n = spark.read.parquet("/root/testdata/sf0.01/orders.parquet").count()
    assert n > 2000
    assert C.corpora(spark, "/root/testdata/sf0.01", ("orders",)).count() == n
    assert W.standard_shards(spark, "/root/testdata/sf0.01", ("orders",)).agg(F.sum("n_recs")).first()[0] == n
    parts = spark.read.parquet(f"{sf}/part.parquet").count()
    got = W.w4_pairs(spark, sf, ("part",), (3,), W.READERS[:1], 600).agg(F.sum(F.size(F.regexp_extract_all("ref", F.lit("retail"), F.lit(0))))).first()[0]
    assert got == parts > 60


def test_no_id_or_language_is_left_out(spark, sf):
    q, d = catalog.QUERIES, spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()
    ids, labels = {r.doc_id for r in d}, {r.doc_id for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    assert {r.doc_id for r in q["join_left_labels"](spark, sf).collect()} == ids
    assert q["join_right_labels"](spark, sf).where("doc_id is null").count() == len(labels - ids)
    assert {r.doc_id for r in q["set_except"](spark, sf).collect()} == ids - labels
    starts = {}
    for r in d:
        u = re.split("[ \\t\\n\\r\\f]+", r.text.strip(" \t\n\r\f"))
        for i in range(len(u) - 1):
            starts.setdefault((str(r.doc_id), f"{u[i]} {u[i + 1]}"), []).append(i)
    want = {}
    for key, at in starts.items():
        if len(at) >= 4:
            kept = []
            for i in at:
                if not kept or i >= kept[-1] + 2:
                    kept.append(i)
            want[key] = ",".join(map(str, kept))
    assert {(r.shard_id, r.gram): r.kept for r in q["disjoint_starts"](spark, sf).collect()} == want
    spanish = {str(r.doc_id) for r in spark.read.parquet(f"{sf}/documents.parquet").where("lang = 'es'").collect()}
    assert {r.shard_id for r in q["udtf_fold_table"](spark, sf).collect()} - spanish


def test_measures_read_whole_texts(spark, tmp_path):
    texts = ["the thin thing " * 60, "un été à la forêt, déjà vu " * 40, "gleich größer " * 50, "", "x", "kurz ää"]
    rows = [(i, x, "en", "s", len(x)) for i, x in enumerate(texts)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    hyp = [x.replace("th", "ht") if i % 3 == 0 else x[: max(len(x) - 5, 0)] if i % 3 == 1 else x for i, x in enumerate(texts)]

    def got(name, *columns):
        return {r.doc_id: tuple(r[c] for c in columns or ("v",)) for r in catalog.QUERIES[name](spark, str(tmp_path)).collect()}

    def lev(a, b):
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            last, row[0] = row[0], i
            for j, y in enumerate(b, 1):
                last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
        return row[-1]

    def same(want, found):
        assert found.keys() == set(range(len(texts)))
        for i, x in enumerate(want):
            assert abs(found[i][0] - x) < 2e-6, (i, x, found[i])

    most = [max(len(a), len(b)) or 1 for a, b in zip(texts, hyp, strict=True)]
    same([float(a == b) for a, b in zip(texts, hyp, strict=True)], got("exact_match"))
    same([1 - lev(a, b) / m for a, b, m in zip(texts, hyp, most, strict=True)], got("lev_sim_shard"))
    same([1.0 if not a and not b else sum(x == y for x, y in zip(a, b, strict=False)) / m for a, b, m in zip(texts, hyp, most, strict=True)], got("ham_sim_shard"))
    counts = [(Counter(a.split()), Counter(b.split())) for a, b in zip(texts, hyp, strict=True)]
    same([(a & b).total() / a.total() if a else float(not b) for a, b in counts], got("rouge1", "recall", "precision"))
    same([sum(u in b for u in a.split()) / len(a.split()) if a.split() else 1.0 for a, b in zip(texts, hyp, strict=True)], got("presence"))
    assert 0 < got("bleu2_docs")[1][0] < 1 == got("bleu2_docs")[5][0]
    assert got("rouge_l")[5] == (1.0,) and got("rouge_l")[1][0] < 1


def test_shard_ids_of_micro_batches_differ(spark, sf, tmp_path):
    from lexfold.operators.fold import unfold
    from lexfold.operators.kernel import Options
    from lexfold.streaming import streams

    events = spark.read.parquet(f"{sf}/events.parquet")
    events.repartition(3).write.parquet(f"{tmp_path}/events")
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/events").withColumn("ts", F.col("ts").cast("timestamp"))
    folded = streams.finished(streams.rendered(stream), each=streams.fold_batch(Options(), 100))
    ids = [r.shard_id for r in folded.select("shard_id").collect()]
    assert len(ids) == len(set(ids)) and {i.split("/")[1] for i in ids} == {"0", "1", "2"}
    n = unfold(folded).select(F.explode("units").alias("u")).where("u = 'performed'").count()
    assert n == events.count()


def test_running_sums_do_not_depend_on_ranges(spark):
    from lexfold.operators import shards as S

    d = spark.range(1000).select(F.when(F.col("id") % 3 == 0, "a").otherwise("b").alias("corpus"), F.lit(0).alias("part"), (F.col("id") * F.col("id")).alias("rec_id"), (F.col("id") % 7).alias("v"))
    want, sums = {}, Counter()
    for r in sorted(d.collect(), key=lambda r: r.rec_id):
        want[r.corpus, r.rec_id] = sums[r.corpus]
        sums[r.corpus] += r.v
    assert {(r.corpus, r.rec_id): r.before for r in S.running(d, F.col("v"), "rec_id").collect()} == want
    plan = S.assign_shards_count(d.drop("part"), 10)._jdf.queryExecution().executedPlan().toString()
    assert "_range" in plan


def test_noisy_reader_takes_one_template_for_another(spark):
    """Batches carry the whole dictionary, so another entry can be taken."""
    from lexfold.operators.prompts import ExactReader, NoisyReader

    kinds = ("alpha starts job", "beta starts job", "gamma ends job", "delta ends job")
    rows = [("c", i, None, f"{kinds[i % 4]} {i}") for i in range(80)] + [("d", i, None, f"a line of its own {chr(97 + i)}") for i in range(5)]
    records = spark.createDataFrame(rows, "corpus string, rec_id long, ts timestamp, text string")
    a = W.template_answers(records, (ExactReader(), NoisyReader(3, 0.5, 0, 0)), budget=60).collect()
    assert len(a) == 2 * len(rows) and all(r.ref == r.hyp for r in a if r.reader == "exact")
    wrong = [r for r in a if r.reader == "noisy" and r.ref != r.hyp]
    assert wrong and all(any(r.hyp == f"{k} {r.rec_id}" for k in kinds) for r in wrong)


def test_regression_is_over_corpora_and_lengths(spark, sf):
    got = W.w5_regress(spark, sf, names=("part", "customer", "ev_error"), l_maxs=(3, 4, 5), budget=800).collect()
    assert {r.n for r in got} == {9} and len({r.metric for r in got}) == 7


def test_a_shard_that_fails_is_no_result():
    """w4, w5 and w8 fold through this; an unfolded shard would be read without a fault."""
    import pytest
    from lexfold.operators.fold import folded_under
    from lexfold.operators.kernel import Options

    units = "a b c d e".split() * 4
    assert [f.n_tok for f in folded_under(units, [Options(l_max=3), Options(l_max=9)])] == [20, 20]
    with pytest.raises(AttributeError):
        folded_under(units, [Options(l_max=3, marker_cost="fixed", fixed_marker=None)])


def test_texts_of_template_batches_travel_once(spark, sf):
    """Batches are found from numbers of records; texts meet neither a join nor a second exchange."""
    from lexfold.operators import shards as S

    records = C.corpora(spark, sf, ("part", "doc_en", "lineitem"))
    plan = W.template_answers(records)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Repartition") == 1 and "collect_list" not in plan and "Window" not in plan
    tokens = S.assign_shards(records, 900)
    want = {}
    for r in tokens.groupBy("corpus", "shard_id").agg(F.min("rec_id").alias("start")).collect():
        want.setdefault(r.corpus, []).append(r.start)
    assert S.budget_starts(tokens, 900) == {k: sorted(v) for k, v in want.items()}


def test_long_legends_read_as_short_ones(monkeypatch):
    """Entries of a long dictionary are places in its text; readers answer as with split ones."""
    from lexfold.operators import prompts as P

    rows = [(f"<M{i}>", f"{'ab'[i % 2]} w{i % 7} x{i % 3}{' y' * (i % 4)} é".split(" ")) for i in range(1, 60)] + [("<M60>", ["only"] * 9)]
    system, _ = P.prompt_texts(rows, [])
    user = " ".join(x for i in range(400) for x in (f"<M{i % 61}>", "plain", "\n"))
    short = [r.read(system, user) for r in (P.ExactReader(), P.NoisyReader(3, 0.5, 0.01, 0.1))]
    P.parse_legend.cache_clear()
    monkeypatch.setattr(P, "SPLIT_AT_ONCE", 10)
    try:
        legend = P.parse_legend(system)
        assert isinstance(legend, P.LongLegend) and dict(legend) == dict(rows)
        assert short == [r.read(system, user) for r in (P.ExactReader(), P.NoisyReader(3, 0.5, 0.01, 0.1))]
    finally:
        P.parse_legend.cache_clear()


def test_tokens_of_budget_shards_are_counted_once(spark, sf):
    """Shards of w4, w5 and w8 come from counts that are written beside the texts."""
    d = W.budget_texts(spark, sf, ("part", "doc_en", "lineitem"), 900)
    plan = d._jdf.queryExecution().optimizedPlan().toString()
    assert "p{L}" not in plan
    from lexfold.operators import shards as S

    want = S.shard_texts(S.assign_shards(C.corpora(spark, sf, ("part", "doc_en", "lineitem")), 900))
    assert sorted(d.select("shard_id", "text").collect()) == sorted(want.select("shard_id", "text").collect())


def test_records_without_number_or_corpus_are_answered(spark):
    rows = [("c", None, None, f"kind {i % 3} of line") for i in range(9)] + [(None, 1, None, "no corpus"), ("d", None, None, "alone"), ("d", 2**60 + 1, None, "far 1")]
    records = spark.createDataFrame(rows, "corpus string, rec_id long, ts timestamp, text string")
    got = W.template_answers(records, W.READERS[:1], budget=30).collect()
    assert sorted(r.ref for r in got) == sorted(r[3] for r in rows) and all(r.ref == r.hyp for r in got)
