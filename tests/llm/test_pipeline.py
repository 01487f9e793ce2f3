import math
import os
import sys
from collections import Counter
from hashlib import sha256

import public_tokenizers as P
import tiktoken
from lexfold.llm.bpe_codec import read_ranks

sys.path[:0] = [os.path.dirname(__file__), os.path.dirname(os.path.dirname(os.path.dirname(__file__)))]
import corpus_pipeline
import test_decontamination
import test_line_dedup
import test_ngram_join
import test_quality_rules as R


def kept_by_rules(docs, trusted, n=1 << 16):
    made = {d: R.buckets(t, n) for d, t in docs.items()}
    raw = Counter(b for x in made.values() for b in x)
    target = Counter(b for d, x in made.items() if d in trusted for b in x)
    total = lambda c, first: sum(v for k, v in c.items() if (k < n) == first)
    sums = {(id(c), first): total(c, first) for c in (raw, target) for first in (False, True)}
    log = lambda c, b: math.log((c[b] + 1) / (sums[id(c), b < n] + n))
    return {d: t for d, t in docs.items() if not R.base(t)[-1] and sum(log(target, b) - log(raw, b) for b in made[d]) >= -0.2 * len(made[d])}


def test_run_equals_plain_python(spark, sf):
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    trusted = {r.doc_id for r in spark.read.parquet(f"{sf}/labels.parquet").where("quality = 1").collect()}
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    docs = kept_by_rules(docs, trusted)
    docs = {d: x[2] for d, x in test_line_dedup.brute(list(docs.items())).items() if x[2].strip(test_line_dedup.BLANK)}
    docs = {d: docs[d] for d, (_, c) in test_ngram_join.brute(list(docs.items()), 5, 80).items() if c == d}
    leaked = {d for d, _ in test_decontamination.brute(list(docs.items()), items)}
    own = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=read_ranks(P.path("byte_bpe_multi_50k.tiktoken")), special_tokens={})
    want = {d: (len(ids := own.encode_ordinary(t)), sha256(",".join(map(str, ids)).encode()).hexdigest()) for d, t in docs.items() if d not in leaked}
    got = {r.doc_id: (r.n_tokens, r.ids_sha256) for r in corpus_pipeline.run(spark, sf).collect()}
    assert got == want


def test_stages_return_the_columns_of_documents(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(20)
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, sf).columns == docs.columns


def odd_tables(spark, sf, folder):
    """A folder of tables with null and repeated doc_ids, odd texts and columns of clashing names; (doc_id, text) in order."""
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").orderBy("doc_id").collect()]
    rows = [(None if i % 4 == 1 else rows[i - 1][0] if i % 10 == 7 else d, t) for i, (d, t) in enumerate(rows)]
    rows += [(None, "too short"), (None, None), (rows[0][0], ""), rows[0], rows[5], (None, rows[8][1]), (10**6, " \n\n ")]
    extra = "bad boolean, words string, hashes int, kept string, own string, lines int, raw string, node long, id long, key long, clean int, text_key int"
    spark.createDataFrame([(d, t, True, "w", 1, "k", "o", 2, "r", 3, 4, 5, 6, 7) for d, t in rows], f"doc_id long, text string, {extra}").repartition(3).write.parquet(f"{folder}/documents.parquet")
    for name in ("labels", "benchmark"):
        spark.read.parquet(f"{sf}/{name}.parquet").write.parquet(f"{folder}/{name}.parquet")
    return rows


def test_null_and_repeated_ids_take_no_other_row_along(spark, sf, tmp_path):
    rows = odd_tables(spark, sf, tmp_path)
    trusted = {r.doc_id for r in spark.read.parquet(f"{sf}/labels.parquet").where("quality = 1").collect()}
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    pairs = lambda d: sorted(((r.doc_id, r.text) for r in d.collect()), key=str)
    good = kept_by_rules(dict(enumerate(t for _, t in rows)), {i for i, (d, _) in enumerate(rows) if d in trusted})
    after = corpus_pipeline.quality(spark, docs, str(tmp_path))
    assert after.columns == docs.columns and pairs(after) == sorted(((rows[i][0], t) for i, t in good.items()), key=str)
    assert any(d is None for d, _ in pairs(after))
    leaked = {i for i, _ in test_decontamination.brute([(i, t) for i, (_, t) in enumerate(rows)], items)}
    clean = corpus_pipeline.decontaminated(spark, docs, str(tmp_path))
    assert clean.columns == docs.columns and pairs(clean) == sorted((r for i, r in enumerate(rows) if i not in leaked), key=str)
    groups = test_ngram_join.brute([(i, t) for i, (_, t) in enumerate(rows)], 5, 80)
    one = corpus_pipeline.near_duplicates(spark, docs, str(tmp_path))
    assert one.columns == docs.columns
    members = {}
    for i, (_, c) in groups.items():
        members.setdefault(c, []).append(rows[i])
    stays = pairs(one)
    for own in members.values():
        named = [r for r in own if r[0] is not None]
        least = min((d for d, _ in named), default=None)
        want = {r for r in own if r[0] is None} | ({r for r in named if r[0] == least} if len({r for r in named if r[0] == least}) == 1 or len(own) == 1 else set())
        assert want <= set(stays)
        assert not {r for r in named if r[0] != least} & set(stays)
    assert corpus_pipeline.lines(spark, docs, str(tmp_path)).columns == docs.columns
    assert corpus_pipeline.run(spark, str(tmp_path)).columns == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]


def test_empty_tables(spark, sf, tmp_path):
    for name in ("documents", "labels", "benchmark"):
        spark.read.parquet(f"{sf}/{name}.parquet").limit(0).write.parquet(f"{tmp_path}/{name}.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
