import math
import re
from collections import Counter

import xxhash
from lexfold.llm import quality_rules as Q

BLANK = r"[\x20\x09-\x0D]+"


def signed(x):
    return x - 2**64 if x >= 2**63 else x


def h(data: bytes, seed=42):
    return xxhash.xxh64_intdigest(data, seed=seed)


def h_long(x, seed):
    return xxhash.xxh64_intdigest((x % 2**64).to_bytes(8, "little"), seed=seed % 2**64)


def words(t):
    return [w for w in re.split(BLANK, t or "") if w]


def base(t):
    w = words(t)
    runs = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    covered = {j for i in range(len(w) - 4) if runs[tuple(w[i : i + 5])] > 1 for j in range(i, i + 5)}
    lines = [x for x in (t or "").split("\n") if words(x)]
    failed = len(w) < 10 or 100 * len(covered) > 20 * len(w)
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t or "")), len(lines) - len(set(lines)), len(covered), failed


def buckets(t, n):
    hs = [h(w.encode()) for w in words(t)]
    one = [x if x < 2**63 else x - 2**64 for x in hs]
    two = [h_long(b, h_long(a, 42)) for a, b in zip(hs, hs[1:], strict=False)]
    return [x % n for x in one] + [signed(x) % n + n for x in two]


def test_against_plain_python(spark, sf):
    n = 512
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    rows += [(9000, None), (9001, ""), (9002, "a b c d e " * 9), (9003, "1 2 3 4 5 6 7 8 9 10 11"), (9004, "\n x \n x \n\n"), (None, rows[0][1])]
    trusted = {d for d, _ in rows[::3]} - {None}
    raw, target = Counter(), Counter()
    for d, t in rows:
        b = buckets(t, n)
        raw.update(b)
        if d in trusted:
            target.update(b)
    sums = [[sum(v for k, v in c.items() if (k < n) == first) for first in (False, True)] for c in (raw, target)]
    weight = {b: math.log((target[b] + 1) / (sums[1][b < n] + n)) - math.log((raw[b] + 1) / (sums[0][b < n] + n)) for b in raw}
    df = spark.createDataFrame([(d, t, "x") for d, t in rows], "doc_id long, text string, llr string").repartition(3)
    ids = spark.createDataFrame([(d,) for d in trusted], "doc_id long")
    got = {r.doc_id: r for r in Q.quality_rules(df, ids, buckets=n).collect()}
    assert len(got) == len(rows)
    for d, t in rows:
        b, r = buckets(t, n), got[d]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) == base(t)
        llr = sum(weight[x] for x in b) / len(b) if b else 0.0
        assert abs(r.llr - llr) < 1e-9
        assert r.kept == (not r.base_failed and llr >= -0.2)


def test_cases(spark):
    df = spark.createDataFrame([(1, "a b"), (1, "a b")], "doc_id long, text string")
    none = spark.createDataFrame([], "doc_id long")
    got = Q.quality_rules(df, none).collect()
    assert len(got) == 2 and {r.llr for r in got} == {0.0}
    assert Q.quality_rules(df.limit(0), none).count() == 0
