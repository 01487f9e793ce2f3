import random
from collections import defaultdict

from lexfold.llm import line_dedup as L

BLANK = " \t\n\r\x0b\x0c"


def within_one(a, b):
    if len(a) > len(b):
        a, b = b, a
    if len(b) - len(a) > 1:
        return False
    i = 0
    while i < len(a) and a[i] == b[i]:
        i += 1
    return a[i + 1 :] == b[i + 1 :] if len(a) == len(b) else a[i:] == b[i + 1 :]


def brute(rows):
    """(exact, near, text) by doc_id."""
    order = sorted(rows, key=lambda r: (r[0] is None, r[0] or 0))
    first, by_length = {}, defaultdict(list)
    for d, t in order:
        for i, x in enumerate((t or "").split("\n")):
            if x.strip(BLANK) and x not in first:
                first[x] = ((d is None, d or 0), i)
                by_length[len(x)].append(x)
    near = {x for x, f in first.items() for n in (len(x) - 1, len(x), len(x) + 1) for y in by_length[n] if y != x and first[y] < f and within_one(x, y)}
    out = {}
    for d, t in order:
        kept, counts = [], [0, 0]
        for i, x in enumerate((t or "").split("\n")):
            if not x.strip(BLANK):
                kept.append(x)
            elif x in near:
                counts[1] += 1
            elif first[x] != ((d is None, d or 0), i):
                counts[0] += 1
            else:
                kept.append(x)
        out[d] = (*counts, "\n".join(kept))
    return out


def test_against_all_pairs(spark, sf):
    rng = random.Random(3)
    rows = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    lines = [x for t in rows.values() for x in t.split("\n") if len(x) > 18]
    for k in range(80):
        x = rng.choice(lines)
        i = rng.randrange(len(x) + 1)
        y = [x[:i] + "Q" + x[i + 1 :], x[:i] + x[i + 1 :], x[:i] + "é" + x[i:]][k % 3]
        rows[rng.randrange(-400, 4000)] = y if k % 2 else f"{y}\n{x}\n\n "
    base = "a line that many others are alike to, but for one place"
    rows |= {10_000 + k: base[: k % 50] + chr(97 + k % 26) + base[k % 50 + 1 :] for k in range(120)}
    rows |= {20_000: None, 20_001: "", 20_002: " \n\n", None: "a null id line with words enough", 20_003: "x" * 3000, 20_004: "x" * 3001, 20_005: "short\nshort\nshorx\nxq\nq\nz\nfoxes\nfoges\nfoge"}
    df = spark.createDataFrame([(d, t, "extra", 1, "a", 2) for d, t in rows.items()], "doc_id long, text string, near string, n_lines int, lines string, own int").repartition(3)
    assert {(r.near, r.lines, r.own) for r in L.dedup_lines(df).collect()} == {("extra", "a", 2)}
    assert L.without_repeated_lines(df).columns == df.columns and {r.n_lines for r in L.without_repeated_lines(df).collect()} == {1}
    got = {r.doc_id: (r.n_exact_dropped, r.n_near_dropped, r.text) for r in L.dedup_lines(df).collect()}
    assert got == brute(list(rows.items()))


def test_repeated_rows_and_empty(spark):
    df = spark.createDataFrame([(1, "one line here"), (1, "one line here"), (2, "one line here")], "doc_id long, text string")
    assert sorted((r.doc_id, r.text) for r in L.dedup_lines(df).collect()) == [(1, "one line here"), (1, "one line here"), (2, "")]
    assert L.dedup_lines(df.limit(0)).count() == 0
    assert [r.doc_id for r in L.without_repeated_lines(df).collect()] == [1, 1]


def test_one_id_with_different_texts(spark):
    near = "a line that is long enough to be near"
    for doc_id in (None, 7):
        rows = [(doc_id, "dup x\nunique first"), (doc_id, "unique second\ndup x"), (doc_id, f"same place\n{near}"), (doc_id, f"same place\n{near}!"), (9, "other")]
        got = L.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string").repartition(2)).collect()
        lines = sorted(x for r in got for x in r.text.split("\n") if x)
        kept_near = [x for x in lines if x.startswith(near)]
        assert len(kept_near) == 1 and [x for x in lines if x not in kept_near] == ["dup x", "other", "same place", "unique first", "unique second"]
        assert sum(r.n_exact_dropped for r in got) == 2 and sum(r.n_near_dropped for r in got) == 1
