import re

import numpy as np
from lexfold.llm import decontamination as D


def words(t):
    return [w for w in re.split(r"[\x20\x09-\x0D]+", "".join(c for c in (t or "").lower() if not (33 <= ord(c) < 127 and not c.isalnum()))) if w]


def brute(docs, items, share=0.5):
    out = set()
    for d, t in docs:
        w = words(t)
        for i, x in items:
            raw = [v for v in re.split(r"[\x20\x09-\x0D]+", x or "") if v]
            k = -(-len(raw) * 2 // 3)
            sides = [words(" ".join(raw[:k])), words(" ".join(raw[k:]))]
            if not any(sides):
                continue
            ok = True
            for s in sides:
                n = min(5, len(s))
                runs = {tuple(s[j : j + n]) for j in range(len(s) - n + 1)} if n else set()
                have = {tuple(w[j : j + n]) for j in range(len(w) - n + 1)} if n else set()
                ok &= not runs or len(runs & have) >= share * len(runs)
            if ok:
                out.add((d, i))
    return out


def test_against_brute_force(spark, sf):
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    long = " ".join(f"lange{i}" for i in range(300))
    items += [(900, long), (901, "Tiny item"), (902, ""), (903, None), (904, items[0][1])]
    docs += [
        (5000, "x " * 200 + items[3][1].upper() + " y" * 90),
        (5001, " ".join(items[4][1].split()[:8])),
        (5002, docs[0][1] + " " + long.replace("lange7 ", "andres ")),
        (5003, "a tiny, item!"),
        (5004, None),
        (5005, ""),
        (None, items[0][1]),
    ]
    df = spark.createDataFrame([(*d, 1) for d in docs], "doc_id long, text string, score int").repartition(3)
    bench = spark.createDataFrame([(*i, 1) for i in items], "item_id long, text string, doc_id int")
    got = {(r.doc_id, r.item_id) for r in D.leaks(df, bench).collect()}
    assert got == brute(docs, items)
    kept = {r.doc_id for r in D.without_leaks(df, bench).collect()}
    assert kept == {d for d, _ in docs} - {d for d, _ in got}
    assert D.leaks(df, bench.limit(0)).count() == 0
    assert D.leaks(df.limit(0), bench).count() == 0


def test_search_finds_all_above_threshold():
    rng = np.random.default_rng(0)
    vocabulary = rng.integers(1, 2**63, 300, dtype=np.uint64)
    weights = 1 / np.arange(1, 301)
    parts = [rng.choice(vocabulary, rng.integers(5, 40), p=weights / weights.sum()) for _ in range(60)]
    idf = {int(t): float(np.log(1 + 60 / (1 + sum(t in p for p in parts)))) for t in vocabulary}
    index = D.PartIndex(parts, idf, 20.0)
    passages = [rng.choice(vocabulary, 60, p=weights / weights.sum()) for _ in range(40)] + parts[:5]
    groups = np.repeat(np.arange(len(passages)), [len(p) for p in passages])
    got = {(g, p): s for g, p, s in index.search(groups, np.concatenate(passages), 0.5)}
    for g, words in enumerate(passages):
        for p in range(60):
            score = sum(x for t, row in enumerate(index.postings) for q, x in row if q == p and index.terms[t] in words)
            assert ((g, p) in got) == (score >= 0.5) or abs(score - 0.5) < 1e-9
            if (g, p) in got:
                assert abs(got[g, p] - score) < 1e-6
