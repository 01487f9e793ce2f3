"""Scores of readers: cut distances are exact, and shards are folded, read and measured in one place."""

import random

from lexfold.functions import measures as M
from lexfold.plans import workloads as W


def test_cut_distance_is_exact(monkeypatch):
    rng, whole, sizes = random.Random(5), M._edits, []
    for kind in ("log", "copies", "two letters"):
        for _ in range(30):
            phrases = ["".join(rng.choice("ab éx") for _ in range(30)) for _ in range(6)]
            line = {"log": lambda: f"1996 order {rng.randrange(10**6)} line {rng.randrange(7)} flag N\n", "copies": lambda: rng.choice(phrases), "two letters": lambda: rng.choice("ab") * rng.randrange(4)}[kind]  # noqa: B023
            a = "".join(line() for _ in range(60))
            b, i = [], 0
            while i < len(a):
                u = rng.random()
                i += rng.randrange(60) if u < 0.004 else 0
                b += a[i : i + 1] if u > 0.01 else "?"
                i += 1
            for x, y in ((a, "".join(b)), ("".join(b), a), (a, a[len(a) // 2 :] + a[: len(a) // 2])):
                assert M.edit_distance(x, y) == whole(x, y)
    a = "".join(f"1996 order {rng.randrange(10**6)} line {rng.randrange(7)} flag N\n" for _ in range(800))
    b = a[:5000] + "?" + a[5001:20000] + a[20025:]
    monkeypatch.setattr(M, "_edits", lambda x, y: sizes.append(len(x) + len(y)) or whole(x, y))
    assert M.edit_distance(a, b) <= 26 and max(sizes) < 3000


def test_runs_are_counted_alike_in_long_and_short_texts():
    rng = random.Random(2)
    for k in (2, 40, 10**5):
        a = [str(rng.randrange(k)) for _ in range(500)]
        b = [u for u in a if rng.random() > 0.1]
        parts = [M._shared(a, b, 4)]
        for n, got in enumerate(parts[0], 1):
            x, y = (M.Counter(zip(*(u[i:] for i in range(n)), strict=False)) for u in (a, b))
            assert got == (x.total(), y.total(), (x & y).total())


def test_answers_do_not_travel(spark, sf):
    """w4 joins nothing: prompts, answers and references stay where a shard is folded (w5 and w8 go the same way)."""
    for d in (W.w4_fold_quality(spark, sf, names=("part",), l_maxs=(3,)), W.w8_outliers(spark, sf, names=("part",))):
        plan = d._jdf.queryExecution().optimizedPlan().toString().split("LogicalRDD")[0]
        assert plan.count("MapInArrow") == 1 and "ArrowEvalPython" not in plan and "collect_list" in plan


def test_dictionaries_go_once_to_a_group(spark):
    """Records meet their answers where they are read, whatever rec_id repeats, and absent texts are empty."""
    rows = [("c", i // 2, None, f"kind {i % 3} of line {i}") for i in range(40)] + [("c", 99, None, None), ("d", 1, None, "alone # here")]
    records = spark.createDataFrame(rows, "corpus string, rec_id long, ts timestamp, text string")
    d = W.template_answers(records, (W.ExactReader(),), budget=30)
    got = d.collect()
    assert len(got) == len(rows) and all(r.ref == r.hyp for r in got)
    s = {r.metric: (r.n, r["mean"]) for r in W.mean_scores(d, ["reader"]).collect()}
    assert s == {m: (len(rows), 1.0) for m in M.MEASURES}
