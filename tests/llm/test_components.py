import numpy as np
import pytest
from lexfold.llm import common


def edges():
    """A long chain, a star, a ring, a repeated edge and random ones, both ways round, with negative ids."""
    rng = np.random.default_rng(3)
    out = [(i, i + 1) for i in range(100, 160)] + [(-7, 300 + i) for i in range(40)] + [(400 + i, 400 + (i + 1) % 9) for i in range(9)] + [(5, 4), (4, 5), (5, 4)]
    return out + [(int(a), int(b)) for a, b in rng.integers(1_000, 1_200, (90, 2)) if a != b]


def reach(pairs):
    up = {x: x for p in pairs for x in p}
    for _ in up:
        for a, b in pairs:
            up[a] = up[b] = min(up[a], up[b])
    return up


@pytest.mark.parametrize("few", [common.FEW_EDGES, -1])
def test_one_task_and_rounds_agree(spark, monkeypatch, few):
    monkeypatch.setattr(common, "FEW_EDGES", few)
    df = spark.createDataFrame(edges(), "a long, b long").repartition(3)
    assert sorted(map(tuple, common.components(df).collect())) == sorted(reach(edges()).items())
    assert common.components(df.limit(0)).collect() == []


def test_few_edges_take_few_jobs(spark):
    """Each job's tasks stay in the driver's memory: a chain of 60 edges took a round of joins for each halving."""
    df = common.cut(spark.createDataFrame(edges(), "a long, b long").repartition(3))
    spark.sparkContext.setJobGroup("few-edges", "components of few edges")
    try:
        common.components(df).collect()
        assert len(spark.sparkContext.statusTracker().getJobIdsForGroup("few-edges")) <= 6
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
        spark.sparkContext.setLocalProperty("spark.job.description", None)
