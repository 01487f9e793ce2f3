"""What folding is compared with: nothing, cutting off, sampling, lossy shortening."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import COSTS, units


def identity(shards: DataFrame, cost: str = "pieces") -> DataFrame:
    """The shards as they are, with ratios of 0."""
    n = COSTS[cost]("text")
    return shards.select("shard_id", "corpus", n.alias("n_tok"), n.alias("n_tok_folded"), F.lit(0).cast("long").alias("n_tok_legend"), F.lit(0.0).alias("cr"), F.lit(0.0).alias("cr_input"))


def truncate_to(records: DataFrame, budget: int, cost: str = "pieces", by: str = "corpus", order: str = "rec_id") -> DataFrame:
    """The first records of each group whose tokens fit the budget together."""
    w = Window.partitionBy(by).orderBy(order).rowsBetween(Window.unboundedPreceding, 0)
    return records.withColumn("n_tok", COSTS[cost]("text")).withColumn("used", F.sum("n_tok").over(w)).where(F.col("used") <= budget)


def sample_to(records: DataFrame, budget: int, seed: int = 0, cost: str = "pieces", by: str = "corpus", key: str = "rec_id") -> DataFrame:
    """Records in hash order as far as the budget goes; the same on any partitioning and engine."""
    order = F.md5(F.concat_ws("|", F.lit(str(seed)), F.col(key).cast("string")))
    return truncate_to(records.withColumn("_h", order), budget, cost, by, "_h").drop("_h")


def distinct_lines(records: DataFrame, by: str = "corpus") -> DataFrame:
    """One record of each text, the first."""
    return records.groupBy(by, "text").agg(F.min("rec_id").alias("rec_id"), F.count("*").alias("n"))


def drop_common(records: DataFrame, share: float = 0.02, by: str = "corpus") -> DataFrame:
    """Records without the commonest distinct units of their corpus (that share of them): shorter, but lossy."""
    words = records.select(by, "rec_id", F.posexplode(units("text")).alias("pos", "unit"))
    counts = words.groupBy(by, "unit").agg(F.count("*").alias("n"))
    top = counts.withColumn("r", F.percent_rank().over(Window.partitionBy(by).orderBy(F.desc("n"), "unit"))).where(F.col("r") < share).select(by, "unit")
    kept = words.join(top, [by, "unit"], "left_anti")
    kept = kept.groupBy(by, "rec_id").agg(F.array_sort(F.collect_list(F.struct("pos", "unit"))).alias("w"))
    d = records.select(by, "rec_id").join(kept, [by, "rec_id"], "left")
    return d.select(by, "rec_id", F.coalesce(F.array_join(F.transform("w", lambda x: x["unit"]), " "), F.lit("")).alias("text"))
