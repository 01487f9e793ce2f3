"""Runs of units as rows: listing, counting and ranking, relationally."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import COSTS, break_even, gain

SEP = "\x1f"


#: Places of a shard that one window holds.
STRETCH = 4096


def stretches(rows: DataFrame, at: str, before: int, after: int) -> DataFrame:
    """Adds `_s`, the stretch of each place; places near a border are given to the next stretch too.

    A window over (shard_id, _s) then sees `before` places before and `after` places behind each place of
    its own, those with `_s` = floor(at / STRETCH), however long the shard is.
    """
    own, place = F.floor(F.col(at) / STRETCH), F.pmod(F.col(at), F.lit(STRETCH))
    also = F.array_compact(F.array(own, F.when(place < after, own - 1), F.when(place >= STRETCH - before, own + 1)))
    return rows.withColumn("_s", F.explode(also))


def at_home(at: str) -> F.Column:
    return F.col("_s") == F.floor(F.col(at) / STRETCH)


def grams(rows: DataFrame, length: int) -> DataFrame:
    """(shard_id, pos, gram) for every start; rows: shard_id, pos, unit."""
    w = Window.partitionBy("shard_id", "_s").orderBy("pos").rowsBetween(0, length - 1)
    d = stretches(rows.select("shard_id", "pos", "unit"), "pos", 0, length - 1)
    return d.select("shard_id", "pos", "_s", F.collect_list("unit").over(w).alias("gram")).where(at_home("pos") & (F.size("gram") == length)).drop("_s")


def gram_counts(rows: DataFrame, length: int, f_min: int = 2, cost: str = "unit", n_m: int = 1) -> DataFrame:
    """Repeated grams: raw_f, first_pos, starts.

    Counting comes first; only grams that occur often enough to pay are joined back for their starts.
    """
    g = grams(rows, length)
    often = g.groupBy("shard_id", "gram").agg(F.count("*").alias("raw_f"), F.min("pos").alias("first_pos"))
    n_s = COSTS[cost](F.array_join("gram", " ")) if cost != "unit" else F.lit(length)
    often = often.where(F.col("raw_f") >= F.greatest(F.lit(f_min), F.coalesce(break_even(n_s, F.lit(n_m)), F.lit(2**40))))
    return g.join(often, ["shard_id", "gram"]).groupBy("shard_id", "gram", "raw_f", "first_pos").agg(F.sort_array(F.collect_list("pos")).alias("starts")).withColumn("len", F.lit(length))


def rank_candidates(df: DataFrame, order: str = "frequency", n_m: int = 1) -> DataFrame:
    """Adds `rank` in each shard and length: by count or by gain, then by first position."""
    key = F.desc("raw_f") if order == "frequency" else gain("raw_f", F.size("gram"), F.lit(n_m)).desc()
    return df.withColumn("rank", F.row_number().over(Window.partitionBy("shard_id", "len").orderBy(key, "first_pos")))
