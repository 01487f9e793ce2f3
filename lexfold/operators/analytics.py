"""Answers computed on the folded form, without unfolding it, and their check against raw answers."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .fold import legend


def folded_unit_freq(folded: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, unit, n): counts in the folded text, plus each legend entry's units times its uses."""
    counts = folded.select("shard_id", *by, F.explode("folded").alias("unit")).groupBy("shard_id", *by, "unit").agg(F.count("*").alias("n"))
    # Counted before the join, so a unit of a shard travels once; markers are known by their shard's legend.
    plain = counts.join(legend(folded).select("shard_id", F.col("marker").alias("unit")), ["shard_id", "unit"], "left_anti").select(*by, "unit", "n")
    e = folded.select(*by, F.explode("legend").alias("e"))
    inside = e.select(*by, F.explode("e.units").alias("unit"), F.col("e.f").alias("n"))
    return plain.unionByName(inside).groupBy(*by, "unit").agg(F.sum("n").alias("n"))


def folded_topk(folded: DataFrame, k: int = 20) -> DataFrame:
    return folded_unit_freq(folded).orderBy(F.desc("n"), "unit").limit(k)


def folded_contains(folded: DataFrame, unit: str) -> DataFrame:
    """(shard_id, n): occurrences of a unit; tested once for each legend entry."""
    per_entry = F.aggregate("legend", F.lit(0).cast("long"), lambda a, e: a + e["f"] * F.size(F.filter(e["units"], lambda u: u == unit)))
    plain = F.size(F.filter("folded", lambda u: u == unit))
    # A literal marker-like unit is never issued as a marker, so equality in the folded text is enough.
    return folded.select("shard_id", (per_entry + plain).alias("n")).where("n > 0")


def folded_records_with(folded: DataFrame, unit: str) -> DataFrame:
    """(shard_id, n_records): records that hold a unit, from markers, entries and record borders.

    A record border may fall inside a marker, so places are kept in units: entries expand to counts only.
    """
    sizes = F.map_from_entries(F.transform("legend", lambda e: F.struct(e["marker"], e["len"])))
    hits = F.map_from_entries(F.transform("legend", lambda e: F.struct(e["marker"], F.filter(F.transform(e["units"], lambda u, i: F.when(u == unit, i)), lambda i: i.isNotNull()))))
    d = folded.select("shard_id", "rec_starts", sizes.alias("sizes"), hits.alias("hits"), F.posexplode("folded").alias("at", "u"))
    before = F.coalesce(F.sum(F.coalesce(F.try_element_at("sizes", "u"), F.lit(1))).over(Window.partitionBy("shard_id").orderBy("at").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    places = F.coalesce(F.try_element_at("hits", "u"), F.when(F.col("u") == unit, F.array(F.lit(0))).otherwise(F.array().cast("array<int>")))
    d = d.withColumns({"before": before, "places": places}).select("shard_id", "rec_starts", "before", F.explode("places").alias("p"))
    rec = F.size(F.filter("rec_starts", lambda s: s <= F.col("p") + F.col("before")))
    return d.select("shard_id", rec.alias("rec")).distinct().groupBy("shard_id").agg(F.count("*").alias("n_records"))


def equivalence(a: DataFrame, b: DataFrame) -> DataFrame:
    """(only_left, only_right): rows in which two answers differ; both 0 when they are the same."""
    left, right = a.exceptAll(b).agg(F.count("*").alias("only_left")), b.exceptAll(a).agg(F.count("*").alias("only_right"))
    return left.crossJoin(right)


def gram_use(folded: DataFrame) -> DataFrame:
    """(gram, n): how often each legend gram stands in the corpus, over all shards."""
    return legend(folded).groupBy(F.array_join("units", " ").alias("gram")).agg(F.sum("f").alias("n"))
