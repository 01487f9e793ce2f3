"""Dividing records into shards that fit a reader's window, and shards into rows of units."""

from __future__ import annotations

import math
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import COSTS, units
from .lineage import checkpointed


def parts(df: DataFrame, n_parts: int, numbered: tuple[str, ...] = ()) -> DataFrame:
    """Adds `part`: equal ranges of rec_id in each corpus, so no window holds a whole corpus.

    numbered: corpora whose rec_id is 1, 2, 3 …; their spans follow from their sizes. Adds `first_rec`,
    the first rec_id that falls into the part.
    """
    own = F.col("corpus").isin(*numbered) if numbered else F.lit(False)
    span = df.where(~own).groupBy("corpus").agg(F.min("rec_id").alias("_lo"), F.max("rec_id").alias("_hi"))
    if numbered:
        span = span.unionByName(df.where(own).groupBy("corpus").agg(F.lit(1).cast("long").alias("_lo"), F.count("*").alias("_hi")))
    d = df.join(F.broadcast(span), "corpus")
    n = F.col("_hi") - F.col("_lo") + 1
    d = d.withColumn("part", F.floor((F.col("rec_id") - F.col("_lo")) * n_parts / n).cast("int"))
    return d.withColumn("first_rec", F.col("_lo") + F.floor((F.col("part") * n + n_parts - 1) / n_parts)).drop("_lo", "_hi")


def _with_part(df: DataFrame) -> DataFrame:
    return df if "part" in df.columns else df.withColumn("part", F.lit(0))


def _named(df: DataFrame) -> DataFrame:
    return df.withColumn("shard_id", F.concat_ws("/", "corpus", F.col("part").cast("string"), F.col("seq").cast("string")))


def running(df: DataFrame, value: F.Column, order: str, out: str = "before") -> DataFrame:
    """Adds the sum of value over the records before each, by corpus and part in the order of a number or time.

    A corpus is cut into ranges of the order, about equal in records; sums run inside a range and start
    from the sums of the ranges before it, so no task holds a whole corpus.
    """
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    key = ["corpus", "part"]
    cuts = F.percentile_approx(order, [k / n for k in range(1, n)] or [0.5], 10_000)
    # Ranges must be the same wherever they are used, so they are written down.
    cuts = checkpointed(df.groupBy(*key).agg(cuts.alias("_cuts")))
    d = df.withColumn("_value", value).join(F.broadcast(cuts), key)
    # Looked up in two steps, among every step-th cut and then among those behind it.
    step = max(1, math.isqrt(n))
    below = lambda a: F.coalesce(F.size(F.filter(a, lambda c: c < F.col(order))), F.lit(0))
    d = d.withColumn("_top", step * below(F.filter("_cuts", lambda c, k: (k + 1) % step == 0)))
    d = d.withColumn("_range", F.col("_top") + below(F.slice("_cuts", F.col("_top") + 1, F.lit(step)))).drop("_cuts", "_top")
    sums = d.groupBy(*key, "_range").agg(F.sum("_value").alias("_sum"))
    earlier = Window.partitionBy(*key).orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    base = sums.select(*key, "_range", F.coalesce(F.sum("_sum").over(earlier), F.lit(0)).alias("_base"))
    here = Window.partitionBy(*key, "_range").orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    d = d.join(F.broadcast(base), [*key, "_range"])
    return d.withColumn(out, F.col("_base") + F.coalesce(F.sum("_value").over(here), F.lit(0))).drop("_range", "_value", "_base")


def assign_shards_count(df: DataFrame, count: int = 2000, numbered: tuple[str, ...] = ()) -> DataFrame:
    """Shards of a fixed number of records in order; numbered: corpora whose rec_id is 1, 2, 3 …"""
    d = _with_part(df)
    if numbered:
        own = F.col("corpus").isin(*numbered)
        known = d.where(own).withColumn("_before", F.col("rec_id") - (F.col("first_rec") if "first_rec" in d.columns else 1))
        d = running(d.where(~own), F.lit(1), "rec_id", "_before").unionByName(known)
    else:
        d = running(d, F.lit(1), "rec_id", "_before")
    return _named(d.withColumn("seq", F.floor(F.col("_before") / count).cast("long")).drop("_before"))


def budget_starts(df: DataFrame, budget: int) -> dict[str, list[int]]:
    """By corpus, the first rec_id of each shard that assign_shards makes; df: corpus, rec_id, n_tok. No text travels."""
    d = running(_with_part(df.select("corpus", "rec_id", "n_tok")), F.col("n_tok"), "rec_id", "_before")
    d = d.groupBy("corpus", F.floor(F.col("_before") / budget).alias("seq")).agg(F.min("rec_id").alias("start"))
    out: dict[str, list[int]] = {}
    for r in d.where("start is not null").select("corpus", "start").collect():
        out.setdefault(r.corpus, []).append(r.start)
    return {k: sorted(v) for k, v in out.items()}


def split_oversize(df: DataFrame, budget: int, cost: str = "pieces") -> DataFrame:
    """Records above the budget become several, cut between units; `piece` counts them."""
    u = F.col("_units")
    # A unit costs at least one token, so pieces of budget // (largest unit's cost) units fit.
    most = F.aggregate(F.transform(u, lambda x: COSTS[cost](x)), F.lit(1).cast("long"), lambda a, x: F.greatest(a, x))
    step = F.greatest(F.floor(F.lit(budget) / most), F.lit(1)).cast("int")
    cut = F.transform(F.sequence(F.lit(0), F.greatest(F.size(u) - 1, F.lit(0)), F.col("_step")), lambda i: F.array_join(F.slice(u, i + 1, F.col("_step")), " "))
    d = df.withColumn("_units", units("text")).withColumn("_step", step).withColumn("_texts", F.when(COSTS[cost]("text") > budget, cut).otherwise(F.array("text")))
    return d.select(*[c for c in df.columns if c != "text"], F.posexplode("_texts").alias("piece", "text"))


def assign_shards(df: DataFrame, budget: int = 32_000, mode: str = "cumsum", cost: str = "pieces", counted: bool = False) -> DataFrame:
    """Shards by token budget in record order.

    cumsum: a running sum divided by the budget; a shard may exceed it by less than one record.
    pack: a record that would exceed the budget opens a new shard; never exceeded but by one record.
    counted: records have their n_tok already.
    """
    d = _with_part(df)
    d = d if counted else d.withColumn("n_tok", COSTS[cost]("text"))
    if mode == "cumsum":
        d = running(d, F.col("n_tok"), "rec_id", "_before")
        return _named(d.withColumn("seq", F.floor(F.col("_before") / budget).cast("long")).drop("_before"))

    def pack(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        key, seq, used = None, 0, 0
        for b in batches:
            out = []
            for corpus, part, n in zip(b["corpus"], b["part"], b["n_tok"], strict=True):
                if (corpus, part) != key:
                    key, seq, used = (corpus, part), 0, 0
                elif used and used + n > budget:
                    seq, used = seq + 1, 0
                used += n
                out.append(seq)
            yield b.assign(seq=out)

    # The scan is over sorted partitions, batch by batch; no group is held in memory.
    dealt = d.repartition("corpus", "part").sortWithinPartitions("corpus", "part", "rec_id")
    schema = ", ".join(f"`{n}` {t}" for n, t in d.dtypes) + ", seq long"
    return _named(dealt.mapInPandas(pack, schema))


def assign_shards_time(df: DataFrame, size: str = "1 day", slide: str | None = None, gap: str | None = None) -> DataFrame:
    """Shards by time: tumbling, sliding (records repeat) or, with gap, sessions of a corpus."""
    d = _with_part(df)
    if gap:
        # Sessions are merged map-side and never meet a record again: each record counts the starts up to its time.
        d = d.where(F.col("ts").isNotNull())
        starts = d.groupBy("corpus", "part", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("_n"))
        starts = starts.select("corpus", "part", F.col("w.start").alias("ts"), F.lit(1).alias("_start"))
        stamped = d.withColumn("_start", F.lit(0)).unionByName(starts, allowMissingColumns=True)
        # In order of time and, at one time, the session's start before its records.
        stamped = stamped.withColumn("_at", 2 * F.unix_micros(F.col("ts").cast("timestamp")) + 1 - F.col("_start"))
        d = running(stamped, F.col("_start"), "_at", "seq").where("_start = 0").drop("_start", "_at")
        return _named(d.withColumn("seq", F.col("seq").cast("long")))
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return _named(d.withColumn("_w", w).withColumn("seq", F.unix_seconds("_w.start")).drop("_w"))


def assign_shards_by(df: DataFrame, key: F.Column, count: int = 2000) -> DataFrame:
    """Shards of records that are alike by key side by side."""
    w = Window.partitionBy("corpus", "part").orderBy(key, "rec_id")
    return _named(_with_part(df).withColumn("seq", F.floor((F.row_number().over(w) - 1) / count).cast("long")))


def shard_texts(df: DataFrame) -> DataFrame:
    """One row a shard: shard_id, corpus, n_recs, text, with records joined by line breaks; not yet segmented."""
    d = df.groupBy("shard_id", "corpus").agg(F.sort_array(F.collect_list(F.struct("rec_id", F.coalesce("text", F.lit("")).alias("text")))).alias("recs"))
    return d.select("shard_id", "corpus", F.size("recs").alias("n_recs"), F.array_join("recs.text", "\n").alias("text"))


def shard_units(df: DataFrame, ws: str = "collapse") -> DataFrame:
    """One row a shard: shard_id, corpus, first_rec, n_recs, units, rec_starts (first unit of each record), text.

    Texts travel, not units: segmentation follows the exchange. Records are joined by line breaks.
    """
    by_record = F.array_sort(F.collect_list(F.struct("rec_id", *(["piece"] if "piece" in df.columns else []), "text")))
    d = df.groupBy("shard_id", "corpus").agg(by_record.alias("recs"))
    texts = F.transform("recs", lambda r: F.coalesce(r["text"], F.lit("")))
    joined = F.array_join(texts, "\n")
    sizes = F.transform(texts, lambda t: F.size(units(t, ws)) + (1 if ws == "lines" else 0))
    starts = F.aggregate(sizes, F.struct(F.lit(0).alias("at"), F.array().cast("array<int>").alias("out")), lambda a, n: F.struct((a["at"] + n).alias("at"), F.concat(a["out"], F.array(a["at"])).alias("out")), lambda a: a["out"])
    return d.select("shard_id", "corpus", F.get("recs", F.lit(0))["rec_id"].alias("first_rec"), F.size("recs").alias("n_recs"), joined.alias("text"), units(joined, ws).alias("units"), starts.alias("rec_starts"))


def unit_rows(shards: DataFrame) -> DataFrame:
    return shards.select("shard_id", F.posexplode("units").alias("pos", "unit"))
