"""Stand-in corpora rendered from the given tables: (corpus, rec_id, ts, text)."""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

EVENT_TYPES = ("click", "view", "purchase", "signup", "error")
LANGS = ("en", "de", "fr", "es")
#: The fourteen corpora that the workloads use, then the further ones.
MAIN = (*(f"ev_{t}" for t in EVENT_TYPES), "orders", "lineitem", "part", "customer", *(f"doc_{x}" for x in LANGS), "dialogue")
EXTRA = ("html", "supplier", "benchmark")


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _words(*parts: str | F.Column) -> F.Column:
    """Literal words and columns with single blanks between; a string is literal."""
    return F.concat_ws(" ", *[F.lit(p) if isinstance(p, str) else p.cast("string") for p in parts])


def _day(c: str) -> F.Column:
    return F.date_format(c, "yyyy-MM-dd")


#: Corpora whose records are numbered 1, 2, 3 … by `numbered`.
NUMBERED = ("lineitem", "dialogue")


def numbered(df: DataFrame, order: tuple[str, ...], out: str) -> DataFrame:
    """Adds the number of each row in an order that begins with a number, from 1.

    Rows are cut into ranges of the first column, about equal in rows; numbers run inside a range and
    start from the rows of the ranges before it, so no task holds the table.
    """
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    cuts = df.agg(F.percentile_approx(order[0], [k / n for k in range(1, n)] or [0.5], 10_000)).first()[0] or []
    cuts = sorted(set(cuts))
    step = max(1, math.isqrt(len(cuts)))
    below = lambda a: F.size(F.filter(a, lambda c: c < F.col(order[0])))
    d = df.withColumn("_cuts", F.array(*map(F.lit, cuts)) if cuts else F.array().cast("array<double>"))
    # Looked up in two steps, among every step-th cut and then among those behind it.
    d = d.withColumn("_top", step * below(F.array(*map(F.lit, cuts[step - 1 :: step])) if cuts else F.col("_cuts")))
    d = d.withColumn("_range", F.col("_top") + below(F.slice("_cuts", F.col("_top") + 1, F.lit(step)))).drop("_cuts", "_top")
    sizes = d.groupBy("_range").agg(F.count("*").alias("_n"))
    earlier = Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    base = sizes.select("_range", F.coalesce(F.sum("_n").over(earlier), F.lit(0)).alias("_base"))
    here = Window.partitionBy("_range").orderBy(*order)
    d = d.withColumn(out, F.row_number().over(here).cast("long")).join(F.broadcast(base), "_range")
    return d.withColumn(out, F.col("_base") + F.col(out)).drop("_base", "_range")


def _rendered(df: DataFrame, corpus: str | F.Column, order: tuple[str, ...], text: F.Column, ts: str | None = None) -> DataFrame:
    c = F.lit(corpus) if isinstance(corpus, str) else corpus
    if len(order) == 1:
        rec = F.col(order[0]).cast("long")
    else:
        df, rec = numbered(df, order, "_rec"), F.col("_rec")
    stamp = F.col(ts).cast("timestamp") if ts else F.lit(None).cast("timestamp")
    return df.select(c.alias("corpus"), rec.alias("rec_id"), stamp.alias("ts"), text.alias("text"))


def events_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    line = _words(F.date_format("ts", "yyyy-MM-dd'T'HH:mm:ss"), "INFO service=events user", F.col("user_id"), "performed", F.col("event_type"), "with value", F.col("value"), "props", F.col("props"))
    return _rendered(read(spark, sf_dir, "events"), F.concat(F.lit("ev_"), "event_type"), ("event_id",), line, "ts")


def orders_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = F.col
    line = _words(_day("o_orderdate"), "order", c("o_orderkey"), "customer", c("o_custkey"), "status", c("o_orderstatus"), "priority", c("o_orderpriority"), "total", c("o_totalprice"))
    return _rendered(read(spark, sf_dir, "orders"), "orders", ("o_orderkey",), line, "o_orderdate")


def lineitem_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = F.col
    df = read(spark, sf_dir, "lineitem")
    line = _words(_day("l_shipdate"), "shipped order", c("l_orderkey"), "line", c("l_linenumber"), "part", c("l_partkey"), "supplier", c("l_suppkey"), "flag", c("l_returnflag"), "status", c("l_linestatus"), "quantity", c("l_quantity"), "discount", c("l_discount"))
    order = ("l_orderkey", "l_linenumber", *(x for x in df.columns if x not in ("l_orderkey", "l_linenumber")))
    return _rendered(df, "lineitem", order, line, "l_shipdate")


def part_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = F.col
    return _rendered(read(spark, sf_dir, "part"), "part", ("p_partkey",), _words("part", c("p_partkey"), "name", c("p_name"), "brand", c("p_brand"), "type", c("p_type"), "size", c("p_size"), "retail", c("p_retailprice")))


def customer_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = F.col
    return _rendered(read(spark, sf_dir, "customer"), "customer", ("c_custkey",), _words(c("c_name"), "nation", c("c_nationkey"), "segment", c("c_mktsegment"), "balance", c("c_acctbal")))


def supplier_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = F.col
    return _rendered(read(spark, sf_dir, "supplier"), "supplier", ("s_suppkey",), _words(c("s_name"), "nation", c("s_nationkey"), "balance", c("s_acctbal")))


def document_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rendered(read(spark, sf_dir, "documents"), F.concat(F.lit("doc_"), "lang"), ("doc_id",), F.col("text"))


def dialogue_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rendered(read(spark, sf_dir, "conversations"), "dialogue", ("conv_id", "turn"), F.concat_ws(": ", "role", "text"))


def html_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rendered(read(spark, sf_dir, "pages"), "html", ("page_id",), F.col("html"))


def benchmark_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rendered(read(spark, sf_dir, "benchmark"), "benchmark", ("item_id",), F.col("text"))


RENDERERS = {
    **{f"ev_{t}": events_records for t in EVENT_TYPES},
    "orders": orders_records,
    "lineitem": lineitem_records,
    "part": part_records,
    "customer": customer_records,
    **{f"doc_{x}": document_records for x in LANGS},
    "dialogue": dialogue_records,
    "html": html_records,
    "supplier": supplier_records,
    "benchmark": benchmark_records,
}


def corpora(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = MAIN, cap: int | None = None) -> DataFrame:
    """Records of the named corpora; a cap, if given, keeps the first records of each by order."""
    made = []
    for render in dict.fromkeys(RENDERERS[n] for n in names):
        own = [n for n in names if RENDERERS[n] is render]
        made.append(render(spark, sf_dir).where(F.col("corpus").isin(own)))
    df = reduce(DataFrame.unionByName, made)
    if cap is None:
        return df
    first = F.row_number().over(Window.partitionBy("corpus").orderBy("rec_id"))
    return df.withColumn("_n", first).where(F.col("_n") <= cap).drop("_n")


def strip_tags(html: F.Column | str) -> F.Column:
    """Text of a page without scripts, styles and tags."""
    c = F.col(html) if isinstance(html, str) else html
    return F.trim(F.regexp_replace(F.regexp_replace(c, r"(?is)<(script|style)\b.*?</\1>|<!--.*?-->", " "), r"<[^>]*>|\s+", " "))
