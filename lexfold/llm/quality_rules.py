"""Quality rules: text counts, then a hashed n-gram log-likelihood ratio with a fixed threshold.

Two multinomials over hash buckets are counted: one over the documents marked as trusted, one over
the whole raw corpus. A document's score is the mean, over its word unigrams and bigrams, of the log
ratio of its buckets' probabilities; it is kept if the score reaches the threshold and no base rule
fails. Everything runs on built-in functions: no Python on the executors.

Cases. A null or empty text has no words: all counts are 0, the base rule fails, kept is false.
Every input row gives one output row, repeated and null doc_ids too. An empty table gives an empty result; without any
trusted document the ratio is 0 everywhere and only the base rules decide. Further columns of the
input are kept, but for those whose names the result uses. A text of any length is handled inside its row.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import BLANKS, cut, sized, table

#: Fixed values of the base rules.
SYMBOLS = "[#*$%&|<>]"
WINDOW = 5
MIN_WORDS = 10
MAX_REPEAT_PERCENT = 20
BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")


def words_of(text: F.Column) -> F.Column:
    """Words in order; trimming first keeps empty pieces away from the ends."""
    inner = F.btrim(F.coalesce(text, F.lit("")), F.lit(" \t\n\x0b\x0c\r"))
    return F.when(inner == "", F.array().cast("array<string>")).otherwise(F.split(inner, f"[{BLANKS}]+"))


def later(column: str, k: int) -> F.Column:
    """The array without its first k entries."""
    return F.slice(column, k + 1, F.greatest(F.size(column) - k, F.lit(0)))


def joined(a: str, b: str, k: int) -> F.Column:
    """Hashes of a[i] and b[i + k] together, null where b has ended."""
    return F.zip_with(a, later(b, k), lambda x, y: F.when(y.isNotNull(), F.xxhash64(x, y)))


def covered_by_repeats(windows: str, spots: str, width: int = WINDOW) -> F.Column:
    """Number of words in windows that occur twice or more; spots: the sorted (hash, place) pairs."""
    at = F.col(spots)
    same = lambda p, k: F.coalesce(p["h"] == F.get(at, k)["h"], F.lit(False))
    marked = F.transform(at, lambda p, k: F.when(same(p, k - 1) | same(p, k + 1), p["i"]))
    starts = F.sort_array(F.filter(marked, lambda i: i.isNotNull()))
    zero = F.struct(F.lit(0).alias("n"), F.lit(0).alias("end"))
    step = lambda acc, p: F.struct((acc["n"] + p + width - F.greatest(p, acc["end"])).alias("n"), (p + width).alias("end"))
    return F.aggregate(starts, zero, step, lambda acc: acc["n"])


def with_counts(docs: DataFrame, own: F.Column) -> DataFrame:
    """own, the base columns, and `hashes` and `pairs`: unigrams and bigrams in order.

    own holds what is kept of the input as one column, out of the way of names used here. Windows of five
    words are hashed by joining runs of two, three and five words; only a text with a repeated window pays
    for sorting them.
    """
    raw = F.coalesce(F.col("text"), F.lit(""))
    lines = F.filter(F.split(raw, "\n"), lambda x: F.regexp_like(x, F.lit(f"[^{BLANKS}]")))
    d = docs.select(own.alias("own"), F.regexp_count(raw, F.lit(SYMBOLS)).cast("long").alias("n_symbols"), lines.alias("lines"), words_of(raw).alias("words"))
    d = d.select(
        "own",
        "n_symbols",
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        F.length(F.array_join("words", "")).cast("long").alias("word_chars"),
        F.transform("words", lambda w: F.xxhash64(w)).alias("hashes"),
    )
    d = d.withColumn("n_words", F.size("hashes").cast("long")).withColumn("pairs", joined("hashes", "hashes", 1))
    d = d.withColumn("threes", joined("pairs", "pairs", 1)).withColumn("fives", joined("threes", "threes", 2))
    full = F.slice("fives", 1, F.greatest(F.col("n_words").cast("int") - (WINDOW - 1), F.lit(0)))
    d = d.withColumn("windows", full).drop("threes", "fives")
    d = d.withColumn("repeats", F.size(F.array_distinct("windows")) < F.size("windows"))
    d = d.withColumn("spots", F.when(F.col("repeats"), F.sort_array(F.transform("windows", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))))
    covered = F.coalesce(F.when(F.col("repeats"), covered_by_repeats("windows", "spots")), F.lit(0)).cast("long")
    d = d.withColumn("n_repeat_words", covered).drop("windows", "spots", "repeats")
    return d.withColumn("base_failed", (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words")))


def base_counts(docs: DataFrame) -> DataFrame:
    """doc_id and the base columns of every row of docs (doc_id, text)."""
    return with_counts(docs, F.struct("doc_id")).select("own.doc_id", *BASE)


def to_buckets(one: F.Column, two: F.Column, buckets: int) -> F.Column:
    """Unigrams fall into 0 .. buckets-1, bigrams into buckets .. 2*buckets-1; null where there is none."""
    return F.explode(F.array(F.pmod(one, F.lit(buckets)).cast("int"), (F.pmod(two, F.lit(buckets)) + buckets).cast("int")))


def raw_buckets(docs: DataFrame, buckets: int) -> DataFrame:
    """One row for each unigram and bigram of docs (text, in_target): in_target and bucket."""
    d = docs.select("in_target", words_of(F.col("text")).alias("words"))
    d = d.select("in_target", F.explode(F.arrays_zip(F.col("words").alias("a"), later("words", 1).alias("b"))).alias("z"))
    one = F.xxhash64("z.a")
    two = F.when(F.col("z.b").isNotNull(), F.xxhash64(one, F.xxhash64("z.b")))
    return d.select("in_target", to_buckets(one, two, buckets).alias("bucket")).where("bucket is not null")


def ratio_table(docs: DataFrame, trusted: DataFrame, buckets: int = 1 << 16, smooth: float = 1.0) -> DataFrame:
    """(bucket, weight): log ratio of the smoothed trusted and raw multinomials; 2*buckets rows at most.

    trusted: doc_id of the documents of the target; docs: doc_id, text. Counts cover all documents.
    """
    mark = trusted.select("doc_id").distinct().withColumn("in_target", F.lit(1))
    d = docs.select("doc_id", "text").join(sized(mark), "doc_id", "left").drop("doc_id")
    counts = raw_buckets(d, buckets).groupBy("bucket").agg(F.count("*").alias("raw"), F.count("in_target").alias("target"))
    order = F.when(F.col("bucket") < buckets, 1).otherwise(2)
    sums = counts.groupBy(order.alias("n")).agg(F.sum("raw").alias("all_raw"), F.sum("target").alias("all_target"))
    p = lambda c: (F.col(c) + smooth) / (F.col(f"all_{c}") + smooth * buckets)
    d = counts.withColumn("n", order).join(F.broadcast(sums), "n")
    return d.select("bucket", F.when(F.col("all_target") > 0, F.log(p("target")) - F.log(p("raw"))).otherwise(0.0).alias("weight"))


def _judged(docs: DataFrame, own: F.Column, trusted: DataFrame, threshold: float, buckets: int, smooth: float) -> DataFrame:
    """own, the base columns, llr and kept of every row of docs."""
    weights = ratio_table(docs, trusted, buckets, smooth)
    d = with_counts(docs, own).withColumn("row", F.monotonically_increasing_id())
    # Apart, numbers stay in a hash aggregate; a struct would make it sort and spill.
    fields = d.schema["own"].dataType.names
    names = [f"own_{i}" for i in range(len(fields))]
    d = d.select("row", *[F.col("own")[f].alias(n) for f, n in zip(fields, names, strict=True)], *BASE, F.explode_outer(F.arrays_zip("hashes", "pairs")).alias("z"))
    d = d.select("row", *names, *BASE, to_buckets(F.col("z.hashes"), F.col("z.pairs"), buckets).alias("bucket"))
    # 2 * buckets weights at most, whatever the corpus.
    d = d.join(F.broadcast(weights), "bucket", "left").groupBy("row").agg(*[F.first(c).alias(c) for c in (*names, *BASE)], F.coalesce(F.sum("weight"), F.lit(0.0)).alias("total"))
    d = d.withColumn("llr", F.when(F.col("n_words") > 0, F.col("total") / (2 * F.col("n_words") - 1)).otherwise(0.0))
    own = F.struct(*[F.col(n).alias(f) for f, n in zip(fields, names, strict=True)]).alias("own")
    return d.select(own, *BASE, "llr", (~F.col("base_failed") & (F.col("llr") >= threshold)).alias("kept"))


def quality_rules(docs: DataFrame, trusted: DataFrame, threshold: float = -0.2, buckets: int = 1 << 16, smooth: float = 1.0) -> DataFrame:
    """Base counts, llr and the verdict `kept` of every row of docs (doc_id, text)."""
    names = [c for c in docs.columns if c not in ("text", *BASE, "llr", "kept")]
    d = _judged(docs, F.struct(*[F.col(f"`{c}`") for c in names]), trusted, threshold, buckets, smooth)
    return d.select("own.*", *BASE, "llr", "kept")


def without_rejected(docs: DataFrame, trusted: DataFrame, threshold: float = -0.2, buckets: int = 1 << 16, smooth: float = 1.0) -> DataFrame:
    """The rows of docs that are kept. A verdict is one on a doc_id and a text, so it takes no other row along."""
    key = F.struct(F.coalesce("doc_id", F.lit(2**63 - 1)).alias("id"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("key"))
    bad = _judged(docs.select("doc_id", "text"), key, trusted, threshold, buckets, smooth).where(~F.col("kept")).select(F.col("own").alias("bad")).distinct()
    own = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("own"), key.alias("this"))
    return own.join(sized(cut(bad)), F.col("this") == F.col("bad"), "left_anti").select("own.*")


def op9_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    trusted = table(spark, sf_dir, "labels").where("quality = 1")
    return quality_rules(table(spark, sf_dir, "documents").select("doc_id", "text"), trusted)
