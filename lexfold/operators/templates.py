"""Folding by templates: every record is one marker and what fills the template's slots."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import fill, masked, slots


def templates_mined(records: DataFrame, min_count: int = 2, slots_too: bool = True) -> DataFrame:
    """(corpus, tpl_id, masked, n_slots, n_recs): lines that recur, equal up to their digit runs if slots_too."""
    key = masked("text") if slots_too else F.col("text")
    d = records.withColumn("masked", key).groupBy("corpus", "masked").agg(F.count("*").alias("n_recs")).where(F.col("n_recs") >= min_count)
    rank = F.row_number().over(Window.partitionBy("corpus").orderBy(F.desc("n_recs"), "masked"))
    n_slots = F.regexp_count("masked", F.lit("#")) if slots_too else F.lit(0)
    return d.select("corpus", rank.alias("tpl_id"), "masked", n_slots.cast("int").alias("n_slots"), "n_recs")


def templates_given(patterns: DataFrame) -> DataFrame:
    """A catalogue from given masks: (corpus, masked)."""
    rank = F.row_number().over(Window.partitionBy("corpus").orderBy("masked"))
    return patterns.select("corpus", rank.alias("tpl_id"), "masked", F.regexp_count("masked", F.lit("#")).cast("int").alias("n_slots"), F.lit(None).cast("long").alias("n_recs"))


def match_templates(records: DataFrame, catalogue: DataFrame) -> DataFrame:
    """records with tpl_id, or null where no template fits; a text with a `#` of its own fits none."""
    c = catalogue.select("corpus", F.col("masked").alias("_masked"), "tpl_id")
    d = records.withColumn("_masked", F.when(~F.contains("text", F.lit("#")), masked("text")))
    return d.join(c, ["corpus", "_masked"], "left").withColumnRenamed("_masked", "masked")


def fold_templates(records: DataFrame, catalogue: DataFrame, mode: str = "slots") -> DataFrame:
    """corpus, rec_id, text, folded (array): each record folded by itself.

    literal: records without slots become their marker; slots: marker and slot values; fragments: every
    fixed piece of two words or more becomes a marker of its own.
    """
    d = match_templates(records, catalogue)
    marker = F.concat(F.lit("<M"), F.col("tpl_id").cast("string"), F.lit(">"))
    own = F.array("text")
    if mode == "literal":
        folded = F.when(F.col("tpl_id").isNotNull() & ~F.contains("masked", F.lit("#")), F.array(marker)).otherwise(own)
    elif mode == "slots":
        folded = F.when(F.col("tpl_id").isNotNull(), F.concat(F.array(marker), slots("text"))).otherwise(own)
    else:
        pieces = F.split("masked", "#")
        put = lambda p, i: F.when(F.size(F.split(F.trim(p), " ")) >= 2, F.concat(F.lit("<M"), F.col("tpl_id").cast("string"), F.lit("."), i.cast("string"), F.lit(">"))).otherwise(p)
        values = slots("text")
        mixed = F.flatten(F.transform(pieces, lambda p, i: F.array_compact(F.array(put(p, i), F.get(values, i)))))
        folded = F.when(F.col("tpl_id").isNotNull(), mixed).otherwise(own)
    return d.select("corpus", "rec_id", "text", "tpl_id", "masked", folded.alias("folded"))


def fragment_legend(catalogue: DataFrame) -> DataFrame:
    """(corpus, marker, piece) of the fragments mode."""
    d = catalogue.select("corpus", "tpl_id", F.posexplode(F.split("masked", "#")).alias("i", "piece"))
    d = d.where(F.size(F.split(F.trim("piece"), " ")) >= 2)
    return d.select("corpus", F.concat(F.lit("<M"), F.col("tpl_id").cast("string"), F.lit("."), F.col("i").cast("string"), F.lit(">")).alias("marker"), "piece")


def unfold_templates(folded: DataFrame, catalogue: DataFrame, mode: str = "slots") -> DataFrame:
    """corpus, rec_id, text, restored; works from the markers and the catalogue alone."""
    if mode == "fragments":
        pieces = F.map_from_entries(F.collect_list(F.struct("marker", "piece")))
        by_corpus = fragment_legend(catalogue).groupBy("corpus").agg(pieces.alias("m"))
        d = folded.join(F.broadcast(by_corpus), "corpus", "left")
        text = F.array_join(F.transform("folded", lambda x: F.coalesce(F.try_element_at("m", x), x)), "")
        return d.select("corpus", "rec_id", "text", text.alias("restored"))
    c = catalogue.select("corpus", F.concat(F.lit("<M"), F.col("tpl_id").cast("string"), F.lit(">")).alias("_marker"), F.col("masked").alias("_mask"))
    d = folded.drop("masked", "tpl_id").withColumn("_marker", F.get("folded", F.lit(0))).join(c, ["corpus", "_marker"], "left")
    rest = F.slice("folded", 2, F.greatest(F.size("folded") - 1, F.lit(0)))
    return d.select("corpus", "rec_id", "text", F.when(F.col("_mask").isNotNull(), fill("_mask", rest)).otherwise(F.get("folded", F.lit(0))).alias("restored"))
