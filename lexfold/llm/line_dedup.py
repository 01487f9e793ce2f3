"""Line deduplication by a deletion-neighbourhood join, on built-in functions only.

A line goes if an equal line, or one within one edit (insertion, deletion or substitution of a code
point), occurs earlier; earlier means a smaller (doc_id, line number), and
among rows of one doc_id with different texts a smaller (hash of the text, line number). Equal lines
meet by hash. For lines within one edit the work narrows in three exact steps:

1. Of two such lines, the shorter with s code points, the first s/2 or the last s - s/2 agree. Lines
   none of whose half keys is shared are out.
2. The edit lies in one block of 32 code points; what stands before and after it agrees. Blocks whose
   surroundings no other line has are out.
3. The remaining blocks emit every deletion variant as a hashed key, beside the block itself for the
   shorter line of an insertion. Variants of one place meet as substitutions, variants and whole
   blocks as insertions. Each line meets only the earliest of its key, which is enough to decide it;
   the edit distance of these pairs is then verified on the texts.

No step lists the pairs of a group, so thousands of near-equal lines cost thousands of rows.

Cases. Lines without a word are never dropped and never a reason to drop. The edit bound is the same
for lines of any length. A null text is an empty one and yields an empty text. Rows of
equal doc_id and equal text stand for one document and are treated alike; rows of one doc_id, or of
none, with different texts are different documents. Null doc_ids come last in the order. Empty tables
give empty results. Other columns of the input are kept, whatever their names; n_lines, n_exact_dropped
and n_near_dropped are added, replacing input columns of these names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import BLANKS, cut, sized, table

BLOCK = 32
#: A line's place, in the order of lines.
PLACE = ("doc_id", "text_key", "line_no")


def _lines(docs: DataFrame) -> DataFrame:
    text = F.coalesce(F.col("text"), F.lit(""))
    d = docs.select(F.coalesce("doc_id", F.lit(2**63 - 1)).alias("doc_id"), F.xxhash64(text).alias("text_key"), F.posexplode(F.split(text, "\n")).alias("line_no", "line"))
    d = d.where(F.regexp_like("line", F.lit(f"[^{BLANKS}]")))
    return d.withColumns({"h1": F.xxhash64("line"), "h2": F.hash("line")})


def _half_keys(line: F.Column) -> F.Column:
    """Four keys: first and last half for itself as the shorter or equal line, and as the longer one."""
    m = F.length(line)
    keys = []
    for s in (m, m - 1):
        head = F.floor(s / 2).cast("int")
        keys += [F.xxhash64(F.lit("head"), s, F.left(line, head)), F.xxhash64(F.lit("tail"), s, F.right(line, s - head))]
    return F.array(*keys)


def _shared(rows: DataFrame, key: str) -> DataFrame:
    """The rows whose key others have too."""
    often = rows.groupBy(key).agg(F.count("*").alias("n")).where("n > 1").select(key)
    return rows.join(often, key, "left_semi")


def _blocks(lines: DataFrame) -> DataFrame:
    """(line columns, around, part, whole): each block of a line with the hash of its surroundings.

    whole = false: the block as it may lose or change a code point; whole = true: the block of a line
    that lacks one code point there.
    """
    m = F.length("line")
    d = lines.withColumn("b", F.explode(F.sequence(F.lit(0), F.floor(m / BLOCK).cast("int"))))
    at = F.col("b") * BLOCK
    form = lambda size, whole: F.struct(
        F.xxhash64("b", F.left("line", at), F.substr("line", at + size + 1)).alias("around"),
        F.substr("line", at + 1, F.lit(size)).alias("part"),
        F.lit(whole).alias("whole"),
    )
    return d.select("first", F.explode(F.array(form(BLOCK, False), form(BLOCK - 1, True))).alias("x")).select("first", "x.*")


def _variants(blocks: DataFrame) -> DataFrame:
    """(first, key, place): hashed deletion variants (place 0, 1, ...) and whole blocks (place -1)."""
    cutout = lambda p: F.struct(F.xxhash64("around", F.concat(F.left("part", p), F.substr("part", p + 2))).alias("key"), p.alias("place"))
    n = F.length("part")
    out = F.when(F.col("whole"), F.array(F.struct(F.xxhash64("around", "part").alias("key"), F.lit(-1).alias("place"))))
    out = out.otherwise(F.when(n > 0, F.transform(F.sequence(F.lit(0), n - 1), cutout)))
    return blocks.select("first", F.explode(out).alias("v")).select("first", "v.*")


def near_lines(distinct: DataFrame, texts: DataFrame) -> DataFrame:
    """(doc_id, text_key, line_no) of the first occurrences that have an earlier line within one edit.

    distinct: first (doc_id, text_key, line_no) and half keys of each distinct line; texts: those columns and line.
    """
    keyed = distinct.select("first", F.explode("halves").alias("key"))
    hot = sized(_shared(keyed, "key").select("first").distinct().select("first.*"))
    lines = cut(texts.join(hot, list(PLACE)).select(F.struct(*PLACE).alias("first"), "line").distinct())
    v = cut(_variants(_shared(_blocks(lines), "around")))
    placed = v.groupBy("key", "place").agg(F.min("first").alias("same"))
    low = v.groupBy("key").agg(F.min(F.when(F.col("place") < 0, F.col("first"))).alias("as_whole"), F.min(F.when(F.col("place") >= 0, F.col("first"))).alias("as_variant"))
    met = v.join(placed, ["key", "place"]).join(low, "key")
    others = F.array(F.when(F.col("place") >= 0, F.col("same")), F.when(F.col("place") < 0, F.col("as_variant")).otherwise(F.col("as_whole")))
    pairs = met.select("first", F.explode(others).alias("other")).where("other < first").distinct()
    pairs = pairs.join(lines, "first").join(lines.select(F.col("first").alias("other"), F.col("line").alias("other_line")), "other")
    return pairs.where(F.levenshtein("line", "other_line", 1) >= 0).select("first.*").distinct()


def dropped_lines(docs: DataFrame) -> DataFrame:
    """(doc_id, text_key, exact, near): line numbers that go, of every document that loses any."""
    occ = cut(_lines(docs).select(*PLACE, "h1", "h2", _half_keys(F.col("line")).alias("halves")))
    groups = occ.groupBy("h1", "h2").agg(F.min(F.struct(*PLACE)).alias("first"), F.count("*").alias("n"), F.first("halves").alias("halves"))
    near = near_lines(groups, _lines(docs).select(*PLACE, "line")).withColumn("near", F.lit(True))
    marked = groups.select("h1", "h2", "n", "first", "first.*").join(near, list(PLACE), "left")
    bad = marked.where("n > 1 or near").select("h1", "h2", "first", F.coalesce("near", F.lit(False)).alias("near"))
    gone = occ.join(bad, ["h1", "h2"]).where("near or doc_id <> first.doc_id or text_key <> first.text_key or line_no <> first.line_no")
    of = lambda near: F.collect_set(F.when(F.col("near") == near, F.col("line_no")))
    return gone.groupBy("doc_id", "text_key").agg(of(False).alias("exact"), of(True).alias("near"))


ADDED = ("n_lines", "n_exact_dropped", "n_near_dropped")


def dedup_lines(docs: DataFrame) -> DataFrame:
    """docs with the dropped lines taken out of text, and counts of lines."""
    gone = dropped_lines(docs.select("doc_id", "text")).toDF("gone_id", "gone_key", "exact", "near")
    others = [c for c in docs.columns if c != "text" and c not in ADDED]
    raw = F.coalesce("text", F.lit(""))
    # The input's other columns travel as one, out of the way of names used here.
    own = docs.select(F.struct(*[F.col(f"`{c}`") for c in others]).alias("own"), F.coalesce("doc_id", F.lit(2**63 - 1)).alias("this_id"), F.xxhash64(raw).alias("this_key"), raw.alias("raw"))
    d = own.join(gone, (F.col("this_id") == F.col("gone_id")) & (F.col("this_key") == F.col("gone_key")), "left")
    none = F.array().cast("array<int>")
    size = lambda c: F.size(F.coalesce(c, none)).cast("long")
    d = d.withColumn("lines", F.split("raw", "\n"))
    rest = F.array_except(F.sequence(F.lit(0), F.size("lines") - 1), F.concat("exact", "near"))
    kept = F.array_join(F.transform(F.sort_array(rest), lambda i: F.get("lines", i)), "\n")
    text = F.when(F.col("gone_id").isNull(), F.col("raw")).otherwise(kept).alias("text")
    return d.select(*[text if c == "text" else F.col(f"own.`{c}`") for c in docs.columns if c not in ADDED], F.size("lines").cast("long").alias("n_lines"), size("exact").alias("n_exact_dropped"), size("near").alias("n_near_dropped"))


def without_repeated_lines(docs: DataFrame) -> DataFrame:
    """docs without repeated lines; documents left without a word go. n_chars, if there, is counted anew.

    Columns named as the added counts are the input's own.
    """
    others = [c for c in docs.columns if c not in ("text", "n_chars")]
    d = docs.select("doc_id", "text", F.struct(*[F.col(f"`{c}`") for c in others]).alias("own"))
    d = dedup_lines(d).where(F.regexp_like("text", F.lit(f"[^{BLANKS}]")))
    new = {"text": F.col("text"), "n_chars": F.length("text").cast(docs.schema["n_chars"].dataType if "n_chars" in docs.columns else "long").alias("n_chars")}
    return d.select(*[new.get(c, F.col(f"own.`{c}`")) for c in docs.columns])


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, counts of lines, and digest and length of what is left of each document."""
    d = dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return d.select("doc_id", "n_lines", "n_exact_dropped", "n_near_dropped", F.length("text").cast("long").alias("chars_kept"), F.sha2(F.col("text").cast("binary"), 256).alias("text_sha256"))
