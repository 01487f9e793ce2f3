"""The experiments, on the stand-in corpora. Each returns rows; readers are simulations."""

from __future__ import annotations

import re
import time
from collections import Counter
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import measures as M
from ..functions.text import masked, slots, tok_pieces
from ..operators import shards as S
from ..operators.fold import fold_global, fold_sweep, folded_under, unit_list
from ..operators.kernel import Folded, Options
from ..operators.lineage import checkpointed, written
from ..operators.prompts import ENTRY_END, UNFOLD, ExactReader, NoisyReader, Reader, align, build_prompts, prompt_texts, read_prompts
from ..operators.templates import fold_templates, templates_mined, unfold_templates
from ..sources.corpora import EXTRA, LANGS, MAIN, NUMBERED, corpora, events_records, read, strip_tags

_PROSE, _DIGIT = regex.compile(r"\p{L}+[.,;:!?]?"), re.compile("[0-9]")
READERS: tuple[Reader, ...] = (ExactReader(), NoisyReader(seed=7))


def tasks(spark: SparkSession) -> int:
    """Tasks that are enough for all cores."""
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), 4 * spark.sparkContext.defaultParallelism)


def dealt(df: DataFrame, *by: str) -> DataFrame:
    """df over tasks enough for all cores: tables of one file come in one, and small ones are merged into few."""
    return df.repartition(tasks(df.sparkSession), *by)


def counted(records: DataFrame) -> DataFrame:
    """records with n_tok, tokens counted once; written down compressed."""
    spread = F.coalesce(F.col("corpus").isin(*NUMBERED, "doc_lines"), F.lit(False))  # made by exchanges already
    records = dealt(records.where(~spread)).unionByName(records.where(spread))
    return written(records.withColumn("n_tok", tok_pieces("text")))


def standard_shards(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = MAIN, cap: int | None = None, ws: str = "collapse") -> DataFrame:
    """Shards of up to 2,000 records over the whole of each corpus; not segmented where blanks collapse."""
    d = S.assign_shards_count(corpora(spark, sf_dir, names, cap), 2000, NUMBERED)
    return S.shard_texts(d) if ws == "collapse" else S.shard_units(d, ws)


def w1_ratio(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = MAIN, l_maxs: Iterable[int] = range(3, 21), cost: str = "pieces") -> DataFrame:
    """corpus, l_max, cr, cr_input, overhead."""
    d = fold_sweep(standard_shards(spark, sf_dir, names), l_maxs, Options(cost=cost))
    return M.ratios(d, ["corpus", "l_max"]).drop("n_tok", "n_tok_folded", "n_tok_legend")


def line_records(docs: DataFrame, key: str, corpus: str) -> DataFrame:
    """(corpus, rec_id, text) of every line of text; rec_id counts lines over all documents in the order of key."""
    d = docs.withColumn("_lines", F.split("text", "\n")).withColumn("_n", F.size("_lines").cast("long"))
    d = S.running(d.select(F.lit(corpus).alias("corpus"), F.lit(0).alias("part"), F.col(key).alias("rec_id"), "_lines", "_n"), F.col("_n"), "rec_id")
    d = d.select("corpus", "before", F.posexplode("_lines").alias("_i", "text"))
    return d.select("corpus", (F.col("before") + F.col("_i")).alias("rec_id"), "text")


def mean_scores(pairs: DataFrame, key: list[str]) -> DataFrame:
    """key, metric, n, mean, std, sem of every measure of (ref, hyp); an absent text counts as an empty one."""

    @F.pandas_udf("array<double>")
    def scored(ref: pd.Series, hyp: pd.Series) -> pd.Series:
        return pd.Series([M.measures(x or "", y or "") for x, y in zip(ref, hyp, strict=True)])

    d = pairs.select(*key, scored("ref", "hyp").alias("v"))
    parts = [F.struct(F.lit(m).alias("metric"), F.count(F.get("v", F.lit(i))).alias("n"), F.avg(F.get("v", F.lit(i))).alias("mean"), F.stddev_samp(F.get("v", F.lit(i))).alias("std")) for i, m in enumerate(M.MEASURES)]
    d = d.groupBy(*key).agg(F.array(*parts).alias("m")).select(*key, F.explode("m").alias("m")).select(*key, "m.*")
    return d.withColumn("sem", F.col("std") / F.sqrt("n"))


def w2_template(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = MAIN, readers: tuple[Reader, ...] = READERS, cap: int | None = None) -> DataFrame:
    """corpus, reader, metric, mean, sem, n of template folding, by record; records travel in batches."""
    return template_scores(corpora(spark, sf_dir, names, cap), readers)


def template_answers(records: DataFrame, readers: tuple[Reader, ...] = READERS, budget: int = 8_000) -> DataFrame:
    """(corpus, reader, rec_id, ref, hyp): records in batches whose answer fits the budget of tokens.

    Each batch's system text is the whole dictionary of its corpus, so a reader has every other template
    to take one for; the user text is one marker, or unfolded record, a line. Slots are filled in after.
    Dictionaries go once to each process that reads. Texts are written down compressed and travel once,
    to their batch; batches and templates are found from numbers of records and digests of masks.
    """
    spark = records.sparkSession
    n = tasks(spark)
    records = records.select("corpus", "rec_id", F.regexp_replace(F.coalesce("text", F.lit("")), r"[ \t\n\r\f]+", " ").alias("text"))
    records = counted(records)
    catalogue = written(templates_mined(records.select("corpus", "rec_id", "text")))
    entries: dict[str, list[str]] = {}
    for r in catalogue.select("corpus", "tpl_id", "masked").orderBy("corpus", "tpl_id").toLocalIterator():
        entries.setdefault(r.corpus, []).append(f"<M{r.tpl_id}> = {r.masked}")
    systems = spark.sparkContext.broadcast({k: UNFOLD + ENTRY_END.join(v) for k, v in entries.items()})
    del entries
    starts = spark.sparkContext.broadcast({k: np.array(v, np.int64) for k, v in S.budget_starts(records, budget).items()})

    @F.pandas_udf("long")
    def batch_of(corpus: pd.Series, rec_id: pd.Series) -> pd.Series:
        out = np.zeros(len(corpus), np.int64)
        for name, at in corpus.groupby(corpus).indices.items():
            out[at] = np.searchsorted(starts.value.get(name, np.zeros(0, np.int64)), rec_id.iloc[at].fillna(-(2**63)).to_numpy(np.int64), "right") - 1
        return pd.Series(np.maximum(out, 0))

    own = ~F.contains("text", F.lit("#"))
    known = catalogue.select("corpus", F.md5(F.col("masked").cast("binary")).alias("_mask"), "tpl_id")
    made = records.drop("n_tok").withColumn("_mask", F.when(own, F.md5(masked("text").cast("binary")))).join(F.broadcast(known), ["corpus", "_mask"], "left").drop("_mask")
    made = made.withColumn("batch", batch_of("corpus", "rec_id")).withColumn("group", F.pmod(F.xxhash64("corpus", "batch"), F.lit(n)))
    made = made.repartition(n, "group").sortWithinPartitions("corpus", "batch", "rec_id", "text")
    marker = F.concat(F.lit("<M"), F.col("tpl_id").cast("string"), F.lit(">"))
    made = made.select("corpus", "batch", "rec_id", "text", F.when(F.col("tpl_id").isNotNull(), F.concat(F.array(marker), slots("text"))).otherwise(F.array("text")).alias("folded"))

    def answered(corpus: str, rows: list[tuple[int, str, list[str]]]) -> Iterator[pa.RecordBatch]:
        system, user = systems.value.get(corpus, UNFOLD), " \n ".join(f[0] for _, _, f in rows)
        for reader in readers:
            hyps = re.sub(" ?\n ?", "\n", reader.read_tried(system, user)).split("\n")
            hyps = [filled(h, f[1:]) for h, (_, _, f) in zip(hyps + [""] * (len(rows) - len(hyps)), rows, strict=False)]
            table = ([corpus] * len(rows), [reader.name] * len(rows), [r for r, _, _ in rows], [t for _, t, _ in rows], hyps)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(table, (pa.string(), pa.string(), pa.int64(), pa.string(), pa.string()), strict=True)], ["corpus", "reader", "rec_id", "ref", "hyp"])

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here, held = None, []
        for batch in rows:
            for k in range(batch.num_rows):
                corpus, no, *record = (batch.column(c)[k].as_py() for c in ("corpus", "batch", "rec_id", "text", "folded"))
                if (corpus, no) != here:
                    if held:
                        yield from answered(here[0], held)
                    here, held = (corpus, no), []
                held.append(tuple(record))
        if held:
            yield from answered(here[0], held)

    return made.mapInArrow(run, "corpus string, reader string, rec_id long, ref string, hyp string")


def filled(line: str, values: list[str]) -> str:
    """As fill; a line without values is left as it is."""
    return "".join(p + (values[i] if i < len(values) else "") for i, p in enumerate(line.split("#"))) if values else line


def template_scores(records: DataFrame, readers: tuple[Reader, ...] = READERS) -> DataFrame:
    return mean_scores(template_answers(records, readers), ["corpus", "reader"])


def w3_full(spark: SparkSession, sf_dir: str, readers: tuple[Reader, ...] = READERS) -> DataFrame:
    """As w2 on whole tables: events (few templates) and document lines (many)."""
    ev = events_records(spark, sf_dir).select(F.lit("events").alias("corpus"), "rec_id", "text")
    docs = line_records(read(spark, sf_dir, "documents").select("doc_id", "text"), "doc_id", "doc_lines").where("text <> ''")
    return template_scores(ev.unionByName(docs), readers)


def budget_texts(spark: SparkSession, sf_dir: str, names: tuple[str, ...], budget: int) -> DataFrame:
    """Texts of shards of a budget of tokens over the whole of each corpus."""
    records = counted(corpora(spark, sf_dir, names).select("corpus", "rec_id", "text"))
    return S.shard_texts(dealt(S.assign_shards(records, budget, counted=True), "shard_id"))


def read_shards(shards: DataFrame, l_maxs: Iterable[int], readers: tuple[Reader, ...], each: Callable[[str, list[str], Folded, tuple[str, ...]], tuple], schema: str) -> DataFrame:
    """shard_id, corpus, l_max and each(text, units, folded, answers of all readers) in the columns of schema.

    A shard is folded, prompted, read and looked at in one place, so neither folded units nor answers
    travel. Lengths that fold alike, as those beyond the longest repeated run, are read once.
    """
    grid = sorted(l_maxs)
    kinds = [("shard_id", pa.string()), ("corpus", pa.string()), ("l_max", pa.int32()), *[(x.split()[0], {"string": pa.string(), "long": pa.int64(), "double": pa.float64(), "array<double>": pa.list_(pa.float64())}[x.split()[1]]) for x in schema.split(", ")]]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                shard_id, corpus, text = (batch.column(c)[k].as_py() for c in ("shard_id", "corpus", "text"))
                units, rows, done = unit_list(text), [], {}
                for m, folded in zip(grid, folded_under(units, [Options(l_max=m) for m in grid]), strict=True):
                    prompt = prompt_texts([(e.marker, e.units) for e in folded.legend], folded.folded)
                    if prompt not in done:
                        done[prompt] = each(text or "", units, folded, tuple(r.read_tried(*prompt) for r in readers))
                    rows.append((shard_id, corpus, m, *done[prompt]))
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(zip(*rows, strict=True), kinds, strict=True)], [n for n, _ in kinds])

    return shards.select("shard_id", "corpus", "text").mapInArrow(run, f"shard_id string, corpus string, l_max int, {schema}")


def w4_pairs(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = MAIN, l_maxs: Iterable[int] = range(3, 11), readers: tuple[Reader, ...] = READERS, budget: int = 8_000) -> DataFrame:
    """shard_id, corpus, l_max, reader, cr, ref, hyp of all records, in shards of a budget of tokens.

    The budget stands for a reader's output window.
    """
    schema = "cr double, ref string, " + ", ".join(f"a{i} string" for i in range(len(readers)))
    d = read_shards(budget_texts(spark, sf_dir, names, budget), l_maxs, readers, lambda text, units, folded, answers: (folded.cr, " ".join(units), *answers), schema)
    pairs = F.explode(F.array(*[F.struct(F.lit(r.name).alias("reader"), F.col(f"a{i}").alias("hyp")) for i, r in enumerate(readers)]))
    return d.withColumn("p", pairs).select("shard_id", "corpus", "l_max", "p.reader", "cr", "ref", "p.hyp")


def w4_fold_quality(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = MAIN, l_maxs: Iterable[int] = range(3, 11), readers: tuple[Reader, ...] = READERS, budget: int = 8_000) -> DataFrame:
    """corpus, l_max, reader, cr, metric, value on whole shards, the pairs of w4_pairs measured where they are made."""
    schema = "cr double, " + ", ".join(f"a{i} array<double>" for i in range(len(readers)))

    def each(text: str, units: list[str], folded: Folded, answers: tuple[str, ...]) -> tuple:
        ref = " ".join(units)
        return (folded.cr, *(list(M.measures(ref, a)) for a in answers))

    d = read_shards(budget_texts(spark, sf_dir, names, budget), l_maxs, readers, each, schema)
    by_reader = F.explode(F.array(*[F.struct(F.lit(r.name).alias("reader"), F.col(f"a{i}").alias("values")) for i, r in enumerate(readers)]))
    d = d.withColumn("p", by_reader).select("corpus", "l_max", "p.reader", "cr", F.posexplode("p.values").alias("i", "value"))
    return d.select("corpus", "l_max", "reader", F.get(F.array(*map(F.lit, M.MEASURES)), "i").alias("metric"), "value", "cr")


def w5_regress(spark: SparkSession, sf_dir: str, **grid) -> DataFrame:
    """Regression of every metric on cr, by reader; a run is a corpus under an l_max, the mean of its shards."""
    runs = w4_fold_quality(spark, sf_dir, **grid).groupBy("corpus", "l_max", "reader", "metric").agg(F.avg("value").alias("value"), F.avg("cr").alias("cr"))
    return M.regress(runs, "value", "cr", ("reader", "metric"))


def w6_clusters(spark: SparkSession, sf_dir: str, **grid) -> DataFrame:
    d = w1_ratio(spark, sf_dir, **grid).groupBy("corpus").agg(F.avg("cr").alias("mean_cr"))
    return d.withColumn("cluster", M.cluster("mean_cr"))


def w7_best(spark: SparkSession, sf_dir: str, **grid) -> DataFrame:
    return M.best_lmax(w1_ratio(spark, sf_dir, **grid))


def w8_outliers(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = MAIN, reader: Reader = READERS[1]) -> DataFrame:
    """corpus, digit_density, mean_unit_len, confusable_share, prose_share, levenshtein of a simulated reader, in shards of 8,000 tokens.

    prose_share: of the units beside markers, those that are words of letters.
    """
    schema = "digits long, units long, chars long, n_entries long, n_confusable long, n_around long, n_prose long, lev double"

    def each(text: str, units: list[str], folded: Folded, answers: tuple[str, ...]) -> tuple:
        masks = Counter(re.sub("[0-9]+", "#", " ".join(e.units)) for e in folded.legend)
        marks = [u.startswith("<M") for u in folded.folded]
        beside = [u for u, m, before, after in zip(folded.folded, marks, [False, *marks], [*marks[1:], False], strict=False) if not m and (before or after)]
        n_prose = sum(_PROSE.fullmatch(u) is not None for u in beside)
        digits = sum(_DIGIT.search(u) is not None for u in units)
        return digits, len(units), len(text), masks.total(), sum(n for n in masks.values() if n > 1), len(beside), n_prose, M.lev_of(" ".join(units), answers[0])

    d = read_shards(budget_texts(spark, sf_dir, names, 8_000), [10], (reader,), each, schema)
    n = F.nullif("units", F.lit(0))
    share = lambda a, b: F.sum(a) / F.nullif(F.sum(b), F.lit(0))
    return d.groupBy("corpus").agg(
        F.avg(F.coalesce(F.col("digits") / n, F.lit(0.0))).alias("digit_density"),
        F.avg(F.col("chars") / n).alias("mean_unit_len"),
        share("n_confusable", "n_entries").alias("confusable_share"),
        share("n_prose", "n_around").alias("prose_share"),
        F.avg("lev").alias("levenshtein"),
    )


def w9_scale(spark: SparkSession, sf_dirs: Iterable[str], cap: int | None = None, count: int = 2000) -> DataFrame:
    """sf, records, seconds, units_per_s, cr_input of folding whole corpora."""
    rows = []
    for d in sf_dirs:
        start = time.time()
        folded = fold_sweep(S.shard_texts(S.assign_shards_count(S.parts(corpora(spark, d, MAIN, cap), 16, NUMBERED), count, NUMBERED)), [10])
        r = folded.agg(F.count("*").alias("n"), F.sum("n_tok").alias("t"), F.sum("n_tok_folded").alias("f"), F.sum("n_tok_legend").alias("l")).first()
        took = time.time() - start
        rows.append((d.rsplit("/", 1)[-1], r.n, took, r.t / took, 1 - (r.f + r.l) / r.t))
    return spark.createDataFrame(rows, "sf string, shards long, seconds double, tokens_per_s double, cr_input double")


def w10_local_global(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = MAIN, counts: Iterable[int] = (2000, 500, 125)) -> DataFrame:
    """mode, count, corpus, cr_input: own legends against one for all, by records a shard."""
    records = checkpointed(dealt(corpora(spark, sf_dir, names)))
    out = None
    for count in counts:
        shards = checkpointed(S.shard_texts(dealt(S.assign_shards_count(records, count, NUMBERED), "shard_id")))
        for mode, d in (("local", fold_sweep(shards, [10])), ("global", fold_global(shards))):
            one = M.ratios(d, ["corpus"]).select(F.lit(mode).alias("mode"), F.lit(count).alias("count"), "corpus", "cr_input")
            out = one if out is None else out.unionByName(one)
    return out


def w11_cost(spark: SparkSession, sf_dir: str, prices: Iterable[float] = (1.0, 3.0), budget: int = 64_000, **grid) -> DataFrame:
    """corpus, l_max, price, cost_raw, cost_folded, records_raw, records_folded by window; output tokens are not reduced."""
    d = fold_sweep(standard_shards(spark, sf_dir, **grid), range(3, 21))
    d = d.groupBy("corpus", "l_max").agg(F.sum("n_tok").alias("raw"), F.sum(F.col("n_tok_folded") + F.col("n_tok_legend")).alias("short"))
    # Each length has all shards of a corpus, so all of its records.
    d = d.join(F.broadcast(corpora(spark, sf_dir, **grid).groupBy("corpus").agg(F.count("*").alias("n"))), "corpus")
    d = d.withColumn("price", F.explode(F.array(*map(F.lit, prices))))
    per = lambda c: F.floor(budget * F.col("n") / F.col(c)).cast("long")
    return d.select("corpus", "l_max", "price", (F.col("raw") * F.col("price") / 1e6).alias("cost_raw"), (F.col("short") * F.col("price") / 1e6).alias("cost_folded"), per("raw").alias("records_raw"), per("short").alias("records_folded"))


def traces(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Process traces: each user's event types in time order, one record a user."""
    e = read(spark, sf_dir, "events").groupBy("user_id").agg(F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type"))).alias("x"))
    return e.select(F.lit("traces").alias("corpus"), F.col("user_id").cast("long").alias("rec_id"), F.lit(None).cast("timestamp").alias("ts"), F.array_join(F.transform("x", lambda v: v["event_type"]), " ").alias("text"))


def w12_domains(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ratios on process traces, pages, page text and documents."""
    pages = corpora(spark, sf_dir, EXTRA[:1])
    plain = pages.select(F.lit("html_text").alias("corpus"), "rec_id", "ts", strip_tags("text").alias("text"))
    docs = corpora(spark, sf_dir, tuple(f"doc_{x}" for x in LANGS))
    d = traces(spark, sf_dir).unionByName(pages).unionByName(plain).unionByName(docs)
    return M.ratios(fold_sweep(S.shard_units(S.assign_shards_count(d)), (3, 5, 10, 20)), ["corpus", "l_max"]).drop("n_tok", "n_tok_folded", "n_tok_legend")


def w14_profile(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = MAIN) -> DataFrame:
    """corpus, records, tokens, templates, shards_64k, shards_32k."""
    r = corpora(spark, sf_dir, names, None).withColumn("n_tok", tok_pieces("text"))
    d = r.groupBy("corpus").agg(F.count("*").alias("records"), F.sum("n_tok").alias("tokens"))
    t = templates_mined(r).groupBy("corpus").agg(F.count("*").alias("templates"))
    d = d.join(t, "corpus", "left")
    return d.select("corpus", "records", "tokens", F.coalesce("templates", F.lit(0)).alias("templates"), F.ceil(F.col("tokens") / 64_000).cast("long").alias("shards_64k"), F.ceil(F.col("tokens") / 32_000).cast("long").alias("shards_32k"))


def template_vs_fold(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = MAIN) -> DataFrame:
    """corpus, method, n_tok, n_tok_folded, n_tok_legend, cr, cr_input of both methods."""
    records = corpora(spark, sf_dir, names)
    a = M.ratios(fold_sweep(S.shard_texts(S.assign_shards_count(records, numbered=NUMBERED)), [10]), ["corpus"]).withColumn("method", F.lit("fold"))
    b = M.ratios(template_sizes(records), ["corpus"]).withColumn("method", F.lit("template"))
    return a.unionByName(b)


def template_sizes(records: DataFrame) -> DataFrame:
    """corpus, n_tok, n_tok_folded, n_tok_legend of folding by mined templates, slots apart.

    Sums by mask come first, so no record meets the catalogue. A text with a `#` of its own counts for
    its mask, but is not folded.
    """
    own = F.contains("text", F.lit("#"))
    sums = {"n": F.count("*"), "n_fit": F.count_if(~own), "n_tok": F.sum("_t"), "n_tok_fit": F.sum(F.when(~own, F.col("_t"))), "n_tok_slots": F.sum(F.when(~own, tok_pieces(F.array_join(slots("text"), " "))))}
    d = records.select("corpus", "text", masked("text").alias("masked"), tok_pieces("text").alias("_t"))
    d = checkpointed(d.groupBy("corpus", "masked").agg(*[F.coalesce(v, F.lit(0)).alias(k) for k, v in sums.items()]))
    fits = d.where("n >= 2 and masked is not null").withColumn("tpl_id", F.row_number().over(Window.partitionBy("corpus").orderBy(F.desc("n"), "masked")))
    marker = F.concat(F.lit("<M"), F.col("tpl_id").cast("string"), F.lit(">"))
    less = F.col("n_tok_fit") - F.col("n_fit") * tok_pieces(marker) - F.col("n_tok_slots")
    entry = F.when(F.col("n_fit") > 0, tok_pieces(F.concat(marker, F.lit(" "), "masked"))).otherwise(0)
    fits = fits.groupBy("corpus").agg(F.sum(less).alias("less"), F.sum(entry).alias("n_tok_legend"))
    d = d.groupBy("corpus").agg(F.sum("n_tok").alias("n_tok")).join(fits, "corpus", "left").fillna(0, ["less", "n_tok_legend"])
    return d.select("corpus", "n_tok", (F.col("n_tok") - F.col("less")).alias("n_tok_folded"), "n_tok_legend")


def template_roundtrip(records: DataFrame, mode: str = "slots", slots_too: bool = True) -> DataFrame:
    catalogue = checkpointed(templates_mined(records, slots_too=slots_too))
    return unfold_templates(fold_templates(records, catalogue, mode), catalogue, mode)


def aligned_exact(spark: SparkSession, sf_dir: str, names: tuple[str, ...], cap: int | None = None) -> DataFrame:
    """(corpus, rec_id, ref, hyp) through prompts and the exact reader; line breaks are units of their own."""
    records = S.assign_shards_count(corpora(spark, sf_dir, names, cap), numbered=NUMBERED)
    folded = fold_sweep(S.shard_units(records, "lines"), [10], full=True)
    prompts = build_prompts(folded).select("shard_id", "reader", "system", "user")  # no counts of tokens
    a = read_prompts(prompts, ExactReader()).withColumn("answer", F.regexp_replace("answer", " ?\n ?", "\n"))
    return align(a, records)
