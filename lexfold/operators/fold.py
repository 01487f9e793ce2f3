"""Folding shards, as a kernel over one row a shard or relationally; legends, unfolding, checks."""

from __future__ import annotations

import re
from collections.abc import Iterable, Iterator
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import COSTS, UNIT, disjoint_starts, unfold_expr
from .grams import at_home, grams, stretches
from .kernel import Folded, Options, Shard, token_cost
from .lineage import checkpointed
from .shards import shard_units, unit_rows

_UNIT = re.compile(UNIT)
_ENTRY = pa.struct([("marker", pa.string()), ("units", pa.list_(pa.string())), ("len", pa.int32()), ("f", pa.int64()), ("gain", pa.int64()), ("starts", pa.list_(pa.int32()))])
FOLDED = "shard_id string, corpus string, l_max int, folded array<string>, legend array<struct<marker: string, units: array<string>, len: int, f: bigint, gain: bigint, starts: array<int>>>, borders array<int>, n_tok long, n_tok_folded long, n_tok_legend long, cr double, cr_input double, guarded boolean, l_eff int, error string"
SUMMARY = "shard_id string, corpus string, l_max int, n_entries int, n_tok long, n_tok_folded long, n_tok_legend long, cr double, cr_input double, guarded boolean, l_eff int, error string"
_TYPES = {"variant": pa.string(), "shard_id": pa.string(), "corpus": pa.string(), "l_max": pa.int32(), "folded": pa.list_(pa.string()), "legend": pa.list_(_ENTRY), "borders": pa.list_(pa.int32()), "n_entries": pa.int32(), "n_tok": pa.int64(), "n_tok_folded": pa.int64(), "n_tok_legend": pa.int64(), "cr": pa.float64(), "cr_input": pa.float64(), "guarded": pa.bool_(), "l_eff": pa.int32(), "error": pa.string()}


def _row(r: Folded, full: bool) -> dict:
    row = {k: getattr(r, k) for k in ("n_tok", "n_tok_folded", "n_tok_legend", "cr", "cr_input", "guarded", "l_eff")}
    if full:
        legend = [{"marker": e.marker, "units": e.units, "len": len(e.units), "f": e.f, "gain": e.gain, "starts": e.starts} for e in r.legend]
        return row | {"folded": r.folded, "legend": legend, "borders": r.borders}
    return row | {"n_entries": len(r.legend)}


def unit_list(text: str | None) -> list[str]:
    return _UNIT.findall(text or "")


def folded_under(units: list[str], grid: list[Options]) -> list[Folded]:
    """One shard folded under each of options of one cost; what fails raises, as unfolded text would pass for a result."""
    shard, done = Shard(units, grid[0].cost), {}
    own = [replace(o, l_max=max(o.l_min, min(o.l_max, shard.l_eff(o.l_max)))) for o in grid]
    for o in own:
        if o not in done:
            done[o] = shard.fold(o)
    return [done[o] for o in own]


def fold_sweep(shards: DataFrame, l_maxs: Iterable[int], options: Options | None = None, full: bool = False) -> DataFrame:
    """Every shard folded under each l_max, coded once; one row each (SUMMARY, or FOLDED if full).

    A shard that fails goes out unfolded with its error, so one odd shard does not end a job. Shards
    without units (`shard_texts`) are segmented here; they know no borders of records.
    """
    base = options or Options()
    return fold_variants(shards, [("", replace(base, l_max=m)) for m in sorted(l_maxs)], full).drop("variant")


def fold_variants(shards: DataFrame, variants: Iterable[tuple[str, Options]], full: bool = False) -> DataFrame:
    """As fold_sweep, under each of named options of one cost; the name goes into `variant`."""
    grid, schema = list(variants), "variant string, " + (FOLDED if full else SUMMARY)
    if len({o.cost for _, o in grid}) > 1:
        raise ValueError("variants of one cost are needed")
    names = [x.split()[0] for x in schema.replace("<", " <").split(", ") if x.split()[0] in _TYPES]
    names = list(dict.fromkeys(names))
    known = [c for c in ("units", "rec_starts", "text") if c in shards.columns]
    known = known[:2] if "units" in known else ["text"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, corpora = (batch.column(c).to_pylist() for c in ("shard_id", "corpus"))
            starts = batch.column("rec_starts").to_pylist() if "rec_starts" in known else [None] * batch.num_rows
            for k in range(batch.num_rows):
                if known == ["text"]:
                    units = unit_list(batch.column("text")[k].as_py())
                else:
                    units = [u for u in batch.column("units")[k].as_py() or [] if u is not None]
                rows, error = [], None
                try:
                    shard, done = Shard(units, grid[0][1].cost, starts[k]), {}
                    for _, o in grid:
                        own = replace(o, l_max=max(o.l_min, min(o.l_max, shard.l_eff(o.l_max))))
                        if own not in done:  # beyond the longest repeated run nothing changes
                            done[own] = shard.fold(own, full)
                        rows.append(_row(done[own], full))
                except Exception as e:
                    error = f"{type(e).__name__}: {e}"
                    n = sum(token_cost(u, grid[0][1].cost) for u in units)
                    rows = [_row(Folded(units, [], n, n, 0, True), full) for _ in grid]
                table = [r | {"variant": v, "shard_id": ids[k], "corpus": corpora[k], "l_max": o.l_max, "error": error} for r, (v, o) in zip(rows, grid, strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array([r[n] for r in table], _TYPES[n]) for n in names], names)

    return shards.select("shard_id", "corpus", *known).mapInArrow(run, schema)


def fold(shards: DataFrame, options: Options | None = None) -> DataFrame:
    """Folded shards (FOLDED); shards: shard_id, corpus, units, rec_starts."""
    o = options or Options()
    return fold_sweep(shards, [o.l_max], o, full=True)


def fold_records(records: DataFrame, options: Options | None = None, ws: str = "collapse") -> DataFrame:
    """Fold records that carry shard_id."""
    return fold(shard_units(records, ws), options)


def legend(folded: DataFrame) -> DataFrame:
    """One row a legend entry, in order."""
    d = folded.select("shard_id", "corpus", F.posexplode("legend").alias("no", "e"))
    return d.select("shard_id", "corpus", "no", "e.*")


def unfold(folded: DataFrame) -> DataFrame:
    """shard_id, corpus, units: what was folded."""
    return folded.select("shard_id", "corpus", unfold_expr("folded", "legend").alias("units"))


def unfold_relational(folded: DataFrame) -> DataFrame:
    """As unfold, by joining places with legend rows; for shards too long for one expression."""
    places = folded.select("shard_id", F.posexplode("folded").alias("at", "unit"))
    entries = legend(folded).select("shard_id", F.col("marker").alias("unit"), "units")
    d = places.join(entries, ["shard_id", "unit"], "left").select("shard_id", "at", F.coalesce("units", F.array("unit")).alias("run"))
    return d.groupBy("shard_id").agg(F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("at", "run"))), lambda x: x["run"])).alias("units"))


def apply_markers(rows: DataFrame, picks: DataFrame) -> DataFrame:
    """Folded places (shard_id, pos, unit) from units and picks (shard_id, marker, len, starts)."""
    heads = picks.select("shard_id", "marker", "len", F.explode("starts").alias("pos"))
    inner = skip_positions(picks)
    kept = rows.join(inner, ["shard_id", "pos"], "left_anti").join(heads.drop("len"), ["shard_id", "pos"], "left")
    return kept.select("shard_id", "pos", F.coalesce("marker", "unit").alias("unit"))


def skip_positions(picks: DataFrame) -> DataFrame:
    """Places that a marker swallows: all of its run but the first."""
    d = picks.select("shard_id", "len", F.explode("starts").alias("s")).where("len > 1")
    return d.select("shard_id", F.explode(F.sequence(F.col("s") + 1, F.col("s") + F.col("len") - 1)).alias("pos"))


def verify(folded: DataFrame, f_min: int = 2, saving_test: bool = True) -> DataFrame:
    """Violations of the folding's rules as (shard_id, rule, detail); empty when all hold."""
    e = legend(folded)
    own = folded.select("shard_id", F.transform("legend", lambda x: x["marker"]).alias("markers"))
    nested = e.join(own, "shard_id").where(F.arrays_overlap("units", "markers"))
    rows = [nested.select("shard_id", F.lit("nested").alias("rule"), F.col("marker").alias("detail"))]
    if saving_test:
        rows.append(e.where("gain <= 0").select("shard_id", F.lit("no gain"), "marker"))
    rows.append(e.where((F.col("f") < f_min) | (F.size("starts") != F.col("f"))).select("shard_id", F.lit("too few"), "marker"))
    places = e.select("shard_id", "marker", F.explode("starts").alias("s"), "len").select("shard_id", "marker", F.explode(F.sequence("s", F.col("s") + F.col("len") - 1)).alias("p"))
    rows.append(places.groupBy("shard_id", "p").agg(F.count("*").alias("n"), F.min("marker").alias("m")).where("n > 1").select("shard_id", F.lit("overlap"), "m"))
    sums = folded.where(F.col("n_tok") - F.col("n_tok_folded") - F.col("n_tok_legend") != F.aggregate("legend", F.lit(0).cast("long"), lambda a, x: a + x["gain"]))
    rows.append(sums.select("shard_id", F.lit("sums"), F.col("n_tok").cast("string")))
    rows.append(folded.where((F.size("legend") > 0) & (F.col("cr_input") <= 0)).select("shard_id", F.lit("larger"), F.col("cr_input").cast("string")))
    out = rows[0]
    for r in rows[1:]:
        out = out.union(r)
    return out


def find_at_length(rows: DataFrame, length: int, f_min: int = 2, cost: str = "unit", n_m: int = 1, covered: DataFrame | None = None) -> DataFrame:
    """Accepted grams of one length: shard_id, gram, len, rank, starts (as the sequential scan accepts them).

    Candidates are decided in rounds: one waits while an undecided, better ranked one could take places
    from it. Free places only shrink, so one that fails the test already is out in any round.
    """
    g = grams(rows, length)
    if covered is not None:
        # A covered run is at least as long as this one, so touching it means covering an end.
        for at in (F.col("pos"), F.col("pos") + length - 1):
            g = g.withColumn("at", at).join(covered.select("shard_id", F.col("pos").alias("at")), ["shard_id", "at"], "left_anti").drop("at")
    often = g.groupBy("shard_id", "gram").agg(F.count("*").alias("raw_f"), F.min("pos").alias("first_pos"))
    n_s = F.lit(length) if cost == "unit" else F.aggregate(F.transform("gram", lambda u: COSTS[cost](u)), F.lit(0).cast("long"), lambda a, x: a + x)
    often = often.withColumn("n_s", n_s)
    pays = lambda f: (f >= f_min) & (f * F.col("n_s") > (1 + f) * n_m + F.col("n_s"))
    # Ranks need no numbers, only an order, so no window goes over a shard.
    often = often.where(pays(F.col("raw_f"))).withColumn("rank", F.struct((-F.col("raw_f")).alias("less"), "first_pos"))
    state = checkpointed(g.join(often, ["shard_id", "gram"]).select("shard_id", "gram", "rank", "n_s", F.col("pos").alias("start"), F.lit(False).alias("used")))
    near = Window.partitionBy("shard_id", "_s").orderBy("start").rangeBetween(-(length - 1), length - 1)
    while state.where("not used").limit(1).count():
        s = stretches(state, "start", length - 1, length - 1)
        s = s.withColumn("hit", F.max("used").over(near)).withColumn("best", F.min(F.when(~F.col("used"), F.col("rank"))).over(near)).where(at_home("start")).drop("_s")
        free = s.where("not used and not hit")
        cands = free.groupBy("shard_id", "rank", "gram", "n_s").agg(F.collect_list("start").alias("starts"), F.max(F.col("best") < F.col("rank")).alias("waits"))
        thin = disjoint_starts("starts", length)
        cands = cands.withColumn("thin", thin).withColumn("ok", pays(F.size("thin")))
        yes = cands.where("ok and not waits").select("shard_id", "gram", "rank", "n_s", F.explode("thin").alias("start"), F.lit(True).alias("used"))
        wait = cands.where("ok and waits").select("shard_id", "gram", "rank", "n_s", F.explode("starts").alias("start"), F.lit(False).alias("used"))
        state = checkpointed(state.where("used").unionByName(yes).unionByName(wait))
    return state.groupBy("shard_id", "gram", "rank").agg(F.sort_array(F.collect_list("start")).alias("starts")).withColumn("len", F.lit(length))


def fold_relational(shards: DataFrame, l_max: int = 10, f_min: int = 2, l_min: int = 2, cost: str = "unit", fixed_marker: str = "<M999>") -> DataFrame:
    """Picks (shard_id, gram, len, marker_no, marker, starts) of shards too large for the kernel.

    Equal to the kernel under marker_cost="fixed"; markers found in the text are skipped in numbering.
    """
    rows = checkpointed(unit_rows(shards))
    n_m = token_cost(fixed_marker, cost)
    covered, picks = None, None
    for length in range(l_max, l_min - 1, -1):
        found = checkpointed(find_at_length(rows, length, f_min, cost, n_m, covered))
        picks = found if picks is None else picks.unionByName(found)
        own = found.select("shard_id", F.explode("starts").alias("s")).select("shard_id", F.explode(F.sequence("s", F.col("s") + length - 1)).alias("pos"))
        covered = own if covered is None else covered.union(own)
    order = Window.partitionBy("shard_id").orderBy(F.desc("len"), "rank")
    numbered = picks.withColumn("nth", F.row_number().over(order))
    literal = rows.select("shard_id", F.explode(F.regexp_extract_all("unit", F.lit("<M([1-9][0-9]*)>"), F.lit(1))).alias("k")).select("shard_id", F.col("k").cast("int").alias("k"))
    skips = literal.groupBy("shard_id").agg(F.sort_array(F.collect_set("k")).alias("skips"))
    d = numbered.join(skips, "shard_id", "left")
    # The nth free number: each literal number at or below the running number pushes it up by one.
    no = F.aggregate(F.coalesce("skips", F.array().cast("array<int>")), F.col("nth"), lambda at, k: F.when(k <= at, at + 1).otherwise(at))
    d = d.withColumn("marker_no", no)
    return d.select("shard_id", "gram", "len", "marker_no", F.concat(F.lit("<M"), F.col("marker_no").cast("string"), F.lit(">")).alias("marker"), "starts")


def fold_global(shards: DataFrame, options: Options | None = None) -> DataFrame:
    """Baseline: one legend for all shards of a corpus, which every shard pays in full.

    The legend is learned on the shards in a row and sent to each; returns shard_id, corpus, n_tok,
    n_tok_folded, n_tok_legend, cr_input. shards: shard_id, corpus, text, segmented here. The corpus must
    fit the kernel (one task a corpus, equal units held once); it is a baseline, not a plan.
    """
    o = options or Options()

    def run(key: tuple[pa.Scalar, ...], t: pa.Table) -> pa.Table:
        t = t.sort_by("shard_id")
        units, begins, known = [], [], {}
        for i, text in enumerate(t.column("text")):
            begins.append(len(units))
            units += [known.setdefault(u, u) for u in unit_list(text.as_py())]
            units.append(f"\x00{i}")  # no run crosses a shard
        shard = Shard(units, o.cost)
        made = shard.fold(replace(o, guard=False), full=False)
        begins = np.array([*begins, len(units)], np.int64)
        n = shard.total[begins[1:] - 1] - shard.total[begins[:-1]]
        saved = np.zeros(len(n), np.int64)
        for e in made.legend:
            at = np.searchsorted(begins, np.array(e.starts, np.int64), "right") - 1
            np.add.at(saved, at, e.n_s - shard.marker_cost(e.marker))
        ids, short, n_legend = t.column("shard_id").to_pylist(), n - saved, made.n_tok_legend
        ratio = np.where(n > 0, 1 - (short + n_legend) / np.maximum(n, 1), 0.0)
        columns = (ids, [key[0].as_py()] * len(ids), n, short, [n_legend] * len(ids), ratio)
        kinds = (pa.string(), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.float64())
        names = ["shard_id", "corpus", "n_tok", "n_tok_folded", "n_tok_legend", "cr_input"]
        return pa.Table.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names)

    return shards.select("corpus", "shard_id", "text").groupBy("corpus").applyInArrow(run, "shard_id string, corpus string, n_tok long, n_tok_folded long, n_tok_legend long, cr_input double")
