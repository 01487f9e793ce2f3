"""Column functions on text: units, token costs, saving arithmetic, masks, unfolding."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Fixed values. The class is written out because engines and Python disagree on what a blank is.
UNIT = r"[^ \t\n\r\f]+"
UNIT_OR_BREAK = r"[^ \t\n\r\f]+|\n"
GAP = r"[ \t\n\r\f]+"
WIDE_UNIT = r"[^\s\x0B\x1C-\x1F\x{85}\x{A0}\x{1680}\x{2000}-\x{200A}\x{2028}\x{2029}\x{202F}\x{205F}\x{3000}]+"
PIECE = r"\p{L}+|\p{N}{1,3}|[^\s\p{L}\p{N}]"
MARKER = "<M{k}>"
DIGITS = r"\p{N}+"


def col(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def let(value: Column, f) -> Column:
    """f of a value that is computed once; inside a lambda, an expression would be computed each time."""
    return F.get(F.transform(F.array(value), f), F.lit(0))


def units(text: Column | str, ws: str = "collapse", unicode_blanks: bool = False) -> Column:
    """Non-blank units in order; ws="lines" keeps line breaks as units of their own.

    ws="exact" gives the same units as "collapse"; `gaps` has what stood between them.
    """
    pattern = WIDE_UNIT if unicode_blanks else UNIT_OR_BREAK if ws == "lines" else UNIT
    return F.regexp_extract_all(col(text), F.lit(pattern), F.lit(0))


def gaps(text: Column | str) -> Column:
    """(pos, sep) of every separator that is not one blank; pos counts units before it."""
    t = col(text)
    seps = F.regexp_extract_all(t, F.lit(GAP), F.lit(0))
    leading = F.regexp_like(t, F.lit(f"^{GAP}")).cast("int")
    at = F.transform(seps, lambda s, i: F.struct((i + 1 - leading).alias("pos"), s.alias("sep")))
    return let(F.size(units(t)), lambda n: F.filter(at, lambda g: (g["sep"] != " ") | (g["pos"] == 0) | (g["pos"] == n)))


def rejoin(words: Column | str, seps: Column | str) -> Column:
    """The text that units and gaps came from."""
    w, g = col(words), col(seps)
    n = F.size(w)
    at = lambda p: F.coalesce(F.get(F.filter(g, lambda x: x["pos"] == p), F.lit(0))["sep"], F.lit(""))
    blanks = lambda many: F.array_repeat(F.lit(" "), many.cast("int"))

    def seps(inner: Column) -> Column:
        before = lambda k: F.coalesce(F.get(inner, k - 1)["pos"], F.lit(0))
        middle = F.flatten(F.transform(inner, lambda x, k: F.concat(blanks(x["pos"] - before(k) - 1), F.array(x["sep"]))))
        rest = blanks(F.greatest(n - 1 - F.coalesce(F.try_element_at(inner, F.lit(-1))["pos"], F.lit(0)), F.lit(0)))
        return F.concat(F.array(at(F.lit(0))), middle, rest)

    all_seps = let(F.filter(g, lambda x: (x["pos"] > 0) & (x["pos"] < n)), seps)
    return F.when(n == 0, at(F.lit(0))).otherwise(F.concat(F.array_join(F.zip_with(F.slice(all_seps, 1, n), w, lambda s, u: F.concat(s, u)), ""), at(n)))


def tok_unit(text: Column | str) -> Column:
    return F.size(units(text)).cast("long")


def tok_pieces(text: Column | str) -> Column:
    return F.regexp_count(col(text), F.lit(PIECE)).cast("long")


def tok_chars(text: Column | str, k: int = 4) -> Column:
    return F.ceil(F.length(col(text)) / F.lit(k)).cast("long")


COSTS = {"unit": tok_unit, "pieces": tok_pieces, "chars": tok_chars}


def vocab_costs(units_df: DataFrame, merges: dict[bytes, int], unit: str = "unit") -> DataFrame:
    """(unit, cost): tokens of each distinct unit under byte-pair ranks that the caller supplies.

    Distinct units are costed once; the table is joined where costs are needed.
    """

    def pieces(word: str) -> int:
        parts = [bytes([b]) for b in word.encode()]
        while len(parts) > 1:
            ranked = [(merges.get(a + b, 1 << 60), i) for i, (a, b) in enumerate(zip(parts, parts[1:], strict=False))]
            best, i = min(ranked)
            if best == 1 << 60:
                break
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
        return len(parts)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield b.assign(cost=b["unit"].map(pieces))

    return units_df.select(F.col(unit).alias("unit")).distinct().mapInPandas(run, "unit string, cost long")


def gain(f: Column | str, n_s: Column | str, n_m: Column | str, overhead: int = 0) -> Column:
    """Tokens saved by f uses of a gram of n_s tokens under a marker of n_m tokens."""
    f, s, m = col(f), col(n_s), col(n_m)
    return f * s - (1 + f) * m - s - overhead


def pays_off(f: Column | str, n_s: Column | str, n_m: Column | str, overhead: int = 0) -> Column:
    return gain(f, n_s, n_m, overhead) > 0


def break_even(n_s: Column | str, n_m: Column | str) -> Column:
    """Least number of uses that pays; null where none does."""
    s, m = col(n_s), col(n_m)
    return F.when(s > m, F.floor((s + m) / (s - m)).cast("long") + 1)


def prompt_cost(n_in: Column | str, n_out: Column | str, price_in: float, price_out: float) -> Column:
    return col(n_in) * F.lit(price_in) + col(n_out) * F.lit(price_out)


def whole_seconds(ts: Column | str) -> Column:
    """Seconds since 1970, rounded to the nearest; halves go to the even second."""
    return F.rint(F.unix_micros(col(ts).cast("timestamp")) / F.lit(1e6)).cast("long")


def records_per_window(n_records: Column | str, n_tokens: Column | str, budget: int) -> Column:
    return F.floor(F.lit(budget) * col(n_records) / F.nullif(col(n_tokens), F.lit(0))).cast("long")


def disjoint_starts(starts: Column | str, length: Column | int) -> Column:
    """Starts thinned left to right so that runs of this length do not overlap."""
    n = length if isinstance(length, Column) else F.lit(length)
    zero = F.struct(F.lit(-(1 << 30)).alias("last"), F.array().cast("array<int>").alias("kept"))
    step = lambda acc, p: F.when(p >= acc["last"] + n, F.struct(p.alias("last"), F.concat(acc["kept"], F.array(p)).alias("kept"))).otherwise(acc)
    return F.aggregate(F.sort_array(col(starts)), zero, step, lambda acc: acc["kept"])


def masked(text: Column | str) -> Column:
    """Digit runs replaced by a slot sign."""
    return F.regexp_replace(col(text), DIGITS, "#")


def slots(text: Column | str) -> Column:
    return F.regexp_extract_all(col(text), F.lit(DIGITS), F.lit(0))


def fill(mask: Column | str, values: Column | str) -> Column:
    """Inverse of masked and slots, for texts without a `#` of their own beside slots."""
    parts = F.split(col(mask), "#")
    return F.array_join(F.transform(parts, lambda p, i: F.concat(p, F.coalesce(F.get(col(values), i), F.lit("")))), "")


def legend_map(legend: Column | str) -> Column:
    return F.map_from_entries(F.transform(col(legend), lambda e: F.struct(e["marker"], e["units"])))


def unfold_expr(folded: Column | str, legend: Column | str) -> Column:
    """Units with every marker of the legend replaced by its entry; one pass, as entries hold no markers.

    Only units that begin as markers do are looked up: a lookup goes through the legend's keys.
    """
    own = lambda m: lambda u: F.when(F.startswith(u, F.lit("<M")), F.coalesce(F.try_element_at(m, u), F.array(u))).otherwise(F.array(u))
    return let(legend_map(legend), lambda m: F.flatten(F.transform(col(folded), own(m))))
