"""Language identification by prediction by partial matching.

For each language a byte context tree of bounded order is counted on learning texts and frozen. A
byte's code length comes from the longest context that has been seen; a byte new to a context costs
that context's escape and is coded one order lower, excluding nothing, down to a uniform code over all
bytes (escape by the number of distinct bytes seen: method C). The language with the shortest code for
the whole text wins.

As the statistics are frozen, a byte's code length depends on the ORDER bytes before it alone, through
the longest of their suffixes that any language has seen. So the lengths of all languages are tabled
once, exactly, by (suffix, byte), and a text is coded by two gathers a byte instead of a tree walk.

Counts cover the whole texts of all learning rows. They are made map-side, as sorted arrays of
(order + 1)-byte runs; shorter contexts' counts are sums of these, and all of them are in the model. Its
form alone is bounded: the most frequent contexts, over all languages, have tables of all bytes until
these take most_cells numbers. Of the others only what was seen is listed, so their bytes are looked up
by search, each distinct run of a slice once.

Cases. Null texts and texts without a letter are `und` with score 0. Ties go to the language whose
name comes first. Rows are returned one for one, null and repeated doc_ids too. An empty table, or one
without learning rows, gives `und`. Other columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import SLICE_BYTES, byte_texts, cut, held_out, parts, table

ORDER = 3
_LETTER = re.compile(r"[^\W\d_]")
#: Symbols of a run: 0 before the start of a text, else a byte plus one.
RADIX = 257
#: Distinct runs that a task holds before it hands them on.
MOST_RUNS = 1 << 20
Counts = tuple[np.ndarray, np.ndarray]


def runs_of(texts: list[bytes], order: int) -> Counts:
    """(run, how often), ascending: every byte of the texts with the `order` symbols before it."""
    texts = [t for t in texts if t]
    if not texts:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    size = np.array([len(t) for t in texts])
    first = np.cumsum(size) - size
    x = np.frombuffer(b"".join(texts), np.uint8).astype(np.int64) + 1
    code, place = x.copy(), np.arange(len(x)) - np.repeat(first, size)
    for j in range(1, order + 1):
        before = np.zeros(len(x), np.int64)
        before[j:] = x[:-j]
        before[place < j] = 0
        code += before * RADIX**j
    return np.unique(code, return_counts=True)


def together(parts: list[Counts]) -> Counts:
    codes, n = (np.concatenate(x) for x in zip(*parts, strict=True))
    found, at = np.unique(codes, return_inverse=True)
    return found, np.bincount(at, n, len(found)).astype(np.int64)


def counts_of(texts: list[bytes], order: int) -> list[Counts]:
    """Runs of some texts with 0 .. order symbols of context."""
    code, n = runs_of(texts, order)
    return [together([(code % RADIX ** (k + 1), n)]) for k in range(order + 1)]


#: Numbers in the tables of frequent contexts, at four bytes each.
MOST_CELLS = 16 << 20
#: Row of a context that is listed, or has a suffix that is.
LISTED = -1


class ContextTables:
    """Exact code lengths in bits, for all languages, by (context, byte)."""

    def __init__(self, counts: dict[str, list[Counts]], most_cells: int | None = None):
        """counts: for each language its runs by order; with a context, all its suffixes are in some language's runs.

        most_cells bounds the tables, not the model: contexts beyond it are listed.
        """
        self.names = sorted(counts)
        self.order = max((len(c) for c in counts.values()), default=1) - 1
        used = np.unique(np.concatenate([np.zeros(1, np.int64), *(counts[n][0][0] for n in self.names)]))[1:]
        #: Symbol of each byte; 0: before the start of a text, 1: bytes that no language has seen.
        self.symbol = np.ones(256, np.int32)
        self.symbol[used - 1] = np.arange(2, len(used) + 2)
        self.size = a = len(used) + 2
        dense = np.concatenate((np.zeros(1, np.int64), self.symbol))

        def packed(runs: Counts, k: int) -> Counts:
            code = sum(dense[runs[0] // RADIX**j % RADIX] * a**j for j in range(k + 1))
            rank = np.argsort(code)
            return code[rank], runs[1][rank]

        own = [[packed(runs, k) for k, runs in enumerate(counts[n])] for n in self.names]
        contexts, rare = self._ranked(own, most_cells)
        self._table([[(c[at], n[at]) for (c, n), at in ((x, ~np.isin(x[0] // a, rare[k])) for k, x in enumerate(by))] for by in own], contexts, rare)
        self.listed = [self._list([by[k] for by in own], rare[k]) for k in range(self.order + 1)]

    def _ranked(self, counts: list, most_cells: int | None) -> tuple[list[np.ndarray], list[np.ndarray]]:
        """By order, contexts of any language that get tables, and those that are listed.

        A context is at least as frequent as those it is a suffix of, so one with a table has no suffix without.
        """
        a = self.size
        found = [together([(c // a, n) for c, n in (by[k] for by in counts)]) if counts else (np.zeros(0, np.int64),) * 2 for k in range(self.order + 1)]
        found[0] = np.zeros(1, np.int64), np.array([found[0][1].sum()])
        order = np.repeat(np.arange(len(found)), [len(c) for c, _ in found])
        code, total = (np.concatenate(x) for x in zip(*found, strict=True))
        n = len(code) if most_cells is None else max(1, most_cells // (a * max(len(self.names), 1)))
        kept = np.zeros(len(code), bool)
        kept[np.lexsort((code, order, -total))[:n]] = True
        return [code[kept & (order == k)] for k in range(len(found))], [code[~kept & (order == k)] for k in range(len(found))]

    def _list(self, counts: list[Counts], own: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Contexts with each language's bits of their escape, and their runs with each language's bits, nan where not seen."""
        a = self.size
        seen = [(c[at], n[at]) for (c, n), at in ((x, np.isin(x[0] // a, own)) for x in counts)]
        runs = np.unique(np.concatenate([np.zeros(0, np.int64), *(c for c, _ in seen)]))
        escapes, bits = np.zeros((len(own), len(counts)), np.float32), np.full((len(runs), len(counts)), np.nan, np.float32)
        for lang, (codes, n) in enumerate(seen):
            at = np.searchsorted(own, codes // a)
            total, kinds = np.bincount(at, n, len(own)), np.bincount(at, minlength=len(own))
            here = total > 0
            escapes[here, lang] = np.log2((total[here] + kinds[here]) / kinds[here])
            bits[np.searchsorted(runs, codes), lang] = np.log2((total[at] + kinds[at]) / n)
        return own, escapes, runs, bits

    def _looked_up(self, codes: np.ndarray, k: int) -> np.ndarray:
        """Bits of runs with k symbols of context."""
        a = self.size
        row = self.rows_of[k][codes // a]
        out = np.zeros((len(codes), len(self.names)), np.float32)
        tabled = row != LISTED
        out[tabled] = self.lengths[row[tabled].astype(np.int64) * a + codes[tabled] % a]
        rest = np.flatnonzero(~tabled)
        if not len(rest):
            return out
        codes = codes[rest]
        bits = self._looked_up(codes % a**k, k - 1)
        contexts, escapes, runs, known = self.listed[k]
        if len(contexts):
            at = np.minimum(np.searchsorted(contexts, codes // a), len(contexts) - 1)
            here = contexts[at] == codes // a
            bits[here] += escapes[at[here]]
            at = np.minimum(np.searchsorted(runs, codes), len(runs) - 1)
            bits = np.where((runs[at] == codes)[:, None] & ~np.isnan(known[at]), known[at], bits)
        out[rest] = bits
        return out

    def _table(self, counts: list, contexts: list[np.ndarray], rare: list[np.ndarray]) -> None:
        a, order = self.size, self.order
        # Order 0 is row 0; rows_of[k] maps the last k symbols to their row.
        first = np.cumsum([0, *map(len, contexts)])
        self.lengths = np.zeros((first[-1] * a, len(self.names)), np.float32)
        row_of = np.zeros(1, np.int32)
        self.rows_of = [row_of]
        for k in range(1, order + 1):
            row_of = np.tile(row_of, a)
            row_of[contexts[k]] = first[k] + np.arange(len(contexts[k]))
            row_of[rare[k]] = LISTED
            self.rows_of.append(row_of)
        for lang, by in enumerate(counts):
            uniform = np.full(a, np.log2(256.0))
            lower = uniform[None, :]
            for k in range(order + 1):
                own = contexts[k]
                below = lower if k == 0 else lower[np.searchsorted(contexts[k - 1], own % a ** (k - 1))]
                bits = np.array(below, np.float64)
                keys, n = by[k]
                if len(keys):
                    at = np.searchsorted(own, keys // a)
                    total = np.bincount(at, n, len(own))
                    kinds = np.bincount(at, minlength=len(own))
                    seen = total > 0
                    escape = np.zeros(len(own))
                    escape[seen] = np.log2((total[seen] + kinds[seen]) / kinds[seen])
                    bits += escape[:, None]
                    bits[at, keys % a] = np.log2((total[at] + kinds[at]) / n)
                self.lengths[first[k] * a : first[k + 1] * a, lang] = bits.ravel()
                lower = bits

    def code_lengths(self, texts: list[bytes]) -> np.ndarray:
        """Bits of every text in every language."""
        out = np.zeros((len(texts), len(self.names)))
        lengths = np.array([len(t) for t in texts])
        full = np.flatnonzero(lengths)
        if not len(full):
            return out
        gap = bytes(self.order)  # each text starts in the context of unseen bytes
        buf = np.frombuffer(gap.join([b"", *(texts[i] for i in full)]), np.uint8)
        x = self.symbol[buf].astype(np.int64)
        starts = np.cumsum(lengths[full] + self.order) - lengths[full]
        for j in range(self.order):
            x[starts - 1 - j] = 0
        context = np.zeros(len(x), np.int64)
        for j in range(self.order, 0, -1):
            context[j:] += x[:-j] * self.size ** (j - 1)
        row = self.rows_of[self.order][context].astype(np.int64)
        bits = self.lengths[np.maximum(row, 0) * self.size + x]
        at = np.flatnonzero(row == LISTED)
        if len(at):
            runs, which = np.unique(context[at] * self.size + x[at], return_inverse=True)
            bits[at] = self._looked_up(runs, self.order)[which]
        for j in range(self.order):
            bits[starts - 1 - j] = 0
        out[full] = np.add.reduceat(bits, starts, axis=0, dtype=np.float64)
        return out


def learned(docs: DataFrame, order: int = ORDER, most_cells: int = MOST_CELLS) -> ContextTables | None:
    """Code lengths counted over all learning rows of docs (doc_id, text, lang); None without any."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, Counts] = {}

        def out() -> Iterator[pa.RecordBatch]:
            for lang, (codes, n) in held.items():
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(codes), pa.string()), pa.array(codes, pa.int64()), pa.array(n, pa.int64())], ["lang", "code", "n"])
            held.clear()

        for part in parts(batches):
            texts: dict[str, list[bytes]] = {}
            for lang, text in zip(part.column(0).to_pylist(), byte_texts(part.column(1)), strict=True):
                texts.setdefault(lang, []).append(text)
            for lang, own in texts.items():
                new = runs_of(own, order)
                held[lang] = together([held[lang], new]) if lang in held else new
            if sum(len(c) for c, _ in held.values()) > MOST_RUNS:
                yield from out()
        yield from out()

    d = docs.where("lang is not null and text is not null and text <> ''").where(~held_out()).select("lang", "text")
    runs = d.mapInArrow(run, "lang string, code long, n long").groupBy("lang", "code").agg(F.sum("n").alias("n"))
    by_order = F.explode(F.array(*[F.struct(F.lit(k).alias("k"), (F.col("code") % RADIX ** (k + 1)).alias("code")) for k in range(order + 1)]))
    counts = cut(runs.select("lang", "n", by_order.alias("x")).groupBy("lang", "x.k", "x.code").agg(F.sum("n").alias("n")))
    found = counts.orderBy("lang", "k", "code").toArrow()
    if not found.num_rows:
        return None
    k, code, n = (found.column(c).to_numpy() for c in ("k", "code", "n"))
    lang = found.column("lang").combine_chunks().dictionary_encode()
    names, own = lang.dictionary.to_pylist(), lang.indices.to_numpy()
    return ContextTables({x: [(code[at], n[at]) for at in (np.flatnonzero((own == i) & (k == j)) for j in range(order + 1))] for i, x in enumerate(names)}, most_cells)


def identify(docs: DataFrame, tables: ContextTables | None) -> DataFrame:
    """doc_id, lang_pred, score, bits_per_byte of every row of docs (doc_id, text)."""
    sent = docs.sparkSession.sparkContext.broadcast(tables)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = sent.value
        for part in parts(batches, most=SLICE_BYTES // 4):
            texts = [x or "" for x in part.column(1).to_pylist()]
            raw = [x.encode() for x in texts]
            lang, score, rate = [], [], []
            bits = t.code_lengths(raw) if t and t.names else np.zeros((len(raw), 1))
            best = bits.argmin(1)
            for x, b, row, k in zip(texts, raw, bits, best.tolist(), strict=True):
                if not (t and t.names and _LETTER.search(x)):
                    lang.append("und"), score.append(0.0), rate.append(None)
                    continue
                lang.append(t.names[k])
                score.append(float(1 / np.exp2(np.maximum(row[k] - row, -1000)).sum()))
                rate.append(float(row[k] / len(b)))
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(lang, pa.string()), pa.array(score, pa.float64()), pa.array(rate, pa.float64())], ["doc_id", "lang_pred", "score", "bits_per_byte"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, lang_pred string, score double, bits_per_byte double")


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return identify(docs, learned(docs)).select("doc_id", held_out().alias("held_out"), "lang_pred", "score", "bits_per_byte")
