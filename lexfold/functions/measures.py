"""Ratios, fidelity measures of a reconstruction, and their statistics."""

from __future__ import annotations

import bisect
import functools
import itertools
import math
import re
import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from .text import UNIT, col, let, units

_UNIT = re.compile(UNIT)

#: Two-sided 95 % quantiles of Student's t by degrees of freedom; the normal's beyond 120.
T95 = {1: 12.706, 2: 4.303, 3: 3.182, 4: 2.776, 5: 2.571, 6: 2.447, 7: 2.365, 8: 2.306, 9: 2.262, 10: 2.228, 20: 2.086, 30: 2.042, 60: 2.000, 120: 1.980}

# --- ratios ---------------------------------------------------------------------------------------


def ratios(df: DataFrame, by: list[str]) -> DataFrame:
    """cr, cr_input and overhead of groups of shards, from sums of tokens; a shard that failed ends the query."""
    if "error" in df.columns:
        failed = F.raise_error(F.concat(F.lit("a shard was not folded: "), "error")).cast("long")
        df = df.withColumn("n_tok", F.when(F.col("error").isNotNull(), failed).otherwise(F.col("n_tok")))
    d = df.groupBy(*by).agg(*[F.sum(c).alias(c) for c in ("n_tok", "n_tok_folded", "n_tok_legend")])
    n = F.nullif("n_tok", F.lit(0))
    return d.withColumns({"cr": 1 - F.col("n_tok_folded") / n, "cr_input": 1 - (F.col("n_tok_folded") + F.col("n_tok_legend")) / n}).withColumn("overhead", F.col("cr") - F.col("cr_input"))


def cluster(cr: Column | str) -> Column:
    """low, medium or high; a flag `?` marks values outside the three named ranges."""
    c = col(cr)
    name = F.when(c < 0.2, "low").when(c < 0.6, "medium").otherwise("high")
    odd = (c < 0.1) | ((c >= 0.5) & (c < 0.6)) | (c > 0.8)
    return F.concat(name, F.when(odd, "?").otherwise(""))


def best_lmax(df: DataFrame, value: str = "cr_input", eps: float = 0.001) -> DataFrame:
    """corpus, best_l_max, best, plateau_at, last, loss_at_end, shape; df: corpus, l_max, value.

    plateau_at: first l_max after which no step changes the value by eps or more.
    """
    w = Window.partitionBy("corpus").orderBy("l_max")
    d = df.withColumn("_step", F.abs(F.col(value) - F.lag(value).over(w)))
    d = d.groupBy("corpus").agg(
        F.max_by("l_max", F.struct(F.col(value), -F.col("l_max"))).alias("best_l_max"),
        F.max(value).alias("best"),
        F.coalesce(F.max(F.when(F.col("_step") >= eps, F.col("l_max"))), F.min("l_max")).alias("plateau_at"),
        F.max_by(value, "l_max").alias("last"),
    )
    d = d.withColumn("loss_at_end", F.col("best") - F.col("last"))
    return d.withColumn("shape", F.when(F.col("loss_at_end") >= eps, "peak then decline").otherwise("plateau"))


# --- fidelity of one pair -------------------------------------------------------------------------


def exact_match(r: Column | str, h: Column | str) -> Column:
    return (col(r) == col(h)).cast("int")


def lev_sim(r: Column | str, h: Column | str) -> Column:
    """1 - edits / longer length, by code point; for records."""
    most = F.greatest(F.length(col(r)), F.length(col(h)))
    return F.when(most == 0, 1.0).otherwise(1 - F.levenshtein(col(r), col(h)) / most)


def ham_sim(r: Column | str, h: Column | str) -> Column:
    """Equal places / longer length."""
    most = F.greatest(F.length(col(r)), F.length(col(h)))
    same = F.size(F.filter(F.zip_with(F.split(col(r), ""), F.split(col(h), ""), lambda a, b: F.coalesce(a == b, F.lit(False))), lambda x: x))
    return F.when(most == 0, 1.0).otherwise(F.when((F.length(col(r)) == 0) | (F.length(col(h)) == 0), 0.0).otherwise(same / most))


def presence(h: Column | str, expected: Column | str) -> Column:
    """Share of the expected strings that stand in h; 1 if none are expected."""
    e = col(expected)
    return F.when(F.size(e) == 0, 1.0).otherwise(F.size(F.filter(e, lambda x: F.contains(col(h), x))) / F.size(e))


def _grams(words: Column, n: int) -> Column:
    return F.transform(F.sequence(F.lit(1), F.size(words) - (n - 1)), lambda i: F.array_join(F.slice(words, i, n), " "))


def gram_overlap(pairs: DataFrame, key: list[str], n: int) -> DataFrame:
    """key, n_ref, n_hyp, shared (clipped) of runs of n units; counted as rows, not in memory."""

    def rows(c: str, other: str) -> DataFrame:
        none = F.array().cast("array<string>")
        made = let(units(c), lambda w: F.when(F.size(w) >= n, _grams(w, n)).otherwise(none))
        return pairs.select(*key, F.explode(made).alias("g"), F.lit(1).alias(c), F.lit(0).alias(other))

    counts = rows("ref", "hyp").unionByName(rows("hyp", "ref")).groupBy(*key, "g").agg(F.sum("ref").alias("r"), F.sum("hyp").alias("h"))
    sums = counts.groupBy(*key).agg(F.sum("r").alias("n_ref"), F.sum("h").alias("n_hyp"), F.sum(F.least("r", "h")).alias("shared"))
    zero = F.lit(0).cast("long")
    return pairs.select(*key).distinct().join(sums, key, "left").select(*key, *[F.coalesce(c, zero).alias(c) for c in ("n_ref", "n_hyp", "shared")])


def _share(a: Column, b: Column, empty: Column) -> Column:
    return F.when(b == 0, empty).otherwise(a / b)


def rouge_n(pairs: DataFrame, key: list[str], n: int = 1) -> DataFrame:
    """key, recall, precision, f1 of clipped runs of n units; two empty texts are equal."""
    d = gram_overlap(pairs, key, n)
    both = (F.col("n_ref") == 0) & (F.col("n_hyp") == 0)
    e = F.when(both, 1.0).otherwise(0.0)
    d = d.select(*key, _share(F.col("shared"), F.col("n_ref"), e).alias("recall"), _share(F.col("shared"), F.col("n_hyp"), e).alias("precision"))
    total = F.col("recall") + F.col("precision")
    return d.withColumn("f1", F.when(total == 0, 0.0).otherwise(2 * F.col("recall") * F.col("precision") / total))


def bleu(pairs: DataFrame, key: list[str], max_n: int = 4, smooth: bool = True) -> DataFrame:
    """key, bleu: geometric mean of clipped precisions by run length, times the brevity penalty.

    Run lengths go up to the shorter text's units; with smooth, lengths above 1 add one to both counts.
    """
    d = None
    for n in range(1, max_n + 1):
        one = gram_overlap(pairs, key, n).select(*key, F.lit(n).alias("n"), "n_ref", "n_hyp", "shared")
        d = one if d is None else d.unionByName(one)
    add = F.when((F.col("n") > 1) & F.lit(smooth), 1).otherwise(0)
    p = F.when((F.col("n_hyp") > 0) & (F.col("n_ref") > 0), (F.col("shared") + add) / (F.col("n_hyp") + add))
    d = d.withColumn("p", p)
    first = lambda c: F.max(F.when(F.col("n") == 1, F.col(c)))
    d = d.groupBy(*key).agg(F.exp(F.avg(F.when(F.col("p") > 0, F.log("p")))).alias("mean"), F.min("p").alias("low"), first("n_ref").alias("r"), first("n_hyp").alias("h"))
    brevity = F.when(F.col("h") >= F.col("r"), 1.0).otherwise(F.exp(1 - F.col("r") / F.col("h")))
    score = F.when((F.col("r") == 0) & (F.col("h") == 0), 1.0).when((F.col("r") == 0) | (F.col("h") == 0) | (F.col("low") == 0), 0.0).otherwise(F.col("mean") * brevity)
    return d.select(*key, score.alias("bleu"))


# --- long texts, by numpy in Arrow batches --------------------------------------------------------


#: Characters of a block that ties two texts together, and of the blocks that count in a stretch.
BLOCK, COUNTED = 16, (4, 8, 16)


def _trimmed(a: str, b: str) -> tuple[str, str]:
    """Both texts without what they begin and end with in common."""
    if a == b:
        return "", ""
    step, k = 1024, 0
    while k < min(len(a), len(b)):  # long stretches are compared as slices
        if a[k : k + step] == b[k : k + step]:
            k += step
        elif step == 1:
            break
        else:
            step //= 4
    a, b = a[k:], b[k:]
    step, k = 1024, 0
    while k < min(len(a), len(b)):
        own = min(step, len(a) - k, len(b) - k)
        if a[len(a) - k - own : len(a) - k] == b[len(b) - k - own : len(b) - k]:
            k += own
        elif step == 1:
            break
        else:
            step //= 4
    return a[: len(a) - k], b[: len(b) - k]


def _edits(a: str, b: str) -> int:
    """Edits by code point, bit-parallel: one integer holds a column's vertical differences."""
    a, b = _trimmed(a, b)
    if len(a) < len(b):
        a, b = b, a
    if not b:
        return len(a)
    ones = (1 << len(b)) - 1
    where: dict[str, int] = {}
    for i, c in enumerate(b):
        where[c] = where.get(c, 0) | 1 << i
    up, down, score, last = ones, 0, len(b), 1 << (len(b) - 1)
    for c in a:
        eq = where.get(c, 0)
        xv = eq | down
        xh = (((eq & up) + up) ^ up) | eq
        ph = down | ~(xh | up) & ones
        mh = up & xh
        score += bool(ph & last) - bool(mh & last)
        ph = (ph << 1 | 1) & ones
        mh = mh << 1 & ones
        up = mh | ~(xv | ph) & ones
        down = ph & xv
    return score


#: Edits between long texts, and between their units, that are looked for one by one before other ways are taken.
FEW_EDITS, FEW_UNITS = 400, 400
_NEVER = -(1 << 40)


def _met(a: str, b: str, i: int, j: int) -> int:
    """First place of a from i on that differs from b's beside it; both end in marks of their own."""
    step = 8
    while True:
        if a[i : i + step] == b[j : j + step]:
            i, j, step = i + step, j + step, min(4 * step, 4096)
        elif step == 1:
            return i
        else:
            step = step // 4 or 1


def _few_edits(a: str, b: str, most: int) -> int | None:
    """Edits by code point if they are at most `most`: by diagonal, the furthest place that each number of edits reaches."""
    n, m = len(a), len(b)
    goal = m - n
    if abs(goal) > most:
        return None
    a, b, mid = a + "\U0010fffe", b + "\U0010ffff", most + 2
    last = [_NEVER] * (2 * mid + 1)
    for s in range(most + 1):
        new = [_NEVER] * (2 * mid + 1)
        for k in range(max(-s, goal - most + s), min(s, goal + most - s) + 1):
            at = mid + k
            i = last[at] + 1
            if last[at + 1] >= i:
                i = last[at + 1] + 1
            if last[at - 1] > i:
                i = last[at - 1]
            if not s:
                i = 0
            if i > n or i + k > m:
                i = min(n, m - k)
            if 0 <= i + k and i >= 0 and a[i] == b[i + k]:
                i = min(_met(a, b, i, i + k), n, m - k)
            new[at] = i
        if new[mid + goal] >= n:
            return s
        last = new
    return None


def _common(a: list[str], b: list[str], most: int = FEW_UNITS) -> list[tuple[int, int, int]] | None:
    """Stretches (first in a, first in b, length) of a longest common subsequence, if at most `most` units stand outside it."""
    place = {u: k for k, u in enumerate(dict.fromkeys(itertools.chain(a, b)))}
    n, m = len(a), len(b)
    goal = m - n
    if abs(goal) > most or len(place) > 1_000_000:
        return None
    # Units as code points beyond the surrogates, so stretches are compared as texts.
    x, y = ((np.fromiter(map(place.__getitem__, u), "<u4", len(u)) + np.uint32(0xE000)).tobytes().decode("utf-32-le") for u in (a, b))
    x, y, mid = x + "\x00", y + "\x01", most + 2
    rounds: list[list[int]] = []
    last = [_NEVER] * (2 * mid + 1)
    for s in range(most + 1):
        new = [_NEVER] * (2 * mid + 1)
        low, high = max(-s, goal - most + s), min(s, goal + most - s)
        for k in range(low + (low + s) % 2, high + 1, 2):
            at = mid + k
            i = max(last[at + 1] + 1, last[at - 1]) if s else 0
            if i < 0 or i > n or not 0 <= i + k <= m:
                continue
            new[at] = _met(x, y, i, i + k) if x[i] == y[i + k] else i
        rounds.append(new)
        if new[mid + goal] >= n:
            break
        last = new
    else:
        return None
    out, k = [], goal
    for s in range(len(rounds) - 1, -1, -1):
        end = rounds[s][mid + k]
        start, before = 0, 0
        if s:
            down, right = rounds[s - 1][mid + k + 1] + 1, rounds[s - 1][mid + k - 1]
            start, before = (down, k + 1) if down >= right else (right, k - 1)
        if end > start:
            out.append((start, start + k, end - start))
        k = before
    return out[::-1]


def _outside(stretches: list[tuple[int, int]], n: int, size: int) -> Iterator[int]:
    """First places of the runs of size units, of n units, that lie in none of the stretches (first, length)."""
    at = 0
    for first, length in stretches:
        yield from range(at, min(first, n - size + 1))
        at = max(at, first, first + length - size + 1)
    yield from range(at, n - size + 1)


def _block_codes(text: str) -> dict[int, np.ndarray]:
    """By size of a block, a code of the characters from each place; equal blocks have equal codes."""
    h = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64) + np.uint64(1)
    n, factor, out = 1, 0x9E3779B97F4A7C15, {}
    while n < BLOCK:
        h = h[:-n] * np.uint64(factor) + h[n:]
        n, factor = 2 * n, factor * factor % 2**64 | 1
        if n in COUNTED:
            out[n] = h ^ h >> np.uint64(29)
    return out


@functools.lru_cache(4)
def _places(text: str) -> tuple[np.ndarray, np.ndarray, dict[int, np.ndarray]]:
    """Sorted codes of blocks, their places, and by size how far off each block's nearest equal one is."""
    far = {}
    for n, codes in _block_codes(text).items():
        order = np.argsort(codes, kind="stable")
        known = codes[order]
        apart = np.where(known[1:] == known[:-1], np.diff(order), len(text))
        far[n] = np.empty(len(order), np.int64)
        far[n][order] = np.minimum(np.append(apart, len(text)), np.append(len(text), apart))
    return known, order, far


def _tied(a: str, b: str) -> list[list[int]]:
    """Stretches [first in a, first in b, length] on which b equals a, in order in both."""
    known, order, far = _places(a)
    mine = _block_codes(b)[BLOCK][::BLOCK]
    at = np.minimum(np.searchsorted(known, mine), len(known) - 1)
    once = (known[at] == mine) & (far[BLOCK][order[at]] == len(a))
    found = [(i, j) for i, j in zip(order[at[once]].tolist(), (np.flatnonzero(once) * BLOCK).tolist(), strict=True) if a.startswith(b[j : j + BLOCK], i)]
    # The longest chain of blocks that rises in both texts.
    ends: list[int] = []
    tops, before = [], [-1] * len(found)
    for k, (i, _) in enumerate(found):
        n = bisect.bisect_left(ends, i)
        before[k] = tops[n - 1] if n else -1
        ends[n : n + 1], tops[n : n + 1] = [i], [k]
    k, chain = tops[-1] if tops else -1, []
    while k >= 0:
        chain.append(found[k])
        k = before[k]
    out: list[list[int]] = []
    for i, j in reversed(chain):
        if out and i - j == out[-1][0] - out[-1][1] and a[out[-1][0] + out[-1][2] : i] == b[out[-1][1] + out[-1][2] : j]:
            out[-1][2] = j + BLOCK - out[-1][1]
        elif not out or i >= out[-1][0] + out[-1][2]:
            out.append([i, j, BLOCK])
    return out


def _grown(a: str, b: str, kept: list[list[int]]) -> list[list[int]]:
    """The stretches, each drawn out to both sides as far as the texts are equal up to its neighbours."""
    for k, (i, j, n) in enumerate(kept):
        low, high = max(0, j - i), (kept[k - 1][1] + kept[k - 1][2] if k else 0)
        low = max(low, high, j - i + (kept[k - 1][0] + kept[k - 1][2] if k else 0))
        while j > low and a[i - 1] == b[j - 1]:
            i, j, n = i - 1, j - 1, n + 1
        stop_a, stop_b = kept[k + 1][:2] if k + 1 < len(kept) else (len(a), len(b))
        while i + n < stop_a and j + n < stop_b and a[i + n] == b[j + n]:
            n += 1
        kept[k] = [i, j, n]
    return kept


def _blocks(a: str, stretch: list[int], reach: int) -> int:
    """Disjoint blocks of a stretch that stand nowhere else in a within reach of it."""
    i, _, n = stretch
    far, n = _places(a)[2], n // BLOCK * BLOCK
    most = None
    for size in COUNTED:
        own = (far[size][i : i + n : size] > reach).astype(np.int64)
        most = own if most is None else np.maximum(own, most.reshape(-1, 2).sum(axis=1))
    return int(most.sum())


def edit_distance(a: str, b: str) -> int:
    """Edits by code point; long texts are cut at stretches that some best alignment must pass through.

    Costs of the gaps between stretches bound the distance, and with it how far a best alignment strays
    from this one. One that meets no place of a stretch on its diagonal pays one edit or more in each of
    its blocks, as they stand nowhere else within reach. If a stretch has as many blocks as the gaps on
    both sides of it have edits together, missing it is never better, whatever stretches are missed in a
    row: the blocks of the missed ones cover the edits of all gaps between those that are met. Other
    stretches are given up, and the gaps beside them become one.
    """
    if a == b:
        return 0
    if min(len(a), len(b)) < 20 * BLOCK:
        return _edits(a, b)
    gap = lambda s, t: _edits(a[s[0] + s[2] : t[0]], b[s[1] + s[2] : t[1]])
    kept = [[0, 0, 0], *_grown(a, b, _tied(a, b)), [len(a), len(b), 0]]
    first = [gap(s, t) for s, t in itertools.pairwise(kept)]
    reach = sum(first)
    done, costs, whole, blocks = [kept[0]], [], [], [reach * 2]
    for s, cost in zip(kept[1:], first, strict=True):
        one = True
        while len(done) > 1 and blocks[-1] < costs[-1] + cost:
            done.pop()
            blocks.pop()
            whole.pop()
            cost, one = cost + costs.pop(), False  # at most, as the stretch itself costs nothing
        done.append(s)
        blocks.append(_blocks(a, s, reach))
        costs.append(cost)
        whole.append(one)
    return sum(cost if one else gap(s, t) for cost, one, (s, t) in zip(costs, whole, itertools.pairwise(done), strict=True))


def common_subsequence(a: list[str], b: list[str]) -> int:
    """Length of the longest common subsequence of units, bit-parallel."""
    k = end = 0
    most = min(len(a), len(b))
    while k < most and a[k] == b[k]:
        k += 1
    while end < most - k and a[-1 - end] == b[-1 - end]:
        end += 1
    a, b = a[k : len(a) - end], b[k : len(b) - end]
    where: dict[str, int] = {}
    for i, u in enumerate(b):
        where[u] = where.get(u, 0) | 1 << i
    ones = (1 << len(b)) - 1
    v = ones
    for u in a:
        if m := where.get(u):
            m &= v
            v = ((v + m) | (v ^ m)) & ones
    return k + end + len(b) - v.bit_count()


def _shared(a: list[str], b: list[str], most: int) -> list[tuple[int, int, int]]:
    """By n from 1 to most: runs of n units in a, in b, clipped number of shared ones."""
    if len(a) + len(b) < 400:
        both = [[Counter(u if n == 1 else zip(*(u[i:] for i in range(n)), strict=False)) for u in (a, b)] for n in range(1, most + 1)]
        return [(x.total(), y.total(), (x & y).total()) for x, y in both]
    place = {u: k for k, u in enumerate(dict.fromkeys(itertools.chain(a, b)))}
    one = [np.fromiter(map(place.__getitem__, u), np.int64, len(u)) for u in (a, b)]
    codes, top, out = one, len(place), []
    for n in range(1, most + 1):
        if n > 1:
            if top * len(place) >= 2**63:  # codes become ranks before they run over
                names, ranks = np.unique(np.concatenate(codes), return_inverse=True)
                codes, top = np.split(ranks, [len(codes[0])]), len(names)
            codes, top = [c[: max(len(u) - n + 1, 0)] * len(place) + u[n - 1 :] for c, u in zip(codes, one, strict=True)], top * len(place)
        (x, n_x), (y, n_y) = (np.unique(c, return_counts=True) for c in codes)
        _, i, j = np.intersect1d(x, y, assume_unique=True, return_indices=True)
        out.append((len(codes[0]), len(codes[1]), int(np.minimum(n_x[i], n_y[j]).sum())))
    return out


def lev_of(x: str, y: str) -> float:
    if x == y:
        return 1.0
    few = _few_edits(x, y, FEW_EDITS) if min(len(x), len(y)) >= 20 * BLOCK else None
    return 1 - (edit_distance(x, y) if few is None else few) / max(len(x), len(y))


def _ham(x: str, y: str) -> float:
    if x == y:
        return 1.0
    a, b = (np.frombuffer(t.encode("utf-32-le"), np.uint32) for t in (x, y))
    n = min(len(a), len(b))
    return float((a[:n] == b[:n]).sum() / max(len(a), len(b)))


def _rouge_l(x: str, y: str) -> float:
    if x == y:
        return 1.0
    a, b = x.split(), y.split()
    return (1.0 if not b else 0.0) if not a else common_subsequence(a, b) / len(a)


def _rouge_1_bleu(x: str, y: str) -> tuple[float, float]:
    """Recall of single units and BLEU, from one count of runs."""
    if x == y:
        return 1.0, 1.0
    a, b = _UNIT.findall(x), _UNIT.findall(y)
    if not a or not b:
        return (float(not a and not b),) * 2
    return _from_counts(len(a), len(b), _shared(a, b, min(4, len(a), len(b))))


def _from_counts(n: int, m: int, counts: list[tuple[int, int, int]]) -> tuple[float, float]:
    recall = counts[0][2] / n
    if not recall:
        return 0.0, 0.0
    logs = [math.log(shared / own if size == 1 else (shared + 1) / (own + 1)) for size, (_, own, shared) in enumerate(counts, 1)]
    return recall, math.exp(sum(logs) / len(logs)) * (1.0 if m >= n else math.exp(1 - n / m))


def _presence(x: str, y: str) -> float:
    """presence of the reference's units."""
    units = set(_UNIT.findall(x))
    if x == y or not units:
        return 1.0
    own = set(_UNIT.findall(y))
    return sum(u in own or u in y for u in units) / len(units)


#: Names of what measures gives.
MEASURES = ("exact", "levenshtein", "hamming", "rouge_l", "string_presence", "rouge_1", "bleu")


@functools.lru_cache(4)
def _plain(text: str) -> list[str] | None:
    """Units of a text that has nothing but single blanks between them."""
    u = text.split()
    return u if u and " ".join(u) == text else None


def _of_units(x: str, y: str) -> tuple[float, float, float, float]:
    """_rouge_l, _presence and _rouge_1_bleu; where two long texts are alike, from what differs alone."""
    a, b = _plain(x), _plain(y)
    kept = _common(a, b) if a and b and min(len(a), len(b)) >= 500 else None
    if not kept:
        return _rouge_l(x, y), _presence(x, y), *_rouge_1_bleu(x, y)
    mine, theirs = ([(s[k], s[2]) for s in kept] for k in (0, 1))
    n_units = len(set(a))
    lost = sum(u not in y for u in {a[i] for i in _outside(mine, len(a), 1)})
    counts = []
    for size in range(1, 5):  # runs inside a stretch stand in both texts
        p, q = (Counter(tuple(u[i : i + size]) for i in _outside(s, len(u), size)) for u, s in ((a, mine), (b, theirs)))
        inside = sum(max(n - size + 1, 0) for _, n in mine)
        counts.append((len(a) - size + 1, len(b) - size + 1, inside + (p & q).total()))
    return sum(n for _, n in mine) / len(a), (n_units - lost) / n_units, *_from_counts(len(a), len(b), counts)


def measures(x: str, y: str) -> tuple[float, ...]:
    """MEASURES of an answer y to a reference x."""
    return (1.0,) * len(MEASURES) if x == y else (0.0, lev_of(x, y), _ham(x, y), *_of_units(x, y))


def _udf(one, doc: str):
    def run(r: pd.Series, h: pd.Series) -> pd.Series:
        return pd.Series([one(x or "", y or "") for x, y in zip(r, h, strict=True)])

    run.__doc__ = doc
    return F.pandas_udf(run, DoubleType())


lev_sim_long = _udf(lev_of, "lev_sim for whole shards.")
ham_sim_long = _udf(_ham, "ham_sim for whole shards.")
rouge_l = _udf(_rouge_l, "Longest common subsequence of units / units of the reference.")
rouge_1_long = _udf(lambda x, y: _rouge_1_bleu(x, y)[0], "Recall of rouge_n of single units, for shards that a budget bounds.")
bleu_long = _udf(lambda x, y: _rouge_1_bleu(x, y)[1], "As bleu with its defaults, for shards that a budget bounds.")


@F.pandas_udf(DoubleType())
def byte_ratio(t: pd.Series) -> pd.Series:
    """1 - compressed bytes / bytes by zlib; a size that no reader can use."""
    raw = [(x or "").encode() for x in t]
    return pd.Series([1 - len(zlib.compress(x, 6)) / len(x) if x else 0.0 for x in raw])


def prose_around_markers(folded: DataFrame) -> DataFrame:
    """shard_id, corpus, n_around, n_prose: units next to a marker, and those of them that are words of letters."""
    marks = F.transform("folded", lambda u: F.startswith(u, F.lit("<M")))
    d = folded.select("shard_id", "corpus", "folded", marks.alias("m"))
    by_marker = lambda i: F.coalesce(F.get("m", i - 1), F.lit(False)) | F.coalesce(F.get("m", i + 1), F.lit(False))
    around = F.filter("folded", lambda u, i: ~F.startswith(u, F.lit("<M")) & by_marker(i))
    d = d.select("shard_id", "corpus", around.alias("a"))
    return d.select("shard_id", "corpus", F.size("a").alias("n_around"), F.size(F.filter("a", lambda u: F.regexp_like(u, F.lit(r"^\p{L}+[.,;:!?]?$")))).alias("n_prose"))


# --- statistics -----------------------------------------------------------------------------------


def mean_sem(df: DataFrame, by: list[str], value: str = "value") -> DataFrame:
    d = df.groupBy(*by).agg(F.count(value).alias("n"), F.avg(value).alias("mean"), F.stddev_samp(value).alias("std"))
    return d.withColumn("sem", F.col("std") / F.sqrt("n"))


def mean_std(df: DataFrame, by: list[str], value: str = "value") -> DataFrame:
    return df.groupBy(*by).agg(F.count(value).alias("n"), F.avg(value).alias("mean"), F.stddev_samp(value).alias("std"))


def aggregate_scores(df: DataFrame, value: str = "value") -> DataFrame:
    """metric, pooled mean and std over all runs, and mean and std of the corpora's means."""
    pooled = df.groupBy("metric").agg(F.avg(value).alias("pooled_mean"), F.stddev_samp(value).alias("pooled_std"))
    means = df.groupBy("metric", "corpus").agg(F.avg(value).alias("m")).groupBy("metric").agg(F.avg("m").alias("mean_of_means"), F.stddev_samp("m").alias("std_of_means"))
    return pooled.join(means, "metric")


def regress(df: DataFrame, y: str = "value", x: str = "cr", by: tuple[str, ...] = ("metric",)) -> DataFrame:
    """slope, intercept, r2 and the slope's error of y on x, in one aggregate; band: half width of its 95 % interval."""
    d = df.groupBy(*by).agg(
        F.regr_count(y, x).alias("n"), F.regr_slope(y, x).alias("slope"), F.regr_intercept(y, x).alias("intercept"), F.regr_r2(y, x).alias("r2"), F.regr_sxx(y, x).alias("sxx"), F.regr_syy(y, x).alias("syy")
    )
    rest = F.greatest(F.col("syy") * (1 - F.col("r2")), F.lit(0.0))
    d = d.withColumn("se_slope", F.when((F.col("n") > 2) & (F.col("sxx") > 0), F.sqrt(rest / (F.col("n") - 2) / F.col("sxx"))))
    quantile = F.lit(1.96)
    for df_, t in sorted(T95.items(), reverse=True):
        quantile = F.when(F.col("n") - 2 <= df_, t).otherwise(quantile)
    return d.withColumn("band", quantile * F.col("se_slope")).drop("sxx", "syy")


def digit_density(text: Column | str) -> Column:
    """Share of units with a digit."""
    u = units(text)
    return F.when(F.size(u) == 0, 0.0).otherwise(F.size(F.filter(u, lambda x: F.regexp_like(x, F.lit("[0-9]")))) / F.size(u))


def legend_confusability(entries: DataFrame) -> DataFrame:
    """(shard_id, n_entries, n_confusable): entries equal to another one but for digits.

    Equality after masking is grouped, never paired.
    """
    d = entries.withColumn("_mask", F.regexp_replace(F.array_join("units", " "), "[0-9]+", "#"))
    d = d.groupBy("shard_id", "_mask").agg(F.count("*").alias("n"))
    return d.groupBy("shard_id").agg(F.sum("n").alias("n_entries"), F.sum(F.when(F.col("n") > 1, F.col("n")).otherwise(0)).alias("n_confusable"))


def near_entries(entries: DataFrame, most: int = 2) -> DataFrame:
    """Pairs of one mask group within `most` edits; groups are small legends' parts."""
    d = entries.select("shard_id", "marker", F.array_join("units", " ").alias("t")).withColumn("_mask", F.regexp_replace("t", "[0-9]+", "#"))
    o = d.select("shard_id", "_mask", F.col("marker").alias("other"), F.col("t").alias("ot"))
    return d.join(o, ["shard_id", "_mask"]).where("marker < other").where(F.levenshtein("t", "ot", most) >= 0).select("shard_id", "marker", "other")


def legend_stats(entries: DataFrame) -> DataFrame:
    return entries.groupBy("shard_id").agg(F.count("*").alias("n_entries"), F.avg("len").alias("mean_len"), F.sum("f").alias("uses"), F.sum("gain").alias("gain"))


def batches_profile(df: DataFrame) -> Iterator[tuple[str, float]]:
    """(measure, value) of running df: seconds and rows, by an observation on the plan."""
    import time

    from pyspark.sql import Observation

    seen, start = Observation(), time.time()
    df.observe(seen, F.count(F.lit(1)).alias("rows")).write.format("noop").mode("overwrite").save()
    yield "seconds", time.time() - start
    yield "rows", float(seen.get["rows"])
