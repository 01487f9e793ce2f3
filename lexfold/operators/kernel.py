"""Folding of one shard: repeated runs of units replaced by markers. No Spark in here.

All work is done in the coordinates of the original text. A run that holds a marker is never a
candidate, so shorter candidates are runs of original units that touch no covered place, and one mask
of covered places stands for the partly folded text; it is rewritten once, at the end.

Coding goes from short to long: the code of a run is the rank of (code of the run one shorter, next
unit), and starts whose shorter run is rare are dropped for good. Choosing goes from long to short.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field

import numpy as np
import regex

_PIECE = regex.compile(r"\p{L}+|\p{N}{1,3}|[^\s\p{L}\p{N}]")
_LITERAL = re.compile(r"<M([1-9][0-9]*)>")


def token_cost(text: str, cost: str) -> int:
    if cost != "pieces":
        return 1 if cost == "unit" else -(-len(text) // 4)
    if text.isascii():  # words of one kind need no matching
        if text.isalpha():
            return 1
        if text.isdigit():
            return -(-len(text) // 3)
    return len(_PIECE.findall(text))


@dataclass(frozen=True)
class Options:
    l_max: int = 10
    f_min: int = 2
    l_min: int = 2
    order: str = "frequency"  # or "savings"
    cost: str = "pieces"  # or "unit", "chars"
    marker_cost: str = "actual"  # or "fixed"
    fixed_marker: str = "<M999>"
    entry_overhead: int = 0
    saving_test: bool = True
    direction: str = "desc"  # or "asc"
    within_record: bool = False
    guard: bool = True

    def __post_init__(self):
        if self.l_min < 1 or self.l_max < self.l_min or self.f_min < 2:
            raise ValueError("1 <= l_min <= l_max and f_min >= 2 are needed")


@dataclass
class Entry:
    marker: str
    units: list[str]
    starts: list[int]
    gain: int
    n_s: int = 0

    @property
    def f(self) -> int:
        return len(self.starts)


@dataclass
class Folded:
    folded: list[str]
    legend: list[Entry]
    n_tok: int
    n_tok_folded: int
    n_tok_legend: int
    guarded: bool = False
    l_eff: int = 0
    borders: list[int] = field(default_factory=list)

    @property
    def cr(self) -> float:
        return 1 - self.n_tok_folded / self.n_tok if self.n_tok else 0.0

    @property
    def cr_input(self) -> float:
        return 1 - (self.n_tok_folded + self.n_tok_legend) / self.n_tok if self.n_tok else 0.0


class Shard:
    """Coded units of one shard; folding it with several options codes it once."""

    def __init__(self, units: list[str], cost: str = "pieces", record_starts: list[int] | None = None):
        self.units, self.cost = units, cost
        place = {u: k for k, u in enumerate(dict.fromkeys(units))}
        self.codes = np.fromiter(map(place.__getitem__, units), np.int64, len(units))
        costs = np.array([token_cost(u, cost) for u in place], np.int64)
        self.total = np.concatenate(([0], np.cumsum(costs[self.codes]))) if units else np.zeros(1, np.int64)
        self.literal = {int(m[1]) for u in place if "<M" in u for m in _LITERAL.finditer(u)}
        self.record = np.zeros(len(units), np.int64)
        if record_starts:
            self.record[[s for s in record_starts if 0 < s < len(units)]] = 1
            self.record = np.cumsum(self.record)
        self.levels: dict[int, tuple[np.ndarray, np.ndarray]] = {1: (np.arange(len(units)), self.codes)}
        self.by_code: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        self.marker_costs: dict[str, int] = {}

    def level(self, length: int, f_min: int) -> tuple[np.ndarray, np.ndarray]:
        """(starts, codes) of the runs of this length that occur f_min = 2 times or more."""
        while (n := max(self.levels)) < length:
            starts, codes = self.levels[n]
            ok = starts + n < len(self.units)
            starts, codes = starts[ok], codes[ok]
            if len(starts):
                often = np.bincount(codes)[codes] >= 2
                starts, codes = starts[often], codes[often]
            pair = codes * (int(self.codes.max(initial=0)) + 1) + self.codes[starts + n]
            _, codes, counts = np.unique(pair, return_inverse=True, return_counts=True)
            often = counts >= 2
            keep = often[codes]
            self.levels[n + 1] = starts[keep], (np.cumsum(often) - 1)[codes[keep]]  # codes that stay, closed up
        return self.levels[length]

    def l_eff(self, l_max: int) -> int:
        """Longest length up to l_max at which anything repeats."""
        n = 1
        while n < l_max and len(self.level(n + 1, 2)[0]):
            n += 1
        return n

    def grouped(self, length: int, f_min: int) -> tuple[np.ndarray, np.ndarray]:
        """The level's starts and codes in the order of codes, sorted once for all foldings."""
        if length not in self.by_code:
            starts, codes = self.level(length, f_min)
            # Starts rise in a level, so sorting (code, start) as one number keeps their order.
            codes, starts = np.divmod(np.sort(codes * len(self.units) + starts), max(len(self.units), 1))
            self.by_code[length] = starts, codes
        return self.by_code[length]

    def marker_cost(self, marker: str) -> int:
        if marker not in self.marker_costs:
            self.marker_costs[marker] = token_cost(marker, self.cost)
        return self.marker_costs[marker]

    def fold(self, o: Options, full: bool = True) -> Folded:
        """Folded units and legend; without full, sizes and legend alone."""
        covered = bytearray(len(self.units))
        picks: list[Entry] = []
        number = 1
        lengths = range(min(o.l_max, self.l_eff(o.l_max)), o.l_min - 1, -1)
        for length in lengths if o.direction == "desc" else reversed(lengths):
            number = self._choose(length, o, covered, picks, number)
        return self._emit(o, picks, full)

    def _marker(self, number: int) -> tuple[str, int]:
        while number in self.literal:
            number += 1
        return f"<M{number}>", number

    def _choose(self, length: int, o: Options, covered: bytearray, picks: list[Entry], number: int) -> int:
        starts, codes = self.grouped(length, o.f_min)
        mask = np.frombuffer(covered, np.bool_)
        if o.direction == "desc":  # what is covered is at least as long, so touching it means covering an end
            free = ~(mask[starts] | mask[starts + length - 1])
        else:
            run = np.concatenate(([0], np.cumsum(mask)))
            free = run[starts + length] == run[starts]
        if o.within_record:
            free &= self.record[starts] == self.record[starts + length - 1]
        starts, codes = starts[free], codes[free]
        if not len(starts):
            return number
        heads = np.flatnonzero(np.concatenate(([True], codes[1:] != codes[:-1])))
        counts = np.diff(np.append(heads, len(codes)))
        firsts = starts[heads]
        n_s = self.total[firsts + length] - self.total[firsts]
        fixed = token_cost(o.fixed_marker, self.cost) if o.marker_cost == "fixed" else None
        low = self.marker_cost(self._marker(number)[0]) if fixed is None else fixed
        worth = counts * n_s - (1 + counts) * low - n_s - o.entry_overhead
        ok = counts >= o.f_min
        if o.saving_test:
            ok &= worth > 0
        ok = np.flatnonzero(ok)
        rank = ok[np.lexsort((firsts[ok], -(counts if o.order == "frequency" else worth)[ok]))]
        places, ones, desc = starts.tolist(), b"\x01" * length, o.direction == "desc"
        for at, count, s_cost in zip(heads[rank].tolist(), counts[rank].tolist(), n_s[rank].tolist(), strict=True):
            own, last = [], -length
            for s in places[at : at + count]:
                if s >= last + length and not (covered[s] or covered[s + length - 1] if desc else covered.find(1, s, s + length) >= 0):
                    own.append(s)
                    last = s
            f = len(own)
            if f < o.f_min:
                continue
            marker, k = self._marker(number)
            m_cost = self.marker_cost(marker) if fixed is None else fixed
            saved = f * s_cost - (1 + f) * m_cost - s_cost - o.entry_overhead
            if o.saving_test and saved <= 0:
                continue
            number = k + 1
            for s in own:
                covered[s : s + length] = ones
            picks.append(Entry(marker, self.units[own[0] : own[0] + length], own, saved, s_cost))
        return number

    def _emit(self, o: Options, picks: list[Entry], full: bool) -> Folded:
        n_tok = int(self.total[-1])
        n_legend = sum(self.marker_cost(e.marker) + e.n_s + o.entry_overhead for e in picks)
        saved_place = sum(e.f * (e.n_s - self.marker_cost(e.marker)) for e in picks)
        made = Folded([], picks, n_tok, n_tok - saved_place, n_legend, False, self.l_eff(o.l_max))
        if o.guard and picks and made.cr_input <= 0:
            return Folded(list(self.units) if full else [], [], n_tok, n_tok, 0, True, made.l_eff)
        if full:
            at = {s: e for e in picks for s in e.starts}
            new = (np.flatnonzero(self.record[1:] != self.record[:-1]) + 1).tolist()  # first places of records
            i = nth = 0
            for s in [*sorted(at), len(self.units)]:
                end = s + (s < len(self.units))
                while nth < len(new) and new[nth] < end:
                    if new[nth] >= max(i, 1):
                        made.borders.append(len(made.folded) + new[nth] - i)
                    nth += 1
                made.folded += self.units[i:s]
                if s < len(self.units):
                    made.folded.append(at[s].marker)
                    i = s + len(at[s].units)
        return made


def fold_units(units: list[str], options: Options | None = None, record_starts: list[int] | None = None) -> Folded:
    o = options or Options()
    return Shard(units, o.cost, record_starts).fold(o)


def unfold_units(folded: list[str], legend: dict[str, list[str]]) -> list[str]:
    return [u for x in folded for u in legend.get(x, [x])]
