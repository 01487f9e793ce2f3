"""Encoding of whole texts through a cache of their parts.

A byte-level tokenizer cuts a text by a pattern and encodes each piece alone, so equal pieces have
equal ids. For the pattern that public tokenizers share (RUNS), the cuts follow from the class of each
character (letter, number, white space, other), so they are found for all texts of a slice at once, on
their bytes. Arrow makes the pieces distinct without copying a text, Python looks up each one once a
slice, and only unknown ones are encoded. Any other pattern cuts each text on its own.

What a worker keeps is bounded in bytes (MOST_BYTES): beyond that pieces used only once go, and where
that is not enough the cache starts anew.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import lru_cache, partial
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex

Encode = Callable[[pa.StringArray], tuple[np.ndarray, np.ndarray]]
Split = Callable[[str], list[tuple[int, int]]]
#: Bytes that the pieces and ids kept by a worker may take, and what one takes beside its characters.
MOST_BYTES, EACH = 80 << 20, 250
#: Fixed value: the pattern whose cuts `run_starts` finds.
RUNS = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
OTHER, LETTER, NUMBER, WHITE = range(4)
#: Classes of code points from here on, where texts hardly have any, are read off only if one occurs.
USUAL = 0x34000


def class_table(split: Split, size: int) -> np.ndarray:
    """The class of every code point below `size`, read off the cuts of a splitter that follows RUNS."""
    every = "".join("!" if c == 0x20 or 0xD800 <= c < 0xE000 else chr(c) for c in range(size))
    out = np.full(size, OTHER, np.uint8)
    for lo, hi in split(every):
        between = split(f"a{every[lo]}1")
        if between[0] == (0, 2):
            out[lo:hi] = LETTER
        elif between[1] == (1, 3):
            out[lo:hi] = NUMBER
        elif split(f"!{every[lo]}")[0] != (0, 2):
            out[lo:hi] = WHITE
    out[0x20] = WHITE
    return out


def bytes_of(texts: pa.StringArray) -> tuple[np.ndarray, np.ndarray]:
    """(bytes of texts one after the other, where those of each begin; one more entry at the end), without nulls."""
    _, begins, data = texts.buffers()
    begins = np.frombuffer(begins, np.int32)[texts.offset : texts.offset + len(texts) + 1]
    return np.frombuffer(data or b"", np.uint8)[begins[0] : begins[-1]], begins - begins[0]


def _byte_classes(data: np.ndarray, table_to: Callable[[int], np.ndarray]) -> np.ndarray:
    """The class of the character that each byte of UTF-8 is part of."""
    table = table_to(USUAL)
    kinds = table[:256][data]
    heads = np.flatnonzero(data >= 0xC0)
    first = data[heads]
    for size, least, most in ((2, 0xC0, 0xDF), (3, 0xE0, 0xEF), (4, 0xF0, 0xFF)):
        at = heads[(first >= least) & (first <= most)]
        if len(at):
            point = (data[at] & (0x7F >> size)).astype(np.int32)
            for k in range(1, size):
                point = point << 6 | data[at + k] & 0x3F
            kind = (table if point.max() < USUAL else table_to(0x110000))[point]
            for k in range(size):
                kinds[at + k] = kind
    return kinds


def run_starts(data: np.ndarray, begins: np.ndarray, table_to: Callable[[int], np.ndarray]) -> np.ndarray:
    """Where the pieces of RUNS begin in the bytes of texts; text k runs from begins[k] to begins[k + 1].

    table_to: gives the classes of the code points below a number.
    A run of one class is a piece. White space before another run gives its last character away: to
    that run if it is a blank, else as a piece of its own. An apostrophe that stands alone takes the
    endings of the pattern from the letters after it.
    """
    n = len(data)
    kinds, starts, first = _byte_classes(data, table_to), np.zeros(n + 3, bool), np.zeros(n + 1, bool)
    first[begins] = True
    starts[1:n] = kinds[1:] != kinds[:-1]
    after = np.flatnonzero(starts[:n] & ~first[:n])
    after = after[kinds[after - 1] == WHITE]
    starts[: n + 1] |= first
    blank = data[after - 1] == 0x20
    last = after - 1
    while len(inside := np.flatnonzero(data[last] & 0xC0 == 0x80)):
        last[inside] -= 1
    starts[last] = True
    starts[after[blank]] = False
    quotes = np.flatnonzero(data == 0x27)
    quotes = quotes[starts[quotes] & ~first[quotes + 1]]
    short = quotes[np.isin(data[quotes + 1], list(b"stmd"))]
    starts[short + 1], starts[short + 2] = False, True
    quotes = quotes[~first[quotes + 2]]
    one, two = data[quotes + 1], data[quotes + 2]
    long = quotes[((one == ord("r")) | (one == ord("v"))) & (two == ord("e")) | (one == ord("l")) & (two == ord("l"))]
    starts[long + 1], starts[long + 3] = False, True
    return np.flatnonzero(starts[:n])


class _Places(dict):
    """Key to place; unknown keys get the next place."""

    def __missing__(self, key: str) -> int:
        self[key] = place = len(self)
        return place


class _Ids:
    """Ids of entries by place."""

    def __init__(self):
        self.starts, self.flat = np.zeros(1, np.int64), np.zeros(0, np.uint32)

    def add(self, flat: np.ndarray, sizes: np.ndarray) -> None:
        self.starts = np.concatenate((self.starts, self.starts[-1] + np.cumsum(sizes)))
        self.flat = np.concatenate((self.flat, flat.astype(np.uint32)))

    def of(self, places: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids of these places one after the other, where those of each begin; one more entry at the end)."""
        lo = self.starts[places]
        size = self.starts[places + 1] - lo
        ends = np.concatenate(([0], np.cumsum(size)))
        return self.flat[np.repeat(lo - ends[:-1], size) + np.arange(ends[-1])], ends


class CachedEncoder:
    """encode_pieces: (ids, how many each) of pattern pieces; texts that hold a special string go to encode_whole.

    split: spans of the pieces of a text, where another engine than `regex` cuts by the pattern; its
    classes of characters hold, as releases of Unicode differ.
    """

    def __init__(self, pattern: str, encode_pieces: Encode, special: tuple[str, ...] = (), encode_whole: Callable[[list[str]], tuple[np.ndarray, np.ndarray]] | None = None, most: int = MOST_BYTES, split: Split | None = None):
        cut = regex.compile(pattern)
        self.cut, self.by_runs = cut.findall, pattern == RUNS
        self.table_to = lru_cache(partial(class_table, split or (lambda x: [m.span() for m in cut.finditer(x)])))
        self.encode_pieces, self.special, self.encode_whole, self.most = encode_pieces, special, encode_whole, most
        self._clear()

    def _clear(self) -> None:
        #: Pieces with their ids; `kept` is an upper estimate of their bytes.
        self.places, self.ids = _Places(), _Ids()
        self.uses = np.zeros(0, np.int64)
        self.kept = 0

    def _shrink(self) -> None:
        """Keep the pieces that have been used more than once since the last time."""
        often = np.flatnonzero(self.uses > 1)
        new = np.full(len(self.uses), -1)
        new[often] = np.arange(len(often))
        pieces = [k for k, p in zip(self.places, new.tolist(), strict=True) if p >= 0]
        flat, begins = self.ids.of(often)
        self._clear()
        kept = EACH * len(pieces) + sum(map(len, pieces)) + 4 * len(flat)
        if kept <= self.most // 2:
            self.kept = kept
            self.places.update(zip(pieces, range(len(pieces)), strict=True))
            self.ids.add(flat, np.diff(begins))
            self.uses = np.zeros(len(pieces), np.int64)

    def _pieces(self, texts: pa.StringArray) -> tuple[pa.StringArray, np.ndarray]:
        """(pieces one after the other, how many before each text; one more entry at the end)."""
        if not self.by_runs:
            cut = list(map(self.cut, texts.to_pylist()))
            return pa.array(chain.from_iterable(cut), pa.string()), np.concatenate(([0], np.cumsum(list(map(len, cut)), dtype=np.int64)))
        data, begins = bytes_of(texts)
        starts = run_starts(data, begins, self.table_to)
        ends = np.append(starts, len(data)).astype(np.int32)
        return pa.StringArray.from_buffers(len(starts), pa.py_buffer(ends), pa.py_buffer(data)), np.searchsorted(starts, begins)

    def _encode(self, texts: pa.StringArray) -> tuple[np.ndarray, np.ndarray]:
        """(ids, how many a text)."""
        pieces, before = self._pieces(texts)
        coded = pieces.dictionary_encode()
        known = len(self.places)
        at = np.fromiter(map(self.places.__getitem__, coded.dictionary.to_numpy(zero_copy_only=False).tolist()), np.int64, len(coded.dictionary))
        new = coded.dictionary.filter(pa.array(at >= known))
        if len(new):
            flat, sizes = self.encode_pieces(new)
            self.ids.add(flat, sizes)
            self.kept += EACH * len(sizes) + pc.sum(pc.binary_length(new)).as_py() + 4 * len(flat)
            self.uses = np.concatenate((self.uses, np.zeros(len(new), np.int64)))
        used = coded.indices.to_numpy()
        self.uses[at] += np.bincount(used, minlength=len(at))
        ids, begins = self.ids.of(at[used])
        return ids, np.diff(begins[before])

    def encode(self, texts: pa.Array | list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """(all ids, where each text's ids begin; one more entry at the end). Null is as empty."""
        if self.kept > self.most:
            self._shrink()
        texts = pc.fill_null(texts if isinstance(texts, pa.Array) else pa.array(texts, pa.string()), "")
        apart = np.zeros(len(texts), bool)
        for x in self.special:
            apart |= pc.match_substring(texts, x).to_numpy(zero_copy_only=False)
        n, order, found = np.zeros(len(texts), np.int64), [], []
        for which, way in ((~apart, self._encode), (apart, lambda x: self.encode_whole(x.to_pylist()))):
            if which.any():
                ids, n[which] = way(texts if which.all() else texts.filter(pa.array(which)))
                found.append(ids), order.append(np.flatnonzero(which))
        ids = np.concatenate(found) if found else np.zeros(0, np.uint32)
        begins = np.concatenate(([0], np.cumsum(n)))
        if len(found) > 1:  # back into the order of the texts
            order = np.concatenate(order)
            place = np.zeros(len(n), np.int64)
            place[order] = np.cumsum(n[order]) - n[order]
            ids = ids[np.repeat(place - begins[:-1], n) + np.arange(begins[-1])]
        return ids, begins
