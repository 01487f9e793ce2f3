"""Secret scan with a worklist of decoded layers.

A text is scanned for secrets; then whatever it holds in URL escapes, Unicode escapes, base64 or, below
base64, compressed bytes is unwrapped into further layers, each scanned and unwrapped in turn until no
layer is new. Layers already seen (by digest and place) are not taken up again, which ends cycles.
Every layer keeps, for each of its characters, the span of the original text that it came from, so
what is found in a layer is reported where its encoded form stands.

Escapes are decoded in the whole layer, so a key before an escape and a value behind it stay together;
base64 runs, decoded at all four places that they may begin at, and percent-encoded compressed bytes
become layers of their own, placed at the run. As the
patterns are ASCII, decoded bytes are read as Latin-1, which no byte prevents; runs of ASCII in UTF-16
are read beside it. Compressed data are unpacked to the end of the input: all members and frames, in
any mix of formats, then what is left over as it stands.

Decoded bytes are scanned as a stream in windows cut where no pattern can stand, so nothing is left
out for its size and only one window of a layer is held at a time.

Cases. Null and empty texts have no spans. Rows are returned one for one, null and repeated doc_ids
too; other columns are ignored and tables may be empty. Offsets count code points. Equal spans found
in several layers count once. A layer of more than MOST_BYTES is scanned like any other, and the run
that holds it is reported as `bomb` besides; so is a run whose unpacking comes back to where it was.
Pattern characters without a break over MOST_BYTES are cut there, with an overlap. Time grows with the
unpacked size.
"""

from __future__ import annotations

import base64
import bz2
import html
import lzma
import re
import zlib
from collections.abc import Iterable, Iterator
from hashlib import sha256
from itertools import chain
from urllib.parse import unquote_to_bytes

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession

from .common import table

#: Kinds in their order, and what they match.
KINDS = ("assign", "access", "hex", "bomb")
KEYS = ("password", "passwd", "secret", "token", "apikey", "api_key")
_any_case = lambda w: "".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in w)
ASSIGN = re.compile("(" + "|".join(map(_any_case, KEYS[:4])) + "|" + _any_case("api") + "_?" + _any_case("key") + r""")["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
ACCESS = re.compile(r"AKIA[A-Z0-9]{14,}")
HEX = re.compile(r"[0-9a-f]{16,}")
LEAST_VALUE = 12

MOST_BYTES = 64 << 20
#: Bytes of a window, what neighbouring windows share, and bytes unpacked in one step.
WINDOW, OVERLAP, STEP = 4 << 20, 4096, 1 << 16
_URL = re.compile(r"(?:%[0-9A-Fa-f]{2})+")
_ESCAPE = re.compile(r"\\u\{[0-9A-Fa-f]{1,6}\}|(?:\\u[0-9A-Fa-f]{4})+|\\x[0-9A-Fa-f]{2}|&#[0-9]{1,7};|&#[xX][0-9A-Fa-f]{1,6};")
_BASE64 = re.compile(r"[A-Za-z0-9+/_-]{16,}={0,2}")
#: Percent-encoded bytes with the characters that encoders leave as they are.
_URL_BYTES = re.compile(r"[A-Za-z0-9_.~/+-]*%[0-9A-Fa-f]{2}(?:%[0-9A-Fa-f]{2}|[A-Za-z0-9_.~/+-])*")
_PACKED = re.compile(rb"\x1f\x8b\x08|x[\x01\x5e\x9c\xda]|BZh[1-9]|\xfd7zXZ\x00|\x28\xb5\x2f\xfd|[\x50-\x5f]\x2a\x4d\x18")
#: Bytes that no pattern holds, and ASCII in UTF-16 of either byte order.
_BREAK = re.compile(rb"[^A-Za-z0-9+/_.=\-\"' :%\\{}&#;\x00]")
_WIDE = re.compile(rb"(?:[\t\n\r\x20-\x7e]\x00){8,}|(?:\x00[\t\n\r\x20-\x7e]){8,}")
_Zlib = type(zlib.decompressobj())
_BAD_DATA = (zlib.error, OSError, EOFError, ValueError, lzma.LZMAError, zstandard.ZstdError)

Span = tuple[str, int, int]


def scan(text: str) -> list[Span]:
    """Spans of the base patterns, leftmost and non-overlapping for each kind."""
    out: list[Span] = []
    if ("=" in text or ":" in text) and any(k in (low := text.lower()) for k in KEYS):
        out += [("assign", *m.span()) for m in ASSIGN.finditer(text) if len(m[2]) >= LEAST_VALUE]
    if "AKIA" in text:
        out += [("access", *m.span()) for m in ACCESS.finditer(text)]
    out += [("hex", *m.span()) for m in HEX.finditer(text)]
    return out


def in_order(spans: set[Span] | list[Span]) -> list[Span]:
    return sorted(spans, key=lambda s: (s[1], KINDS.index(s[0]), s[2]))


def shown(spans: list[Span]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


class Layer:
    """Text with the original span of each character; spans None: the characters stand for themselves."""

    def __init__(self, text: str, spans: list[tuple[int, int]] | tuple[int, int] | None = None):
        self.text, self.spans = text, spans

    def original(self, a: int, b: int) -> tuple[int, int]:
        if self.spans is None:
            return a, b
        if isinstance(self.spans, tuple):
            return self.spans
        return self.spans[a][0], self.spans[b - 1][1]

    def key(self) -> tuple:
        place = self.spans if isinstance(self.spans, tuple) else None
        return sha256(self.text.encode("utf-8", "surrogatepass")).digest(), place


def _url_run(run: str) -> list[tuple[str, int]]:
    """(character, escapes that make it) of a run of %XX; bytes that are not UTF-8 as Latin-1."""
    text = bytes.fromhex(run.replace("%", "")).decode("utf-8", "surrogateescape")
    return [(chr(ord(c) - 0xDC00), 3) if "\udc80" <= c <= "\udcff" else (c, 3 * len(c.encode())) for c in text]


def _escape_run(run: str) -> list[tuple[str, int]] | None:
    if run[0] == "&":
        text = html.unescape(run)
        return [(text, len(run))] if len(text) == 1 else None
    if run[1] == "x" or run[2] == "{":
        code = int(run.strip("\\ux{}"), 16) if run[2] == "{" else int(run[2:], 16)
        return [(chr(code), len(run))] if code < 0x110000 and not 0xD800 <= code < 0xE000 else None
    units = [int(u, 16) for u in run.split("\\u")[1:]]
    text = b"".join(u.to_bytes(2, "big") for u in units).decode("utf-16-be", "surrogatepass")
    return [(c, 12 if ord(c) > 0xFFFF else 6) for c in text]


def unescaped(layer: Layer, pattern: re.Pattern, decode) -> Layer | None:
    """The layer with all escapes of a kind decoded; None if there are none."""
    pieces, spans, at, changed = [], [], 0, False
    one_place = isinstance(layer.spans, tuple)
    for m in pattern.finditer(layer.text):
        got = decode(m[0])
        if got is None:
            continue
        changed = True
        pieces.append(layer.text[at : m.start()])
        pieces += [c for c, _ in got]
        if not one_place:
            spans += [layer.original(i, i + 1) for i in range(at, m.start())]
            i = m.start()
            for _, n in got:
                spans.append(layer.original(i, i + n))
                i += n
        at = m.end()
    if not changed:
        return None
    pieces.append(layer.text[at:])
    if one_place:
        return Layer("".join(pieces), layer.spans)
    spans += [layer.original(i, i + 1) for i in range(at, len(layer.text))]
    return Layer("".join(pieces), spans)


class Stream:
    """Chunks of bytes that can be looked at ahead and given back."""

    def __init__(self, chunks: Iterable[bytes]):
        self.chunks, self.kept = filter(None, chunks), b""
        self.taken: list[bytes] | None = None

    def take(self) -> bytes:
        out, self.kept = self.kept or next(self.chunks, b""), b""
        if self.taken is not None:
            self.taken.append(out)
        return out

    def peek(self, n: int) -> bytes:
        while len(self.kept) < n and (more := next(self.chunks, b"")):
            self.kept += more
        return self.kept[:n]

    def give_back(self, data: bytes) -> None:
        self.kept = data + self.kept
        if self.taken is not None and data:
            self.taken = [b"".join(self.taken)[: -len(data)]]


def in_chunks(data: bytes) -> Iterator[bytes]:
    return (data[i : i + STEP] for i in range(0, len(data), STEP))


def engine_for(head: bytes):
    """What unpacks data that begin so; None for anything else."""
    if head[:2] == b"\x1f\x8b":
        return zlib.decompressobj(31)
    if len(head) > 2 and head[0] == 0x78 and (head[0] << 8 | head[1]) % 31 == 0:
        return zlib.decompressobj()
    if head[:3] == b"BZh":
        return bz2.BZ2Decompressor()
    if head[:6] == b"\xfd7zXZ\x00":
        return lzma.LZMADecompressor()
    if head[:4] == b"\x28\xb5\x2f\xfd":
        return zstandard.ZstdDecompressor().decompressobj()
    return None


def _member(engine, source: Stream) -> Iterator[bytes]:
    """What one member holds, piece by piece; what follows it, or cannot be read, goes back to the source."""
    while data := source.take():
        try:
            if isinstance(engine, _Zlib):
                left = data
                while left and not engine.eof:
                    yield engine.decompress(left, STEP)
                    left = engine.unconsumed_tail
            elif isinstance(engine, (bz2.BZ2Decompressor, lzma.LZMADecompressor)):
                yield engine.decompress(data, STEP)
                while not engine.eof and not engine.needs_input:
                    yield engine.decompress(b"", STEP)
            else:  # zstandard has no bound on what a step gives, so the steps are small
                for i in range(0, len(data), 256):
                    yield engine.decompress(data[i : i + 256])
                    if engine.eof:
                        source.give_back(data[i + 256 :])
                        break
        except _BAD_DATA:
            source.give_back(data)
            raise
        if engine.eof:
            source.give_back(engine.unused_data)
            return
    if isinstance(engine, _Zlib):
        yield engine.flush()


def _skipped(source: Stream) -> bool:
    """Take padding or a zstandard frame without data off the source; False if it begins with neither."""
    head = source.peek(8)
    if head[:1] == b"\x00":
        while (data := source.take()) and not (rest := data.lstrip(b"\x00")):
            pass
        source.give_back(rest if data else b"")
        return True
    if len(head) == 8 and 0x50 <= head[0] <= 0x5F and head[1:4] == b"\x2a\x4d\x18":
        left = 8 + int.from_bytes(head[4:], "little")
        while left and (data := source.take()):
            source.give_back(data[left:])
            left -= min(left, len(data))
        return True
    return False


def _members(source: Stream) -> Iterator[bytes]:
    """All members one after the other, then what is left over, on a line of its own."""
    begun = False
    while head := source.peek(8):
        if (engine := engine_for(head)) is None:
            if (begun or head[1:4] == b"\x2a\x4d\x18") and _skipped(source):
                continue
            break
        try:
            for out in _member(engine, source):
                begun = begun or bool(out)
                yield out
            begun = True
        except _BAD_DATA:
            break
    if begun and source.peek(1):
        yield b"\n"
        while data := source.take():
            yield data


def opened(source: Stream) -> Stream | None:
    """What the source holds one level of compression below; None, and the source as it was, if nothing."""
    source.taken = []
    inner = filter(None, _members(source))
    first = next(inner, b"")
    taken, source.taken = source.taken, None
    if first and first != b"\n":
        return Stream(chain([first], inner))
    # Nothing came out, so what was taken is all there was to it.
    source.kept, source.chunks = b"", filter(None, chain(taken, [source.kept], source.chunks))
    return None


def windows(data: bytes, place: tuple[int, int], out: set[Span]) -> Iterator[Layer]:
    """Layers over what data hold below any compression; marks what is too large, or comes back, in out."""
    source, heads, total = Stream(in_chunks(data)), set(), 0
    while (inner := opened(source)) is not None:
        source = inner
        if (head := source.peek(STEP)) in heads or head == data:
            out.add(("bomb", *place))
            return
        heads.add(head)

    def layer(b: bytes) -> Layer:
        wide = b"".join(b"\n" + (m[0][1::2] if m[0][0] == 0 else m[0][::2]) for m in _WIDE.finditer(b)) if b"\x00" in b else b""
        return Layer((b + wide).decode("latin-1"), place)

    parts: list[bytes] = []
    size = 0
    while chunk := source.take():
        total += len(chunk)
        if total > MOST_BYTES:
            out.add(("bomb", *place))
        parts.append(chunk)
        size += len(chunk)
        if size < WINDOW:
            continue
        at = max((m.start() for m in _BREAK.finditer(chunk)), default=None)
        if at is None and size < MOST_BYTES:
            continue
        whole = b"".join(parts)
        end = len(whole) if at is None else len(whole) - len(chunk) + at
        yield layer(whole[:end])
        parts = [whole[max(0, end - OVERLAP) :]]
        size = len(parts[0])
    if parts:
        yield layer(b"".join(parts))


def packed_parts(data: bytes) -> Iterator[bytes]:
    """The data from each place on where compressed data that can be unpacked begin, but the start."""
    for m in _PACKED.finditer(data, 1):
        if opened(Stream(in_chunks(data[m.start() :]))) is not None:
            yield data[m.start() :]


def base64_bytes(run: str) -> Iterator[bytes]:
    """What a run may stand for: it may begin with characters that are not part of it, so at all four places."""
    body = run.rstrip("=").replace("-", "+").replace("_", "/")
    for k in range(4):
        n = (len(body) - k) // 4 * 4 + (0, 0, 2, 3)[(len(body) - k) % 4]
        if n > 0:
            data = base64.b64decode(body[k : k + n] + "=" * (-n % 4))
            yield data
            yield from packed_parts(data)


def url_bytes(run: str) -> Iterator[bytes]:
    """Compressed data that a percent-encoded run may hold, from where they begin; + also as a blank."""
    for form in {run, run.replace("+", " ")}:
        data = unquote_to_bytes(form)
        if opened(Stream(in_chunks(data))) is not None:
            yield data
        yield from packed_parts(data)


def decoded_spans(text: str) -> set[Span]:
    """Spans, in the original text, of what the decoded layers hold."""
    out: set[Span] = set()
    seen, runs = set(), set()
    work: list[Iterator[Layer]] = [iter([Layer(text)])]
    while work:
        if (layer := next(work[-1], None)) is None:
            work.pop()
            continue
        if (key := layer.key()) in seen:
            continue
        seen.add(key)
        if len(seen) > 1:
            out.update((k, *layer.original(a, b)) for k, a, b in scan(layer.text))
        if "%" in layer.text:
            if new := unescaped(layer, _URL, _url_run):
                work.append(iter([new]))
            for m in _URL_BYTES.finditer(layer.text):
                place = layer.original(*m.span())
                work += [windows(data, place, out) for data in url_bytes(m[0])]
        if ("\\" in layer.text or "&#" in layer.text) and (new := unescaped(layer, _ESCAPE, _escape_run)):
            work.append(iter([new]))
        for m in _BASE64.finditer(layer.text):
            place = layer.original(*m.span())
            if (run := (sha256(m[0].encode()).digest(), place)) in runs:
                continue
            runs.add(run)
            work += [windows(data, place, out) for data in base64_bytes(m[0])]
    return out


def scan_all(text: str) -> tuple[list[Span], list[Span]]:
    """(base spans, all spans) in order."""
    base = in_order(scan(text))
    if "%" not in text and "\\" not in text and "&#" not in text and not _BASE64.search(text):
        return base, base
    return base, in_order({*base, *decoded_spans(text)})


def secrets(docs: DataFrame) -> DataFrame:
    """doc_id and the spans (kind, start, end, in_text) of every row of docs (doc_id, text)."""
    kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("in_text", pa.bool_())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = []
            for t in batch.column(1).to_pylist():
                base, all_spans = scan_all(t or "")
                found.append([{"kind": k, "start": a, "end": b, "in_text": (k, a, b) in base} for k, a, b in all_spans])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found, kind)], ["doc_id", "spans"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, spans array<struct<kind: string, start: long, end: long, in_text: boolean>>")


def op10_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql import functions as F

    d = secrets(table(spark, sf_dir, "documents"))
    own = F.filter("spans", lambda s: s["in_text"])
    count = lambda kind: F.size(F.filter("spans", lambda s: s["in_text"] & (s["kind"] == kind))).cast("long")
    text = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
    return d.select("doc_id", count("assign").alias("n_assign"), count("access").alias("n_access"), count("hex").alias("n_hex"), F.sha2(text(own).cast("binary"), 256).alias("base_sha256"), text(F.col("spans")).alias("spans"))
