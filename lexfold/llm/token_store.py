"""Token ids in plane-shuffled files.

A file holds the ids of consecutive documents as one stream, cut into chunks of a fixed number of
ids. In a chunk, byte k of all ids (or bit k) forms plane k; each plane is compressed by zstandard on
its own. Chunks are followed by a document table (ids and lengths) and a chunk index, and the file
ends with their place:

    magic | chunks: planes one after the other | tables: zstandard-compressed JSON | place, size | magic

Documents are dealt to files by ranges of doc_id, so files in order of their first doc_id hold the
corpus in order, and a document's start is the sum of what files before it hold plus its place.

Cases. Null and empty texts give the end id alone. Null doc_ids come first. Rows that repeat a doc_id
are all kept, in an order that their texts fix. An empty table gives an empty result. Other columns
are ignored. Names of special tokens that stand in a text become their ids, as the library has it. A
text of any length runs over as many chunks as it needs. A writer holds the ids of a slice of texts and
its file's document table, a reader one chunk's ids and that table.
"""

from __future__ import annotations

import json
import os
import struct
import zlib
from collections.abc import Iterator
from functools import lru_cache
from itertools import chain

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .bpe_codec import byte_letters
from .common import SLICE_BYTES, cut, fresh_dir, parts, table
from .files import create, new_name, open_at
from .pretokens import CachedEncoder, bytes_of

MAGIC = b"IDPLANE1"
CHUNK_IDS = 1 << 16
#: Pieces handed to the model at a call.
AT_ONCE = 64


def to_planes(ids: np.ndarray, kind: str) -> list[bytes]:
    """Planes of 32-bit ids, lowest first, without the highest planes that are all zero."""
    by_byte = np.ascontiguousarray(ids.astype("<u4").view(np.uint8).reshape(-1, 4).T)
    if kind == "byte":
        planes = list(by_byte)
    else:
        planes = [np.packbits(p >> k & 1) for p in by_byte for k in range(8)]
    while planes and not planes[-1].any():
        planes.pop()
    return [p.tobytes() for p in planes]


def from_planes(planes: list[bytes], n: int, kind: str) -> np.ndarray:
    by_byte = np.zeros((4, n), np.uint8)
    for k, p in enumerate(planes):
        if kind == "byte":
            by_byte[k] = np.frombuffer(p, np.uint8)
        else:
            by_byte[k // 8] |= np.unpackbits(np.frombuffer(p, np.uint8), count=n) << (k % 8)
    return np.ascontiguousarray(by_byte.T).view("<u4").ravel()


class Writer:
    def __init__(self, path: str, kind: str = "byte", chunk: int = CHUNK_IDS, level: int = 3):
        self.path, self.kind, self.chunk = path, kind, chunk
        self.out, self.at = create(path), 0
        self.pack = zstandard.ZstdCompressor(level=level).compress
        self.docs: list[int | None] = []
        self.lengths: list[int] = []
        self.index: list[list[int]] = []
        self.rest: list[np.ndarray] = []
        self.n_rest = 0
        self._write(MAGIC)

    def _write(self, data: bytes) -> None:
        self.out.write(data)
        self.at += len(data)

    def add(self, doc_ids: list[int | None], lengths: np.ndarray, ids: np.ndarray) -> None:
        self.docs += doc_ids
        self.lengths += lengths.tolist()
        self.rest.append(ids)
        self.n_rest += len(ids)
        if self.n_rest >= self.chunk:
            self._flush(self.n_rest // self.chunk * self.chunk)

    def _flush(self, n: int) -> None:
        flat = np.concatenate(self.rest) if self.rest else np.zeros(0, np.uint32)
        for a in range(0, n, self.chunk):
            part = flat[a : min(a + self.chunk, n)]
            planes = [self.pack(p) for p in to_planes(part, self.kind)]
            self.index.append([self.at, len(part), *map(len, planes)])
            for p in planes:
                self._write(p)
        self.rest, self.n_rest = [flat[n:]], len(flat) - n

    def close(self) -> None:
        self._flush(self.n_rest)
        tables = self.pack(json.dumps({"kind": self.kind, "docs": self.docs, "lengths": self.lengths, "index": self.index}).encode())
        place = self.at
        self._write(tables)
        self._write(struct.pack("<QQ", place, len(tables)) + MAGIC)
        self.out.close()


class Reader:
    def __init__(self, path: str):
        self.file = open_at(path)
        size = self.file.size()
        if self.file.read_at(8, 0) != MAGIC or self.file.read_at(8, size - 8) != MAGIC:
            raise ValueError(f"{path} is not a complete token file")
        place, n = struct.unpack("<QQ", self.file.read_at(16, size - 24))
        self.unpack = zstandard.ZstdDecompressor().decompress
        tables = json.loads(self.unpack(self.file.read_at(n, place)))
        self.kind, self.docs, self.lengths, self.index = (tables[k] for k in ("kind", "docs", "lengths", "index"))

    def chunk(self, k: int) -> np.ndarray:
        at, n, *sizes = self.index[k]
        planes = []
        for s in sizes:
            planes.append(self.unpack(self.file.read_at(s, at)))
            at += s
        return from_planes(planes, n, self.kind)

    def documents(self) -> Iterator[tuple[int | None, int, Iterator[np.ndarray]]]:
        """(doc_id, n, parts of its ids) in order; the parts of one are to be used up before the next."""
        have, k = np.zeros(0, np.uint32), 0
        for doc, n in zip(self.docs, self.lengths, strict=True):

            def parts(left: int = n) -> Iterator[np.ndarray]:
                nonlocal have, k
                while left:
                    if not len(have):
                        have, k = self.chunk(k), k + 1
                    part, have = have[:left], have[left:]
                    left -= len(part)
                    yield part

            yield doc, n, parts()


def _alone(letters: list[str], vocabulary: dict[str, int]) -> str | None:
    """A letter of a byte that no UTF-8 holds and that no merge takes in: pieces joined by it stay apart."""
    inside = set(chain.from_iterable(t for t in vocabulary if len(t) > 1))
    return next((x for b in (0xC0, 0xC1, *range(0xF5, 0x100)) if (x := letters[b]) in vocabulary and x not in inside), None)


@lru_cache(maxsize=2)
def _encoder(path: str, pattern: str) -> CachedEncoder:
    """Byte-level tokenizers go through the cache of pieces; what any other does to a text is left to it alone."""
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(path)
    config = json.loads(t.to_str())
    how = config["pre_tokenizer"] or {}
    by_pieces = config["normalizer"] is None and config["model"]["type"] == "BPE" and how.get("type") == "ByteLevel" and not how["add_prefix_space"] and how["use_regex"]

    def whole(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        ids = [e.ids for e in t.encode_batch_fast(texts, add_special_tokens=False)]
        return np.array(list(chain.from_iterable(ids)), np.uint32), np.array(list(map(len, ids)), np.int64)

    if not by_pieces:
        return CachedEncoder(pattern, whole, special=("",), encode_whole=whole)
    letters, model, vocabulary = byte_letters(), t.model, t.get_vocab(with_added_tokens=False)
    special = tuple(x.content for x in t.get_added_tokens_decoder().values())
    if (mark := _alone(letters, vocabulary)) is None:
        return CachedEncoder(pattern, whole, special, whole)
    mark_id, mark_byte, by_byte = vocabulary[mark], letters.index(mark), np.array(list(map(ord, letters)), "<u2")

    def of_pieces(pieces: pa.StringArray) -> tuple[np.ndarray, np.ndarray]:
        """The model's ids of many pieces at a call."""
        data, begins = bytes_of(pieces)
        joined = by_byte[np.insert(data, begins[1:], mark_byte)].tobytes().decode("utf-16-le")
        ends = (begins + np.arange(len(begins)))[[*range(0, len(pieces), AT_ONCE), len(pieces)]].tolist()
        out: list[int] = []
        for lo, hi in zip(ends[:-1], ends[1:], strict=True):
            out += [x.id for x in model.tokenize(joined[lo:hi])]
        ids = np.array(out, np.uint32)
        return ids[ids != mark_id], np.diff(np.flatnonzero(ids == mark_id), prepend=-1) - 1

    return CachedEncoder(pattern, of_pieces, special, whole, split=lambda x: [at for _, at in t.pre_tokenizer.pre_tokenize_str(x)])


def write_store(docs: DataFrame, folder: str, path: str, pattern: str, end_id: int = 0, kind: str = "byte") -> DataFrame:
    """Encode docs (doc_id, text) into files of the folder; returns the list of files.

    (path, first, n_docs, n_ids). first: least doc_id. The list is written down at once, so that a
    lost executor never leads to a second, different set of files.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, writer, n_ids, first = _encoder(path, pattern), None, 0, None
        for part in parts(batches, most=2 * SLICE_BYTES):
            doc_ids = part.column(0).to_pylist()
            if writer is None:
                writer, first = Writer(new_name(folder, "ids"), kind), doc_ids[0]
            ids, begins = encoder.encode(part.column(1))
            ids = np.insert(ids, begins[1:], np.uint32(end_id))
            writer.add(doc_ids, np.diff(begins) + 1, ids)
            n_ids += len(ids)
        if writer is not None:
            writer.close()
            yield pa.RecordBatch.from_arrays([pa.array([writer.path]), pa.array([first], pa.int64()), pa.array([len(writer.docs)], pa.int64()), pa.array([n_ids], pa.int64())], ["path", "first", "n_docs", "n_ids"])

    dealt = docs.select("doc_id", "text").repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    return cut(dealt.mapInArrow(run, "path string, first long, n_docs long, n_ids long"))


def read_store(files: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, from the files."""
    before = F.sum("n_ids").over(Window.orderBy(F.col("first").asc_nulls_first(), "path").rowsBetween(Window.unboundedPreceding, -1))
    placed = files.select("path", F.coalesce(before, F.lit(0)).alias("start"))

    def packed(rows: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], ["doc_id", "start", "n_tokens", "ids_crc32"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path, start in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                rows: list[tuple] = []
                for doc, n, pieces in Reader(path).documents():
                    crc = 0
                    for p in pieces:
                        crc = zlib.crc32(p.tobytes(), crc)
                    rows.append((doc, start, n, crc))
                    start += n
                    if len(rows) == 4096:
                        yield packed(rows)
                        rows = []
                if rows:
                    yield packed(rows)

    # One task a file, as AQE would put small lists of large files into one task.
    return placed.repartition(max(1, files.count()), "path").mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def op3_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    files = write_store(table(spark, sf_dir, "documents"), fresh_dir(spark, "token-store"), public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.PATTERN)
    return read_store(files)
