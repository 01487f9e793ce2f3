"""Byte-level BPE encoding and decoding through a sentencepiece model made from a rank file.

The model is serialised directly from the vocabulary: each token's bytes mapped to printable
characters, scored by its negative rank, in rank order so that piece numbers are ranks, with identity
normalisation. sentencepiece then merges as byte-level BPE does. Texts are cut by the pattern before
(each piece encoded alone); a piece that is itself in the vocabulary takes its rank at once, as rank
encoders do. Decoding maps each id back to its bytes.

Cases. Null and empty texts have no ids; their digests are those of the empty string. Every row is
returned, whatever its other columns hold; null and repeated doc_ids are allowed, tables may be
empty. Special tokens' names are ordinary text. Lone surrogates cannot occur in Spark's strings.
"""

from __future__ import annotations

import base64
import struct
from collections.abc import Iterator
from functools import lru_cache
from hashlib import sha256
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import SLICE_BYTES, parts, table
from .pretokens import CachedEncoder


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


def byte_letters() -> list[str]:
    """A printable character for each byte: itself where it is one, else from 256 on."""
    keep = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    spare = iter(range(256, 512))
    return [chr(b if b in keep else next(spare)) for b in range(256)]


def _field(number: int, kind: int, value: bytes | int | float) -> bytes:
    """One field in protobuf's wire format; kind 0: varint, 2: bytes, 5: 32-bit float."""

    def varint(x: int) -> bytes:
        out = bytearray()
        while x > 0x7F:
            out.append(x & 0x7F | 0x80)
            x >>= 7
        return bytes([*out, x])

    body = {0: lambda: varint(value & (2**64 - 1)), 2: lambda: varint(len(value)) + value, 5: lambda: struct.pack("<f", value)}[kind]()
    return varint(number << 3 | kind) + body


def model_proto(ranks: dict[bytes, int]) -> bytes:
    """A serialised sentencepiece BPE model whose piece numbers are the ranks."""
    letters = byte_letters()
    by_rank = sorted(ranks, key=ranks.get)
    if [ranks[t] for t in by_rank] != list(range(len(by_rank))):
        raise ValueError("ranks must run from 0 without gaps")
    piece = lambda text, score, kind: _field(1, 2, _field(1, 2, text.encode()) + _field(2, 5, score) + _field(3, 0, kind))
    out = [piece("".join(map(letters.__getitem__, t)), -float(r), 1) for r, t in enumerate(by_rank)]
    out.append(piece("⁇", 0.0, 2))  # the unknown piece that a model must have; no byte maps to it
    trainer = _field(3, 0, 2) + _field(4, 0, len(out)) + _field(40, 0, len(by_rank)) + _field(41, 0, -1) + _field(42, 0, -1) + _field(43, 0, -1)
    normal = _field(1, 2, b"identity") + _field(3, 0, 0) + _field(4, 0, 0) + _field(5, 0, 0)
    return b"".join(out) + _field(2, 2, trainer) + _field(3, 2, normal)


class BpeCodec:
    def __init__(self, ranks: dict[bytes, int], pattern: str):
        from sentencepiece import SentencePieceProcessor

        self.ranks, self.letters = ranks, byte_letters()
        self.model = SentencePieceProcessor(model_proto=model_proto(ranks))
        self.bytes_of = sorted(ranks, key=ranks.get)
        self.cached = CachedEncoder(pattern, self._pieces)

    def _pieces(self, pieces: pa.StringArray) -> tuple[np.ndarray, np.ndarray]:
        raw = pieces.cast(pa.binary()).to_pylist()
        whole = [self.ranks.get(p) for p in raw]
        todo = ["".join(map(self.letters.__getitem__, p)) for p, w in zip(raw, whole, strict=True) if w is None]
        merged = iter(self.model.encode(todo, num_threads=1) if todo else ())
        ids = [next(merged) if w is None else [w] for w in whole]
        return np.array(list(chain.from_iterable(ids)), np.uint32), np.array(list(map(len, ids)))

    def encode(self, texts: pa.Array | list[str]) -> tuple[np.ndarray, np.ndarray]:
        return self.cached.encode(texts)

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))


@lru_cache(maxsize=2)
def _codec(path: str, pattern: str) -> BpeCodec:
    """A worker's codec; the vocabulary file is one of an installed package, found on each machine."""
    return BpeCodec(read_ranks(path), pattern)


def encode_decode(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id, ids (array), decoded (bytes) of every row of docs (doc_id, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = _codec(path, pattern)
        for part in parts(batches):
            ids, begins = codec.encode(part.column(1))
            decoded = [codec.decode(ids[a:b].tolist()) for a, b in zip(begins[:-1], begins[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.ListArray.from_arrays(pa.array(begins, pa.int32()), pa.array(ids.astype(np.int32))), pa.array(decoded, pa.binary())], ["doc_id", "ids", "decoded"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, ids array<int>, decoded binary")


def digests(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256; made where the ids are, so they never travel."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = _codec(path, pattern)
        names = list(map(str, range(len(codec.bytes_of))))
        for part in parts(batches, most=2 * SLICE_BYTES):
            ids, begins = codec.encode(part.column(1))
            out: list[list] = [[], [], []]
            for a, b in zip(begins[:-1].tolist(), begins[1:].tolist(), strict=True):
                own = ids[a:b].tolist()
                out[0].append(b - a)
                out[1].append(sha256(",".join(map(names.__getitem__, own)).encode()).hexdigest())
                out[2].append(sha256(codec.decode(own)).hexdigest())
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(out[0], pa.int64()), pa.array(out[1], pa.string()), pa.array(out[2], pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def op4_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return digests(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)
