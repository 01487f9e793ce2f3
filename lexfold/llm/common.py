"""Shared pieces of the training-data operators: tables, shared folder, text hashing, components."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: The blanks between words, as regular expression and as bytes.
BLANKS = r"\x20\x09-\x0D"
BLANK_BYTES = b" \t\n\x0b\x0c\r"
#: Text handled at once inside a Python task; bounds the arrays made from it.
SLICE_BYTES = 2 << 20
#: Edges that one task brings to components; more go by rounds of joins.
FEW_EDGES = 100_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def held_out(doc_id: str | F.Column = "doc_id") -> F.Column:
    """True for the fifth of documents that no model may learn from."""
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % 5 == 0


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share; a local one is set only where the session names none."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    found = spark.sparkContext.getCheckpointDir()
    if named:
        if not found:
            spark.sparkContext.setCheckpointDir(named)
        return named.rstrip("/")
    if not found:
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        spark.sparkContext.setCheckpointDir(f"file://{tempfile.mkdtemp(prefix='lexfold-')}")
        found = spark.sparkContext.getCheckpointDir()
    return found.rstrip("/")


def cut(df: DataFrame) -> DataFrame:
    """Write df to the shared folder and read it from there, so that lost executors cost nothing."""
    shared_dir(df.sparkSession)
    return df.checkpoint()


def swept(df: DataFrame) -> DataFrame:
    """cut(df), after which the driver collects its garbage: its heap shrinks, and Spark drops the shuffles, broadcasts and checkpoints that nothing refers to any more."""
    out = cut(df)
    gc.collect()
    df.sparkSession.sparkContext._jvm.System.gc()
    return out


def fresh_dir(spark: SparkSession, what: str) -> str:
    return f"{shared_dir(spark)}/{what}-{uuid.uuid4().hex}"


def remove_dir(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def byte_texts(column: pa.Array) -> list[bytes]:
    """UTF-8 bytes of every text; null counts as empty."""
    return [x or b"" for x in column.cast(pa.binary()).to_pylist()]


def released() -> None:
    """Give unused memory of this Python process back; workers live on and are shared by later tasks."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):  # not glibc
        pass


def parts(batches: Iterator[pa.RecordBatch], column: str | int = "text", most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """The rows of batches in parts of about `most` bytes of a column (texts or lists of longs); memory is given back at the end."""
    try:
        for batch in batches:
            x = batch.column(column)
            size = pc.binary_length(x) if pa.types.is_string(x.type) or pa.types.is_binary(x.type) else pc.multiply(pc.list_value_length(x), 8)
            for lo, hi in slices(pc.fill_null(size, 0).to_pylist(), most):
                yield batch.slice(lo, hi - lo)
    finally:
        released()


def slices(sizes: list[int], most: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of rows of about `most` bytes; a row is never split."""
    lo = total = 0
    for i, n in enumerate(sizes):
        if total and total + n > most:
            yield lo, i
            lo, total = i, 0
        total += n
    if lo < len(sizes):
        yield lo, len(sizes)


def sized(df: DataFrame, most_rows: int = 1_000_000) -> DataFrame:
    """df marked for broadcast if a count proves it small; beyond that the join shuffles both sides."""
    return F.broadcast(df) if df.limit(most_rows + 1).count() <= most_rows else df


# --- hashing of words and word runs -----------------------------------------------------------

_RNG = np.random.default_rng(20240229)
_BYTE = _RNG.integers(1, 2**63, 256, dtype=np.uint64) | np.uint64(1)
_BASE = 0x9E3779B97F4A7C15
_BASE_INV = pow(_BASE, -1, 1 << 64)
_PLACE = (_RNG.integers(1, 2**63, 64, dtype=np.uint64) << np.uint64(1)) | np.uint64(1)
_IS_BLANK = np.zeros(256, bool)
_IS_BLANK[list(BLANK_BYTES)] = True
_POWERS: dict[str, np.ndarray] = {}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_POWERS.get("up", ())) < n:
        size = max(n, SLICE_BYTES + 4096)
        for key, base in (("up", _BASE), ("down", _BASE_INV)):
            p = np.full(size, base, np.uint64)
            p[0] = 1
            _POWERS[key] = np.multiply.accumulate(p)
    return _POWERS["up"][:n], _POWERS["down"][:n]


def mix(x: np.ndarray) -> np.ndarray:
    """Bijective scrambling of 64-bit numbers."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def word_hashes(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(hash of every word, where each text's words begin; one more entry at the end)."""
    buf = np.frombuffer(b" ".join(texts) + b" ", np.uint8)
    blank = _IS_BLANK[buf]
    edge = np.flatnonzero(np.diff(np.concatenate(([True], blank)).astype(np.int8)))
    starts, ends = edge[0::2], edge[1::2]
    up, down = _powers(len(buf) + 1)
    run = np.zeros(len(buf) + 1, np.uint64)
    np.cumsum(_BYTE[buf] * up[: len(buf)], out=run[1:])
    words = mix((run[ends] - run[starts]) * down[starts] + (ends - starts).astype(np.uint64))
    begins = np.cumsum([0, *(len(t) + 1 for t in texts)])
    return words, np.searchsorted(starts, begins)


def run_hashes(words: np.ndarray, n: int) -> np.ndarray:
    """Hash of each run of n words; run i begins at word i."""
    if len(words) < n:
        return np.zeros(0, np.uint64)
    last = len(words) - n + 1
    out = words[:last] * _PLACE[0]
    for k in range(1, n):
        out = out + words[k : k + last] * _PLACE[k]
    return mix(out)


# --- connected components ---------------------------------------------------------------------


def least_in_reach(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, least node in reach) of every node of the edges (a[i], b[i])."""
    ids, at = np.unique(np.concatenate((a, b)), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    top = np.arange(len(ids))
    while (top[x] != top[y]).any():
        np.minimum.at(top, np.maximum(top[x], top[y]), np.minimum(top[x], top[y]))
        while (top[top] != top).any():
            top = top[top]
    return ids, ids[top]


def _few_components(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    t = [(x.column("a").to_numpy(), x.column("b").to_numpy()) for x in batches]
    if t:
        yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in least_in_reach(*map(np.concatenate, zip(*t, strict=True)))], ["id", "component"])


def components(edges: DataFrame) -> DataFrame:
    """(id, component) of every node of edges (a, b); component is the least id in reach.

    Up to FEW_EDGES edges go through one task, and their components are marked for broadcast: rounds of
    joins would be thousands of tasks for the driver to keep. More edges alternate two star contractions;
    each step is a grouped minimum and a join, and the edge list never grows, until a round changes
    nothing. Nodes without an edge are not returned.
    """
    e = cut(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct())

    def stamp(df: DataFrame) -> tuple:
        return tuple(df.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())

    seen = stamp(e)
    if seen[0] <= FEW_EDGES:
        return F.broadcast(e.coalesce(1).mapInArrow(_few_components, "id long, component long"))
    while True:
        both = e.select("a", "b").union(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.join(low, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        low2 = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(low2, "a").select(F.explode(F.array(F.struct(F.col("b").alias("a"), F.col("m").alias("b")), F.struct("a", F.col("m").alias("b")))).alias("x")).select("x.*").where("a <> b").distinct()
        e = cut(small)
        now = stamp(e)
        if now == seen:
            break
        seen = now
    heads = e.select(F.col("a").alias("id"), F.col("b").alias("component"))
    return heads.union(e.select(F.col("b").alias("id"), F.col("b").alias("component")).distinct())
