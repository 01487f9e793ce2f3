"""Benchmark decontamination: a BM25 index of test items, searched with every training passage.

Test items are cut into parts of at most PART words and indexed with BM25 impacts, each divided by
the part's own total, so a part's score is the share of its BM25 mass that a passage holds and one
threshold fits all. Every text becomes passages of 2 * PART words, a new one each PART words, so a part
that a text holds lies whole in one passage. Parts stand in blocks; the largest impact of every term
in every block bounds what a block can score (block-max), which rules out nearly all blocks for a
whole batch of passages at once. In blocks that remain, postings are walked part by part with WAND's
pivots, and all parts at or above the threshold are retrieved. A retrieved item counts as leaked when
enough five-word runs of its question and enough of its answer stand in the text.

An item with columns `question` and `answer` uses them; one with only `text` is split at two thirds of
its words. Words are lower-cased and lose ASCII punctuation.

The index goes to the executors in pieces of at most PIECE_PARTS parts each, whose size that bounds;
statistics (document frequencies, mean length) are those of all items. A benchmark too large for
MOST_PIECES pieces at once is searched in several passes over the texts.

Cases. Null and empty texts, and items without words, match nothing. Null ids are kept as ids of their
own rows. Repeated documents and items are searched and reported each. Items that say the same are all
reported. Empty tables give empty results; other columns are ignored (filtering keeps them, and judges
each row by its own text).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut, parts, run_hashes, table, word_hashes

PART, BLOCK, RUN = 64, 2, 5
PIECE_PARTS, MOST_PIECES = 1_024, 64
K1, B = 1.2, 0.75
_PUNCTUATION = bytes(i for i in range(33, 127) if not chr(i).isalnum())


def plain(text: str | None) -> bytes:
    return (text or "").lower().encode().translate(None, _PUNCTUATION)


def hashed(texts: list[str | None]) -> list[np.ndarray]:
    words, begins = word_hashes([plain(t) for t in texts])
    return [words[a:b] for a, b in zip(begins[:-1], begins[1:], strict=True)]


class PartIndex:
    """Inverted index with block maxima over some parts."""

    def __init__(self, parts: list[np.ndarray], idf: dict[int, float], mean_length: float):
        self.n = len(parts)
        self.terms = np.unique(np.concatenate(parts)) if parts else np.zeros(0, np.uint64)
        rows: list[list[tuple[int, float]]] = [[] for _ in self.terms]
        for p, words in enumerate(parts):
            own, tf = np.unique(words, return_counts=True)
            w = np.array([idf[int(t)] for t in own]) * tf * (K1 + 1) / (tf + K1 * (1 - B + B * len(words) / mean_length))
            for t, x in zip(np.searchsorted(self.terms, own), w / w.sum(), strict=True):
                rows[t].append((p, float(x)))
        self.postings = rows
        self.block_max = np.zeros((len(self.terms), -(-self.n // BLOCK)), np.float32)
        for t, row in enumerate(rows):
            for p, x in row:
                self.block_max[t, p // BLOCK] = max(self.block_max[t, p // BLOCK], x)

    def search(self, groups: np.ndarray, words: np.ndarray, threshold: float) -> Iterator[tuple[int, int, float]]:
        """(group, part, score) at or above the threshold; groups: the passage of each word, ascending."""
        if not self.n or not len(words):
            return
        at = np.minimum(np.searchsorted(self.terms, words), len(self.terms) - 1)
        hit = self.terms[at] == words
        pairs = np.unique(groups[hit] * len(self.terms) + at[hit])
        if not len(pairs):
            return
        g, t = pairs // len(self.terms), pairs % len(self.terms)
        starts = np.flatnonzero(np.concatenate(([True], g[1:] != g[:-1])))
        ends = np.append(starts[1:], len(g))
        for lo in range(0, self.block_max.shape[1], 32):
            bound = np.add.reduceat(self.block_max[t, lo : lo + 32], starts, axis=0)
            for k, b in zip(*np.nonzero(bound >= threshold * 0.9999), strict=True):
                for part, score in self._walk(t[starts[k] : ends[k]].tolist(), lo + int(b), threshold):
                    yield int(g[starts[k]]), part, score

    def _walk(self, terms: list[int], block: int, threshold: float) -> Iterator[tuple[int, float]]:
        """WAND over the postings of one block."""
        lists = []
        for t in terms:
            if self.block_max[t, block]:
                own = [x for x in self.postings[t] if x[0] // BLOCK == block]
                lists.append([0, own, float(self.block_max[t, block])])
        while lists:
            lists.sort(key=lambda x: x[1][x[0]][0])
            bound, pivot = 0.0, None
            for at, own, most in lists:
                bound += most
                if bound >= threshold * 0.9999:
                    pivot = own[at][0]
                    break
            if pivot is None:
                return
            if lists[0][1][lists[0][0]][0] == pivot:
                score = sum(x[1][x[0]][1] for x in lists if x[1][x[0]][0] == pivot)
                if score >= threshold:
                    yield pivot, score
                floor = pivot + 1
            else:
                floor = pivot
            for x in lists:
                while x[0] < len(x[1]) and x[1][x[0]][0] < floor:
                    x[0] += 1
            lists = [x for x in lists if x[0] < len(x[1])]


def _runs(words: np.ndarray) -> tuple[int, np.ndarray]:
    n = min(RUN, len(words))
    return n, np.unique(run_hashes(words, n)) if n else np.zeros(0, np.uint64)


class Items:
    """A piece of the benchmark: the index of its parts, and what is verified."""

    def __init__(self, ids: list[int | None], questions: list[np.ndarray], answers: list[np.ndarray], idf: dict[int, float], mean_length: float):
        parts, self.owner = [], []
        for k, (q, a) in enumerate(zip(questions, answers, strict=True)):
            words = np.concatenate((q, a))
            for lo in range(0, len(words), PART):
                parts.append(words[lo : lo + PART])
                self.owner.append(k)
        self.ids = ids
        self.runs = [(_runs(q), _runs(a)) for q, a in zip(questions, answers, strict=True)]
        self.index = PartIndex(parts, idf, mean_length)

    def overlap(self, k: int, words: np.ndarray, cache: dict[int, np.ndarray]) -> tuple[float, float]:
        """Shares of the question's and of the answer's runs that the text holds; an empty side counts as held."""
        out = []
        for n, runs in self.runs[k]:
            if n not in cache:
                cache[n] = np.unique(run_hashes(words, n)) if n else np.zeros(0, np.uint64)
            out.append(float(np.isin(runs, cache[n]).mean()) if n else 1.0)
        return out[0], out[1]


def item_rows(benchmark: DataFrame) -> DataFrame:
    """item_id, question, answer."""
    if {"question", "answer"} <= set(benchmark.columns):
        return benchmark.select("item_id", "question", "answer")
    words = F.filter(F.split(F.coalesce("text", F.lit("")), r"[\x20\x09-\x0D]+"), lambda w: w != "")
    cutting = F.ceil(F.size("w") * 2 / 3).cast("int")
    d = benchmark.select("item_id", words.alias("w"))
    return d.select("item_id", F.array_join(F.slice("w", 1, cutting), " ").alias("question"), F.array_join(F.slice("w", cutting + 1, F.size("w")), " ").alias("answer"))


def _terms(items: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            both = [f"{q or ''} {a or ''}" for q, a in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)]
            rows = [(int(t.astype(np.int64)), int(c), len(w)) for w in hashed(both) for t, c in zip(*np.unique(w, return_counts=True), strict=True)]
            columns = zip(*rows, strict=True) if rows else [[]] * 3
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], ["term", "tf", "length"])

    return items.select("question", "answer").mapInArrow(run, "term long, tf long, length long")


def build(benchmark: DataFrame) -> Iterator[list[Items]]:
    """The benchmark's pieces, at most MOST_PIECES at once; each holds at most PIECE_PARTS parts and an item."""
    items = cut(item_rows(benchmark))
    terms = cut(_terms(items))
    total = items.count()
    size = terms.agg(F.sum("tf")).first()[0] or 0
    mean_length = min(PART, max(1.0, size / max(1, total)))
    df = terms.groupBy("term").agg(F.count("*").alias("df"))
    bucket = F.pmod(F.xxhash64("item_id", "question", "answer"), F.lit(max(1, -(-max(total, size // PART) // (PIECE_PARTS * MOST_PIECES // 2)))))
    numbered = items.withColumn("bucket", bucket)
    for k in sorted(r.bucket for r in numbered.select("bucket").distinct().collect()):
        rows = numbered.where(F.col("bucket") == k).orderBy("item_id", "question", "answer").collect()
        mine = df.join(_terms(numbered.where(F.col("bucket") == k)).select("term").distinct(), "term").collect()
        idf = {r.term & (2**64 - 1): float(np.log(1 + (total - r.df + 0.5) / (r.df + 0.5))) for r in mine}
        q, a = hashed([r.question for r in rows]), hashed([r.answer for r in rows])
        pieces, lo, parts = [], 0, 0
        for i in range(len(rows)):
            parts += -(-(len(q[i]) + len(a[i])) // PART)
            if parts >= PIECE_PARTS or i == len(rows) - 1:
                pieces.append(Items([r.item_id for r in rows[lo : i + 1]], q[lo : i + 1], a[lo : i + 1], idf, mean_length))
                lo, parts = i + 1, 0
        yield pieces


def leaks(docs: DataFrame, benchmark: DataFrame, threshold: float = 0.4, share: float = 0.5) -> DataFrame:
    """(doc_id, item_id, score, question_share, answer_share) of every leaked item of every text."""
    spark, found = docs.sparkSession, None
    schema = "doc_id long, item_id long, score double, question_share double, answer_share double"
    for pieces in build(benchmark):
        sent = spark.sparkContext.broadcast(pieces)

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            for part in parts(batches):
                rows = list(_search(part.column(0).to_pylist(), part.column(1).to_pylist(), sent.value, threshold, share))
                columns = list(zip(*rows, strict=True)) if rows else [[]] * 5
                kinds = (pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.float64())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], ["doc_id", "item_id", "score", "question_share", "answer_share"])

        one = docs.select("doc_id", "text").mapInArrow(run, schema)
        found = one if found is None else found.union(one)
    return spark.createDataFrame([], schema) if found is None else found


def _search(doc_ids: list, texts: list, pieces: list[Items], threshold: float, share: float) -> Iterator[tuple]:
    words, begins = word_hashes([plain(t) for t in texts])
    place = np.arange(len(words)) - np.repeat(begins[:-1], np.diff(begins))
    doc = np.repeat(np.arange(len(texts)), np.diff(begins))
    n_passages = np.maximum(1, -(-np.diff(begins) // PART) - 1)
    first = np.concatenate(([0], np.cumsum(n_passages)))
    last = place // PART
    # Each word lies in the passage that its stretch of PART words opens and in the one before.
    for_groups = np.concatenate((first[doc] + np.minimum(last, n_passages[doc] - 1), first[doc] + np.clip(last - 1, 0, None)))
    both = np.concatenate((words, words))
    for items in pieces:
        best: dict[tuple[int, int], float] = {}
        for g, part, score in items.index.search(for_groups, both, threshold):
            d = int(np.searchsorted(first, g, "right")) - 1
            key = (d, items.owner[part])
            best[key] = max(score, best.get(key, 0.0))
        cache: dict[int, dict[int, np.ndarray]] = {}
        for (d, k), score in sorted(best.items()):
            q, a = items.overlap(k, words[begins[d] : begins[d + 1]], cache.setdefault(d, {}))
            if q >= share and a >= share:
                yield doc_ids[d], items.ids[k], score, q, a


def without_leaks(docs: DataFrame, benchmark: DataFrame, threshold: float = 0.4, share: float = 0.5) -> DataFrame:
    """The rows of docs whose text holds no test item; each row has its own verdict, whatever its doc_id."""
    at, schema = docs.columns.index("text"), docs.schema
    for pieces in build(benchmark):
        sent = docs.sparkSession.sparkContext.broadcast(pieces)

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            for part in parts(batches, at):
                clean = np.ones(part.num_rows, bool)
                clean[[row[0] for row in _search(list(range(part.num_rows)), part.column(at).to_pylist(), sent.value, threshold, share)]] = False
                yield part.filter(pa.array(clean))

        docs = docs.mapInArrow(run, schema)
    return docs


def op6_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
