"""N-gram Jaccard join over count-vector R-trees, with the groups of linked documents.

A document's set holds its distinct runs of four words. Two documents link when their sets' Jaccard
similarity reaches a bound. The join is exact:

1. One scan makes, for every document, its set's size, fingerprint, count vector (how many shingles
   fall in each of G hash groups) and prefix: so many of its smallest hashes that two linking sets
   share one of them. Documents of equal sets are one class from here on.
2. Members of a block (a shared prefix hash) are tried against three of the block's members; verified
   links give a first labelling. Large groups of near copies collapse here, at a few pairs a member.
3. In each block, members of different labels are joined through an R-tree of their count vectors:
   the sum of coordinate minima of two points, or of the upper corners of two nodes, bounds the
   overlap from above; pairs below the overlap that the bound on similarity asks for are pruned.
4. What survives is verified on the whole sets, and verified links are contracted to groups.
5. Inside each group every pair of classes is compared on the whole sets, tile by tile, which gives
   the exact number of links of each document.

Blocks are cut by size class (linking sets differ by a bounded factor) and, where they are large,
into tiles, so that no task holds an unbounded group. A pair inside one label is known to be
connected already, so leaving it out loses no group; the links of step 5 do not depend on it. The work
of step 5 grows with the square of a group, in memory bounded by tiles.

Cases. Null and empty texts have no shingles, link with nothing and are their own group, as is every
null doc_id (a null group). Texts under four words are one shingle. Rows that repeat a doc_id and text
count once for links and are returned each; rows of one doc_id with different texts are documents of
their own. Empty tables give empty results; other columns are ignored (filtering keeps them).
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import byte_texts, components, cut, mix, parts, released, run_hashes, sized, slices, swept, table, word_hashes

#: A block's tile; R-tree leaf and inner node sizes.
TILE, LEAF = 2048, 32
#: Shingles of a tile whose links are counted, and columns of a membership matrix.
TILE_SHINGLES, COLUMNS = 500_000, 2048
#: Pairs that a task remembers having sent, and pairs made distinct at once.
MOST_SEEN, AT_ONCE = 200_000, 50_000
#: Pairs of one owner that are verified together.
CHUNK = 256
#: Hash groups by set size: enough that unlike sets of that size differ in their counts.
GROUPS = ((1_500, 256), (6_000, 512), (math.inf, 1_024))


def shingle_sets(texts: list[bytes], width: int) -> Iterator[np.ndarray]:
    """Sorted distinct shingle hashes of each text."""
    for lo, hi in slices([len(t) for t in texts]):
        words, begins = word_hashes([t.lower() for t in texts[lo:hi]])
        runs = run_hashes(words, width)
        for a, b in zip(begins[:-1].tolist(), begins[1:].tolist(), strict=True):
            if b - a >= width:
                yield np.unique(runs[a : b - width + 1])
            elif b > a:
                yield run_hashes(words[a:b], b - a) ^ np.uint64(b - a)
            else:
                yield np.zeros(0, np.uint64)


def groups_of(n: int) -> int:
    return next(g for most, g in GROUPS if n < most)


def count_vector(shingles: np.ndarray) -> bytes:
    """Counts by group, one byte each where they fit, else four."""
    g = groups_of(len(shingles))
    counts = np.bincount((shingles >> np.uint64(20)).astype(np.int64) & (g - 1), minlength=g)
    return counts.astype(np.uint8 if counts.max(initial=0) < 256 else np.int32).tobytes()


def vector_of(data: bytes, n: int) -> np.ndarray:
    kind = np.uint8 if len(data) == groups_of(n) else np.int32
    return np.frombuffer(data, kind).astype(np.int32)


def folded(vector: np.ndarray, g: int) -> np.ndarray:
    """A vector over fewer groups; the groups' numbers are nested."""
    return vector.reshape(-1, g).sum(0) if len(vector) > g else vector


def least_overlap(a: np.ndarray, b: np.ndarray, percent: int) -> np.ndarray:
    """Shared shingles that sets of these sizes need: 100 * shared >= percent * union."""
    return -((-percent * (a + b)) // (100 + percent))


class CountTree:
    """R-tree over points of counts, packed by size and then by leading coordinates."""

    def __init__(self, points: np.ndarray, sizes: np.ndarray):
        half = points[:, : max(1, points.shape[1] // 2)].sum(1)
        self.order = np.lexsort((half, sizes))
        self.points, self.sizes = points[self.order], sizes[self.order]
        self.cuts = np.arange(0, len(sizes), LEAF)
        self.upper = np.maximum.reduceat(self.points, self.cuts, axis=0)
        self.least = np.minimum.reduceat(self.sizes, self.cuts)
        self.most = np.maximum.reduceat(self.sizes, self.cuts)

    def leaf(self, k: int) -> slice:
        return slice(k * LEAF, min((k + 1) * LEAF, len(self.sizes)))

    def join(self, other: CountTree, percent: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(own, other) places of the points whose bound leaves a link possible."""
        for i in range(len(self.cuts)):
            bound = np.minimum(self.upper[i], other.upper).sum(1)
            near = (bound >= least_overlap(self.least[i], other.least, percent)) & (100 * self.most[i] >= percent * other.least) & (100 * other.most >= percent * self.least[i])
            for k in np.flatnonzero(near):
                a, b = self.leaf(i), other.leaf(k)
                shared = np.minimum(self.points[a, None, :], other.points[None, b, :]).sum(2)
                x, y = self.sizes[a, None], other.sizes[None, b]
                p, q = np.nonzero((shared >= least_overlap(x, y, percent)) & (100 * np.minimum(x, y) >= percent * np.maximum(x, y)))
                if len(p):
                    yield self.order[a][p], other.order[b][q]


def block_pairs(ids: np.ndarray, labels: np.ndarray, sizes: np.ndarray, home: np.ndarray, vectors: list[np.ndarray], percent: int) -> Iterator[np.ndarray]:
    """Candidate pairs (rows of two, smaller id first) between home members, and of home members with visitors."""
    if (labels == labels[0]).all() or not home.any():
        return
    g = min(len(v) for v in vectors)
    points = np.stack([folded(v, g) for v in vectors])

    def trees() -> Iterator[tuple[np.ndarray, np.ndarray]]:
        at_home, away = np.flatnonzero(home), np.flatnonzero(~home)
        own = CountTree(points[at_home], sizes[at_home])
        yield from ((at_home[p], at_home[q]) for p, q in own.join(own, percent))
        if len(away):
            yield from ((at_home[p], away[q]) for p, q in own.join(CountTree(points[away], sizes[away]), percent))

    if len(ids) <= LEAF:
        i, j = np.triu_indices(len(ids), 1)
        x, y = sizes[i], sizes[j]
        ok = (home[i] | home[j]) & (100 * np.minimum(x, y) >= percent * np.maximum(x, y))
        i, j = i[ok], j[ok]
        ok = np.minimum(points[i], points[j]).sum(1) >= least_overlap(sizes[i], sizes[j], percent)
        found = iter([(i[ok], j[ok])])
    else:
        found = trees()
    for i, j in found:
        ok = labels[i] != labels[j]
        x, y = ids[i[ok]], ids[j[ok]]
        if len(x):
            yield np.stack((np.minimum(x, y), np.maximum(x, y)), 1)


def lists(arrays: list[np.ndarray]) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, arrays)]), pa.int32()), pa.array(np.concatenate(arrays) if arrays else np.zeros(0, np.int64)))


def profiles(docs: DataFrame, width: int, percent: int) -> DataFrame:
    """doc_id, text_key (hash of the text), n, d1, d2 (fingerprint of the set), vector, prefix."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in parts(batches):
            n, d1, d2, vec, pre = [], [], [], [], []
            for s in shingle_sets(byte_texts(part.column(1)), width):
                n.append(len(s))
                d1.append(int(mix(s).sum(dtype=np.uint64).astype(np.int64)) if len(s) else 0)
                d2.append(int(mix(s ^ np.uint64(0x5851F42D4C957F2D)).sum(dtype=np.uint64).astype(np.int64)) if len(s) else 0)
                vec.append(count_vector(s) if len(s) else b"")
                pre.append(s[: len(s) - -(-percent * len(s) // 100) + 1].view(np.int64).copy() if len(s) else np.zeros(0, np.int64))
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array(n, pa.int64()), pa.array(d1, pa.int64()), pa.array(d2, pa.int64()), pa.array(vec, pa.binary()), lists(pre)], ["doc_id", "text_key", "n", "d1", "d2", "vector", "prefix"])

    return docs.select("doc_id", "text", F.xxhash64(F.coalesce("text", F.lit(""))).alias("text_key")).mapInArrow(run, "doc_id long, text_key long, n long, d1 long, d2 long, vector binary, prefix array<long>")


def sets_of(docs: DataFrame, ids: DataFrame, width: int) -> DataFrame:
    """(id, shingles) of the documents in ids; made anew from the texts, so sets are never stored."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in parts(batches):
            yield pa.RecordBatch.from_arrays([part.column(0), lists([s.view(np.int64) for s in shingle_sets(byte_texts(part.column(1)), width)])], ["id", "shingles"])

    wanted = docs.select("doc_id", "text").join(sized(ids.select(F.col("id").alias("doc_id"))), "doc_id", "left_semi")
    return wanted.mapInArrow(run, "id long, shingles array<long>")


def verified(docs: DataFrame, pairs: DataFrame, width: int, percent: int) -> DataFrame:
    """The pairs (a, b) whose whole sets are similar enough.

    The end that is in more pairs owns a pair. An owner's pairs are cut into chunks of about CHUNK; its set
    is sent once a chunk, the other one's once a pair, so no set and no key is in the way of all others.
    """
    pairs = cut(pairs)
    ends = cut(pairs.select(F.explode(F.array("a", "b")).alias("id")).groupBy("id").agg(F.count("*").alias("n")))
    sets = sets_of(docs, ends, width)
    hot = sized(ends.where(F.col("n") > CHUNK))
    d = pairs
    for c in ("a", "b"):
        d = d.join(hot.select(F.col("id").alias(c), F.col("n").alias(f"n_{c}")), c, "left")
    n_a, n_b = F.coalesce("n_a", F.lit(1)), F.coalesce("n_b", F.lit(1))
    owner, other = F.when(n_a >= n_b, F.col("a")).otherwise(F.col("b")), F.when(n_a >= n_b, F.col("b")).otherwise(F.col("a"))
    d = d.select(owner.alias("owner"), other.alias("id"), F.pmod(F.xxhash64(other), F.ceil(F.greatest(n_a, n_b) / CHUNK)).alias("chunk"))
    owners = d.select("owner", F.col("owner").alias("id"), "chunk").distinct()
    rows = owners.withColumn("role", F.lit(0)).unionByName(d.withColumn("role", F.lit(1))).join(sets, "id")
    rows = rows.select("owner", "chunk", "role", "id", "shingles").repartition("owner", "chunk").sortWithinPartitions("owner", "chunk", "role")
    return rows.mapInArrow(lambda it: _verify(it, percent), "a long, b long").distinct()


def _verify(rows: Iterator[pa.RecordBatch], percent: int) -> Iterator[pa.RecordBatch]:
    """Linking pairs of rows (owner, chunk, role, id, shingles), where each chunk begins with its owner's set."""
    bases: list[np.ndarray] = []  # more than one if rows with different texts share the owner's doc_id
    before = None
    for batch in parts(rows, "shingles"):
        owner, chunk, role, ids = (batch.column(c).to_numpy() for c in ("owner", "chunk", "role", "id"))
        sets = batch.column("shingles")
        sizes = sets.value_lengths().to_numpy().astype(np.int64)
        ends = np.cumsum(sizes)
        flat = sets.flatten().to_numpy().view(np.uint64)
        new = np.flatnonzero((owner[1:] != owner[:-1]) | (chunk[1:] != chunk[:-1])) + 1
        kept = []
        for lo, hi in zip([0, *new.tolist()], [*new.tolist(), len(ids)], strict=True):
            if (here := (owner[lo], chunk[lo])) != before:
                bases, before = [], here
            while lo < hi and role[lo] == 0:
                bases.append(flat[ends[lo] - sizes[lo] : ends[lo]].copy())
                lo += 1
            if lo == hi:
                continue
            part = flat[ends[lo] - sizes[lo] : ends[hi - 1]]
            at = ends[lo:hi] - (ends[lo] - sizes[lo])
            for base in bases:
                held = np.concatenate(([0], np.cumsum(base[np.minimum(np.searchsorted(base, part), len(base) - 1)] == part)))
                shared = held[at] - held[at - sizes[lo:hi]]
                ok = lo + np.flatnonzero(100 * shared >= percent * (sizes[lo:hi] + len(base) - shared))
                kept.append(np.stack((np.minimum(owner[ok], ids[ok]), np.maximum(owner[ok], ids[ok])), 1))
        if kept:
            yield _pairs(np.concatenate(kept))


def _pairs(x: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(x[:, 0], pa.int64()), pa.array(x[:, 1], pa.int64())], ["a", "b"])


def _search(rows: Iterator[pa.RecordBatch], percent: int) -> Iterator[pa.RecordBatch]:
    """Candidate pairs of blocks that arrive one after the other, sorted by block."""
    rest: pa.Table | None = None
    seen: set[int] = set()

    def new(found: list[np.ndarray]) -> pa.RecordBatch:
        """Found pairs that were not sent before; what is sent twice for want of memory is made distinct later."""
        x = np.concatenate(found) if found else np.zeros((0, 2), np.int64)
        keys = [a << 64 | b & (1 << 64) - 1 for a, b in x.tolist()]
        places = {k: i for i, k in enumerate(keys) if k not in seen}
        if len(seen) + len(places) <= MOST_SEEN:
            seen.update(places)
        return _pairs(x[np.fromiter(places.values(), np.int64, len(places))])

    def pairs(t: pa.Table) -> Iterator[pa.RecordBatch]:
        block = np.stack([t.column(c).to_numpy() for c in ("key", "band", "i", "j")])
        starts = np.flatnonzero(np.concatenate(([True], (block[:, 1:] != block[:, :-1]).any(0))))
        ids, labels, sizes, home = (t.column(c).to_numpy(zero_copy_only=False) for c in ("id", "label", "n", "home"))
        raw = t.column("vector").to_pylist()
        found, n = [], 0
        for a, b in zip(starts.tolist(), [*starts[1:].tolist(), len(ids)], strict=True):
            if b - a > 1:
                for x in block_pairs(ids[a:b], labels[a:b], sizes[a:b], home[a:b], [vector_of(v, n) for v, n in zip(raw[a:b], sizes[a:b].tolist(), strict=True)], percent):
                    found.append(x)
                    n += len(x)
                    if n >= AT_ONCE:
                        yield new(found)
                        found, n = [], 0
        yield new(found)

    try:
        for batch in rows:
            t = pa.Table.from_batches([batch])
            t = pa.concat_tables([rest, t]).combine_chunks() if rest is not None else t
            block = np.stack([t.column(c).to_numpy() for c in ("key", "band", "i", "j")])
            changes = np.flatnonzero((block[:, 1:] != block[:, :-1]).any(0))
            if len(changes):
                yield from pairs(t.slice(0, changes[-1] + 1))
                t = t.slice(changes[-1] + 1)
            rest = t
        if rest is not None and len(rest):
            yield from pairs(rest)
    finally:
        rest = None
        released()


def tree_candidates(members: DataFrame, percent: int) -> DataFrame:
    """Distinct pairs (a, b) of members that share a prefix hash and pass the R-tree's bounds.

    members: id, label, n, vector, prefix.
    """
    rows = members.select("id", "label", "n", F.explode("prefix").alias("key"))
    h = F.xxhash64("id")
    blocks = rows.groupBy("key").agg(F.min("label").alias("x"), F.max("label").alias("y"), F.count("*").alias("m"), F.bit_xor(h).alias("s1"), F.bit_xor(F.xxhash64(h, F.lit(1))).alias("s2"))
    # Blocks of the same members would yield the same pairs: one of them stays.
    mixed = blocks.where("x <> y").groupBy("m", "s1", "s2").agg(F.min("key").alias("key")).select("key")
    band = F.floor(F.log("n") / (-math.log(percent / 100) * (1 + 1e-9))).cast("int")
    rows = cut(rows.join(mixed, "key", "left_semi").withColumn("band", band))
    # A member is at home in its size class and visits the next one below, where smaller partners are.
    spread = rows.select("id", "label", "n", "key", F.explode(F.array(F.struct("band", F.lit(True).alias("home")), F.struct((F.col("band") - 1).alias("band"), F.lit(False).alias("home")))).alias("x")).select("id", "label", "n", "key", "x.*")
    often = spread.groupBy("key", "band").agg(F.count("*").alias("m"), F.count_if("home").alias("at_home")).where("m > 1 and at_home > 0")
    spread = spread.join(often.drop("at_home"), ["key", "band"])
    tiles = F.ceil(F.col("m") / TILE).cast("int")
    own = F.pmod(F.xxhash64("id"), tiles).cast("int")
    cell = lambda k: F.struct(F.least(k, own).alias("i"), F.greatest(k, own).alias("j"))
    cells = spread.select("id", "label", "n", "key", "band", "home", F.explode(F.transform(F.sequence(F.lit(0), tiles - 1), cell)).alias("c")).select("id", "label", "n", "key", "band", "home", "c.*")
    cells = cells.join(members.select("id", "vector"), "id")
    sorted_cells = cells.repartition("key", "band", "i", "j").sortWithinPartitions("key", "band", "i", "j")
    return sorted_cells.mapInArrow(lambda it: _search(it, percent), "a long, b long").distinct()


def leader_candidates(made: DataFrame, ids: DataFrame, percent: int, keys: int = 3) -> DataFrame:
    """Pairs of each member with three members of its first few blocks, where the bounds leave a link possible.

    The three are the first, the one whose class has most copies (what others were copied from), and the
    first of its own sixteenth of the block, so that large groups meet in many ways. ids: doc_id, copies.
    """
    members = made.join(ids, "doc_id").withColumnRenamed("doc_id", "id")
    rows = members.select("id", "copies", F.explode(F.slice("prefix", 1, keys)).alias("key"))
    leaders = rows.groupBy("key").agg(F.min("id").alias("first"), F.max(F.struct("copies", -F.col("id"))).alias("top"), F.count("*").alias("m")).where("m > 1")
    leaders = leaders.select("key", F.explode(F.array_distinct(F.array("first", -F.col("top.col2")))).alias("a"))
    sixteenth = rows.select("id", F.xxhash64("key", F.pmod(F.xxhash64("id", "key"), F.lit(16))).alias("key"))
    own_leaders = sixteenth.groupBy("key").agg(F.min("id").alias("a"), F.count("*").alias("m")).where("m > 1").select("key", "a")
    met = rows.select("id", "key").join(leaders, "key").unionByName(sixteenth.join(own_leaders, "key"))
    pairs = met.where("a <> id").select(F.least("a", "id").alias("a"), F.greatest("a", "id").alias("b")).distinct()
    own = lambda c: members.select(F.col("id").alias(c), F.col("n").alias(f"n_{c}"), F.col("vector").alias(f"v_{c}"))
    near = pairs.join(own("a"), "a").join(own("b"), "b").where(100 * F.least("n_a", "n_b") >= percent * F.greatest("n_a", "n_b"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            t = {c: batch.column(c).to_pylist() for c in ("n_a", "n_b", "v_a", "v_b")}
            keep = []
            for n, m, v, w in zip(t["n_a"], t["n_b"], t["v_a"], t["v_b"], strict=True):
                x, y = vector_of(v, n), vector_of(w, m)
                g = min(len(x), len(y))
                keep.append(bool(np.minimum(folded(x, g), folded(y, g)).sum() >= least_overlap(np.int64(n), np.int64(m), percent)))
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return near.select("a", "b", "n_a", "n_b", "v_a", "v_b").mapInArrow(run, "a long, b long")


def _nodes(docs: DataFrame, width: int, percent: int) -> tuple[DataFrame, DataFrame]:
    """(profiles with `node`, docs as node and text): a node is a doc_id, or a hash where an id has several texts."""
    made = cut(profiles(docs, width, percent))
    several = made.where("doc_id is not null").groupBy("doc_id").agg(F.min("text_key").alias("x"), F.max("text_key").alias("y"))
    several = sized(cut(several.where("x <> y").select("doc_id", F.lit(True).alias("several"))))
    key = F.when(F.col("several"), F.xxhash64("doc_id", "text_key")).otherwise(F.col("doc_id"))
    of = lambda d: d.join(several, "doc_id", "left").withColumn("node", key).drop("several")
    return of(made), of(docs.select("doc_id", "text", F.xxhash64(F.coalesce("text", F.lit(""))).alias("text_key"))).select(F.col("node").alias("doc_id"), "text")


def _grouped(docs: DataFrame, width: int, percent: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Profiles of the documents; their classes (d1, d2, n, id, least doc_id, copies) with their group; docs by node."""
    made, docs = _nodes(docs, width, percent)
    classes = cut(made.where("n > 0 and doc_id is not null").groupBy("d1", "d2", "n").agg(F.min("node").alias("id"), F.min("doc_id").alias("least"), F.count_distinct("node").alias("copies")))
    nodes = made.drop("doc_id").withColumnRenamed("node", "doc_id")
    ids = classes.select("id", "copies")
    first = swept(verified(docs, leader_candidates(nodes, sized(ids.withColumnRenamed("id", "doc_id")), percent), width, percent))
    labels = components(first).select("id", F.col("component").alias("label"))
    labelled = sized(swept(ids.select("id").join(labels, "id", "left").withColumn("label", F.coalesce("label", "id"))))
    members = nodes.withColumnRenamed("doc_id", "id").join(labelled, "id")
    second = swept(verified(docs, tree_candidates(members, percent), width, percent))
    links = first.select("a", "b").union(second.select("a", "b"))
    grouped = classes.join(components(links), "id", "left").withColumn("component", F.coalesce("component", "id"))
    return made, swept(grouped), docs


def cell_links(cell: pa.Table, percent: int) -> pa.Table:
    """(id, n_links) of the members of a cell: of tile i with tile j, both ways; or inside one tile.

    cell: id, copies, tile, i, j, shingles. Overlaps are products of membership matrices.
    """
    ids, copies, tile = (cell.column(c).to_numpy() for c in ("id", "copies", "tile"))
    sets = cell.column("shingles").combine_chunks()
    sizes = sets.value_lengths().to_numpy().astype(np.int64)
    _, column, often = np.unique(sets.flatten().to_numpy(), return_inverse=True, return_counts=True)
    row = np.repeat(np.arange(len(ids)), sizes)
    # What one set alone holds is shared with none; shingles of the same sets are one column with a weight.
    kept = often[column] > 1
    column, row = np.unique(column[kept], return_inverse=True)[1], row[kept]
    marks = mix(np.arange(1, 2 * len(ids) + 1, dtype=np.uint64)).reshape(2, -1)
    sums = np.zeros((2, int(column.max(initial=-1)) + 1), np.uint64)
    for k in (0, 1):
        np.add.at(sums[k], column, marks[k][row])
    _, first, merged, weight = np.unique(sums, axis=1, return_index=True, return_inverse=True, return_counts=True)
    kept = first[merged[column]] == column
    column, row = merged[column[kept]], row[kept]
    order = np.argsort(column, kind="stable")
    column, row = column[order], row[order]
    one, other = np.flatnonzero(tile == cell.column("i")[0].as_py()), np.flatnonzero(tile == cell.column("j")[0].as_py())
    shared = np.zeros((len(one), len(other)), np.float32)
    for lo in range(0, len(weight), COLUMNS):
        x, y = np.searchsorted(column, (lo, lo + COLUMNS))
        held = np.zeros((len(ids), min(COLUMNS, len(weight) - lo)), np.float32)
        held[row[x:y], column[x:y] - lo] = 1
        shared += (held[one] * weight[lo : lo + COLUMNS].astype(np.float32)) @ held[other].T
    found = np.zeros(len(ids), np.int64)
    for lo in range(0, len(one), LEAF):
        part, own = shared[lo : lo + LEAF].astype(np.int64), one[lo : lo + LEAF]
        link = (100 * part >= percent * (sizes[own][:, None] + sizes[other] - part)) & (ids[own][:, None] != ids[other])
        found[own] += link @ copies[other]
        if cell.column("i")[0] != cell.column("j")[0]:
            found[other] += link.T @ copies[own]
    released()
    return pa.table({"id": pa.array(ids, pa.int64()), "n_links": pa.array(found, pa.int64())})


def all_links(docs: DataFrame, members: DataFrame, width: int, percent: int) -> DataFrame:
    """(id, n_links): documents of other classes that link with class id. members: id, component, n, copies.

    Linking classes are in one group, so each group is cut into tiles of bounded size and every tile
    meets every other one of its group. Sets travel once a tile of their group, pairs not at all.
    """
    of_group = members.groupBy("component").agg(F.sum("n").alias("most"), F.count("*").alias("m"))
    tiles = F.greatest(F.ceil(F.col("most") / TILE_SHINGLES), F.ceil(F.col("m") / TILE)).cast("int")
    m = members.join(of_group.select("component", tiles.alias("tiles")), "component").withColumn("tile", F.pmod(F.xxhash64("id"), "tiles").cast("int"))
    cell = lambda k: F.struct(F.least(k, "tile").alias("i"), F.greatest(k, "tile").alias("j"))
    cells = m.select("id", "component", "copies", "tile", F.explode(F.transform(F.sequence(F.lit(0), F.col("tiles") - 1), cell)).alias("c")).select("id", "component", "copies", "tile", "c.*")
    sets = sets_of(docs, members.select("id"), width).dropDuplicates(["id"])
    met = cells.join(sets, "id").groupBy("component", "i", "j").applyInArrow(lambda t: cell_links(t, percent), "id long, n_links long")
    return met.groupBy("id").agg(F.sum("n_links").alias("n_links"))


def jaccard_groups(docs: DataFrame, width: int = 4, percent: int = 85) -> DataFrame:
    """doc_id, n_shingles, component_id and n_links of every row of docs (doc_id, text).

    n_links counts the other documents (distinct ids) whose sets are similar enough, equal sets included.
    """
    made, classes, docs = _grouped(docs, width, percent)
    groups = classes.groupBy("component").agg(F.min("least").alias("component_id"), F.count("*").alias("m"))
    # A class that is a group of its own links with its copies alone.
    linked = classes.join(groups.where("m > 1").select("component"), "component", "left_semi").select("id", "component", "n", "copies")
    links = all_links(docs, cut(linked), width, percent)
    n_links = F.col("copies") - 1 + F.coalesce("n_links", F.lit(0))
    of_class = classes.join(groups, "component").join(links, "id", "left").select("d1", "d2", "n", "component_id", n_links.alias("n_links"))
    d = made.select("doc_id", "n", "d1", "d2").join(of_class, ["d1", "d2", "n"], "left")
    alone = F.col("component_id").isNull() | F.col("doc_id").isNull()
    return d.select("doc_id", F.col("n").alias("n_shingles"), F.when(alone, F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"), F.when(alone, 0).otherwise(F.col("n_links")).cast("long").alias("n_links"))


def one_of_each_group(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """docs without those that another document stands for; the least doc_id of a group stays.

    Rows go by doc_id and text, so a text that a repeated doc_id has beside a dropped one stays. Rows that
    repeat the doc_id and text of the one that stays, stay too.
    """
    made, classes, _ = _grouped(docs, width, percent)
    keepers = classes.groupBy("component").agg(F.min(F.struct("least", "id")).alias("keeper"))
    of_class = classes.join(keepers, "component").select("d1", "d2", "n", "id", "keeper")
    rest = made.where("doc_id is not null").join(of_class, ["d1", "d2", "n"]).where("doc_id <> keeper.least or id <> keeper.id").select("doc_id", "text_key").distinct()
    rest = sized(cut(rest.toDF("gone_id", "gone_key")))
    own = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("own"), F.col("doc_id").alias("this_id"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("this_key"))
    return own.join(rest, (F.col("this_id") == F.col("gone_id")) & (F.col("this_key") == F.col("gone_key")), "left_anti").select("own.*")


def op1_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_groups(table(spark, sf_dir, "documents").select("doc_id", "text"))
