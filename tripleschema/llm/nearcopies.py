"""Near copies: word shingles, bit-sliced SimHash comparison, exact Jaccard similarity.

Texts with the same set of shingles are one class, which the row with the least number stands for.  Two sets with a
Jaccard similarity of 4/5 or more share an element among the first n - ceil(4 n / 5) + 1 of each in any common order, so
classes meet in buckets of those elements and no pair is lost; nor is one whose elements behind the first common one are too few for that similarity.  Shingles that a sample finds frequent come last in the
order, which keeps buckets small; the sample decides only how long it takes.  Buckets tie their classes together to
clusters, and a cluster is compared as a whole: the bit planes of wide SimHash fingerprints tell in one pass which of a
block's sets can be near a set, and those in other trees of the block are compared exactly.  In clusters beyond a block,
small buckets give their pairs, and what large buckets tie together is compared block by block in tasks of their own.

On request the links of SimHash fingerprints at a few bits count as well, found as op7 finds them; the exact comparison
then adds the near copies that lie further apart in bits.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tripleschema.llm.common import give_back, numbered, only_members, prepare, removed, slices, spread_join, without, written
from tripleschema.llm.components import connected_components
from tripleschema.llm.simhash import fingerprint, linked, near_wide, wide_fingerprint, wide_planes

SHINGLE = 5  # words
SHARE = (4, 5)  # the least Jaccard similarity, as a fraction
SMALL = 128  # classes of a bucket that gives its pairs; more than four times what the sample finds frequent
CHUNK = 1024  # classes in a side of a block
ELEMENTS = 1 << 18  # and elements, about
SAMPLE = 8  # one text in so many is looked at for frequent shingles
PARTS = 256  # of a set, in which the place of an element is told
FREQUENT = 4  # occurrences in the sample
MOST_FREQUENT = 200_000
RADIUS = 80  # of WIDE bits; at 4/5 the expected distance is 39 with a deviation of 6, so it is seven deviations away
SURE = 48  # elements from which a fingerprint is asked; smaller sets are always compared exactly
SEEN = 200_000  # classes that a task remembers to have dealt out


def shingles(text: str | None, shingle: int = SHINGLE) -> np.ndarray:
    """Hashes of the distinct word shingles (ASCII lower case), rising; of all words if there are fewer; none without words."""
    words = (text or "").encode().lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    grams = [b" ".join(words)] if len(words) < shingle else map(b" ".join, zip(*(words[i:] for i in range(shingle)), strict=False))
    return np.unique(np.fromiter(map(xxhash.xxh64_intdigest, grams, repeat(42)), np.uint64))


def similar(inter, size, other):
    """Whether sets of these sizes with so many common elements are near copies."""
    a, b = SHARE
    return b * inter >= a * (size + other - inter)


def leading(h: np.ndarray, frequent: np.ndarray, rank: np.ndarray) -> np.ndarray:
    """The elements of which two near copies share one: the first in the order of rank in ``frequent``, then of hash."""
    n = len(h) - -(-SHARE[0] * len(h) // SHARE[1]) + 1 if len(h) else 0
    if n and len(frequent):
        at = np.minimum(np.searchsorted(frequent, h), len(frequent) - 1)
        h = h[np.argsort(np.where(frequent[at] == h, rank[at], 0), kind="stable")]
    return h[:n]


def _signs(prints: bool):
    """``rid, none, id, sign, fp``: the sign is a 128-bit hash of the set of shingles, ``fp`` op7's fingerprint if asked."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches):
            texts = part.column(1).to_pylist()
            signs = [xxhash.xxh3_128_digest(shingles(t).tobytes()) for t in texts]
            fps = np.array([fingerprint(t) if prints else 0 for t in texts], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(2).is_null(), part.column(2), pa.array(signs, pa.binary()), pa.array(fps)], ["rid", "none", "id", "sign", "fp"])

    return run


def _elements(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for part in slices(batches):
        found = [np.zeros(0, np.uint64), *map(shingles, part.column(1).to_pylist())]
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(found).view(np.int64))], ["key"])


def _keys(frequent: np.ndarray, rank: np.ndarray):
    """``key, rid, sign, size`` of the leading elements, ``size`` with the place in PARTS of the set in its last byte; of equal sets that a task has met lately, the first one's."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[bytes] = set()
        for part in slices(batches):
            keys, rids, signs, sizes = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)], [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)]
            for rid, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                h = shingles(text)
                sign = xxhash.xxh3_128_digest(h.tobytes())
                if sign in seen:
                    continue
                if len(seen) >= SEEN:
                    seen.clear()
                seen.add(sign)
                keys.append(leading(h, frequent, rank))
                n = len(keys[-1])
                rids.append(np.full(n, rid, np.int64))
                sizes.append((len(h) << 8) + np.arange(n) * PARTS // max(1, len(h)))
                signs.append(np.full(n, int.from_bytes(sign[:8], "big"), np.uint64))
            cols = [np.concatenate(keys).view(np.int64), np.concatenate(rids), np.concatenate(signs).view(np.int64), np.concatenate(sizes)]
            yield pa.RecordBatch.from_arrays(list(map(pa.array, cols)), ["key", "rid", "sign", "size"])

    return run


def _meet(small: int):
    """Rows sorted by key, size, sign and rid: pairs of small buckets, and ties of each class of a large one to its first.

    Rows with one key, size and sign are one class, of which the first stays.  The rows of a class are the same in all
    its buckets, so the first is the same one everywhere."""

    def found(key: np.ndarray, rid: np.ndarray, size: np.ndarray) -> pa.RecordBatch:
        place, size = size & 255, size >> 8
        rest = size - place * size // PARTS  # no more elements can be common, if this is the first common one
        starts = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
        count = np.diff(np.r_[starts, len(key)])
        large = np.repeat(count > small, count)
        first = np.repeat(starts, count)
        a, b = [rid[first[large]]], [rid[large]]
        ties = int(large.sum())
        for lag in range(1, min(small, len(key))):
            i = np.flatnonzero((key[lag:] == key[:-lag]) & ~large[lag:])
            if not len(i):
                break
            i = i[SHARE[0] * size[i + lag] <= SHARE[1] * size[i]]
            i = i[sum(SHARE) * np.minimum(rest[i], rest[i + lag]) >= SHARE[0] * (size[i] + size[i + lag])]
            a.append(rid[i])
            b.append(rid[i + lag])
        a, b = np.concatenate(a), np.concatenate(b)
        tie = np.arange(len(a)) < ties
        keep = np.flatnonzero(a != b)
        return pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)[keep]), pa.array(np.maximum(a, b)[keep]), pa.array(tie[keep])], ["a", "b", "tie"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        rows, enough, last = 0, 1 << 16, None
        for batch in batches:
            if not batch.num_rows:
                continue
            key, rid, sign, size = (batch.column(k).to_numpy(zero_copy_only=False) for k in range(4))
            new = np.r_[last != (key[0], size[0], sign[0]), (key[1:] != key[:-1]) | (size[1:] != size[:-1]) | (sign[1:] != sign[:-1])]
            last = (key[-1], size[-1], sign[-1])
            held.append((key[new], rid[new], size[new]))
            rows += int(new.sum())
            if rows >= enough:
                cols = [np.concatenate(c) for c in zip(*held, strict=True)]
                cut = int(np.searchsorted(cols[0], cols[0][-1]))  # the last bucket may go on
                if cut:
                    yield found(*(c[:cut] for c in cols))
                held, rows = [tuple(c[cut:] for c in cols)], rows - cut
                enough = max(1 << 16, 2 * rows)
        if rows:
            yield found(*(np.concatenate(c) for c in zip(*held, strict=True)))

    return run


# -- comparison


def _verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """``a, b`` of the pairs whose texts are near copies."""
    for batch in batches:
        keep = []
        for i in range(batch.num_rows):
            x, y = (shingles(batch.column(k)[i].as_py()) for k in (2, 3))
            if similar(len(np.intersect1d(x, y, assume_unique=True)), len(x), len(y)):
                keep.append(i)
        kept = batch.take(pa.array(keep, pa.int64()))
        yield pa.RecordBatch.from_arrays([kept.column(0), kept.column(1)], ["a", "b"])


class Block:
    """Sets that are compared with each other, or those of one side with those of the other."""

    def __init__(self, sets: list[np.ndarray], side: np.ndarray, crossed: bool):
        self.sets, self.side, self.crossed = sets, side, crossed
        self.size = np.array([len(s) for s in sets], np.int64)
        self.tree = np.arange(len(sets))  # a number for each tree of the forest so far
        values, self.at = np.unique(np.concatenate(sets), return_inverse=True)
        owner = np.repeat(np.arange(len(sets)), self.size)
        order = np.argsort(self.at, kind="stable")
        self.owner = owner[order]
        count = np.bincount(self.at, minlength=len(values))
        self.begin = np.r_[0, np.cumsum(count)]
        self.ends = np.r_[0, np.cumsum(self.size)]
        #: How common a set's elements are in the block: the texts that others are copies of come first.
        self.common = np.bincount(owner, weights=count[self.at], minlength=len(sets)) / np.maximum(1, self.size)
        self.prints = None

    def candidates(self, rows: np.ndarray) -> np.ndarray:
        """For each of the rows, which lanes may be near."""
        a, b = SHARE
        size = self.size
        fit = (a * size[rows][:, None] <= b * size[None, :]) & (a * size[None, :] <= b * size[rows][:, None])
        if self.crossed:
            fit &= self.side[rows][:, None] != self.side[None, :]
        if len(self.sets) > 64:
            if self.prints is None:
                self.prints = np.array([wide_fingerprint(s) for s in self.sets])
                self.planes = wide_planes(self.prints)
            fit &= near_wide(self.planes, self.prints[rows], len(self.sets), RADIUS) | (size < SURE)[None, :] | (size[rows] < SURE)[:, None]
        return fit

    def row(self, i: int, lanes: np.ndarray) -> list[tuple[int, int]]:
        """Links of set i to one set of each other tree that has a near copy among ``lanes``."""
        lanes = lanes[self.tree[lanes] != self.tree[i]]
        out = []
        if len(lanes) > 32:  # all at once
            posts = [self.owner[self.begin[v] : self.begin[v + 1]] for v in self.at[self.ends[i] : self.ends[i + 1]]]
            inter = np.bincount(np.concatenate(posts), minlength=len(self.sets))[lanes]
            lanes = lanes[similar(inter, self.size[lanes], self.size[i])]
            for j in lanes[np.unique(self.tree[lanes], return_index=True)[1]].tolist():
                out.append((j, i))
                self.tree[self.tree == self.tree[j]] = self.tree[i]
        else:
            for j in lanes.tolist():
                if self.tree[j] != self.tree[i] and similar(len(np.intersect1d(self.sets[i], self.sets[j], assume_unique=True)), self.size[i], self.size[j]):
                    out.append((j, i))
                    self.tree[self.tree == self.tree[j]] = self.tree[i]
        return out

    def links(self) -> list[tuple[int, int]]:
        """A spanning forest of the near copies.  Only sets outside the largest tree need to be asked: of two sets in
        different trees, one is outside."""
        done, out, n = np.zeros(len(self.sets), bool), [], 1
        while True:
            largest = int(np.bincount(self.tree).argmax())
            todo = np.flatnonzero(~done & (self.tree != largest))
            if not len(todo):
                return out
            rows = todo[np.argsort(-self.common[todo], kind="stable")[:n]]
            for i, fit in zip(rows.tolist(), self.candidates(rows), strict=True):
                out += self.row(i, np.flatnonzero(fit))
            done[rows] = True
            n = min(64, 2 * n)


def block_links(rid: list[int], sets: list[np.ndarray], side: list[int], crossed: bool) -> list[tuple[int, int]]:
    """Links of a spanning forest of the near copies in a block (of those from one side to the other, if ``crossed``)."""
    return [(rid[i], rid[j]) for i, j in Block(sets, np.array(side), crossed).links()]


def _blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by cluster and block."""
    key, held = None, []

    def links() -> pa.RecordBatch:
        found = block_links([r[0] for r in held], [r[2] for r in held], [r[1] for r in held], key[2])
        return pa.RecordBatch.from_arrays([pa.array([x[k] for x in found], pa.int64()) for k in (0, 1)], ["a", "b"])

    for batch in batches:
        for label, block, crossed, rid, side, text in zip(*(batch.column(k).to_pylist() for k in range(6)), strict=True):
            if (label, block, crossed) != key:
                if held:
                    yield links()
                    if len(held) > 64:
                        give_back()
                key, held = (label, block, crossed), []
            held.append((rid, side, shingles(text)))
    if held:
        yield links()


def frequent_shingles(texts: DataFrame, sample: int = SAMPLE, least: int = FREQUENT, most: int = MOST_FREQUENT) -> tuple[np.ndarray, np.ndarray]:
    """Frequent shingles of a sample, rising, and their counts; at most ``most``."""
    part = texts.where(F.pmod(F.xxhash64("rid"), F.lit(sample)) == 0).mapInArrow(_elements, "key long")
    rows = part.groupBy("key").agg(F.count("*").alias("n")).where(F.col("n") >= least).orderBy(F.desc("n"), "key").limit(most).toArrow()
    keys, n = rows.column("key").to_numpy().view(np.uint64), rows.column("n").to_numpy()
    order = np.argsort(keys)
    return keys[order], n[order]


def texts_of(texts: DataFrame, rids: DataFrame) -> DataFrame:
    """The rows of ``rid, text`` with a number in ``rids``; other texts are kept out of the shuffle where that can be."""
    rids = written(rids, "wanted")
    return only_members(texts, rids).join(rids, "rid", "left_semi")


def links(texts: DataFrame, small: int = SMALL, chunk: int = CHUNK) -> DataFrame:
    """Links ``(a, b)`` that connect all near copies among the classes of ``rid, text``, named by their least numbers."""
    prepare(texts.sparkSession)
    frequent, rank = frequent_shingles(texts)
    keys = texts.mapInArrow(_keys(frequent, rank), "key long, rid long, sign long, size long")
    met = keys.repartition("key").sortWithinPartitions("key", "size", "sign", "rid").mapInArrow(_meet(small), "a long, b long, tie boolean")
    met = written(met.groupBy("a", "b").agg(F.bool_or("tie").alias("tie")), "near-candidates")
    clusters = written(connected_components(met), "near-clusters")
    size = clusters.groupBy("label").agg(F.count("*").alias("n"))
    wide = written(clusters.join(size.where(F.col("n") > chunk), "label").select("node", "label"), "near-wide")
    whole = _compared(texts, written(clusters.join(size.where(F.col("n") <= chunk), "label").select("node", "label"), "near-whole"), chunk)
    if wide.isEmpty():
        return whole
    # beyond a block, what small buckets tie together is compared pair by pair, and what large ones do in blocks
    within = met.join(wide.select(F.col("node").alias("a")), "a", "left_semi")
    tied = written(connected_components(within.where("tie")), "near-tied")
    own = tied.select(F.col("node").alias("a"), F.col("label").alias("la"))
    other = tied.select(F.col("node").alias("b"), F.col("label").alias("lb"))
    pairs = within.where(~F.col("tie")).select("a", "b").join(own, "a", "left").join(other, "b", "left").where("la is null or lb is null or la != lb").select("a", "b")
    pairs = written(pairs, "near-pairs")
    wanted = texts_of(texts, pairs.select(F.explode(F.array("a", "b")).alias("rid")).distinct())
    left, right = (wanted.select(F.col("rid").alias(n), F.col("text").alias(f"of_{n}")) for n in ("a", "b"))
    single = pairs.join(left, "a").join(right, "b").select("a", "b", "of_a", "of_b").mapInArrow(_verify, "a long, b long")
    return whole.unionByName(single).unionByName(_compared(texts, tied, chunk))


def _compared(texts: DataFrame, clusters: DataFrame, chunk: int) -> DataFrame:
    """Links of the near copies within each cluster ``node, label``, dealt over blocks of ``chunk`` by ``chunk`` texts
    (fewer, if they are long)."""
    texts = texts_of(texts, clusters.select(F.col("node").alias("rid")))
    sized = texts.select("rid", (F.length("text") / 6).alias("words")).join(clusters.select(F.col("node").alias("rid"), "label"), "rid")
    size = sized.groupBy("label").agg(F.greatest(F.ceil(F.count("*") / chunk), F.ceil(F.sum("words") / ELEMENTS), F.lit(1)).cast("int").alias("c"))
    placed = clusters.join(size, "label").withColumn("own", F.pmod(F.xxhash64("node"), F.col("c")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("c") - 1)))
    placed = placed.select("label", (F.least("own", "other") * F.col("c") + F.greatest("own", "other")).cast("long").alias("block"), (F.col("own") != F.col("other")).alias("crossed"), F.col("node").alias("rid"), (F.col("own") > F.col("other")).cast("int").alias("side"))
    placed = texts.join(placed, "rid").select("label", "block", "crossed", "rid", "side", "text")
    return placed.repartition("label", "block").sortWithinPartitions("label", "block", "side", "rid").mapInArrow(_blocks, "a long, b long")


# -- the operator


def print_links(signs: DataFrame, classes: DataFrame, radius: int) -> DataFrame:
    """Links ``(a, b)`` that connect the classes whose texts have fingerprints in one component of op7: each to the first.

    A class may have several fingerprints, and a fingerprint several classes."""
    marks = written(signs.select("fp", "sign").distinct().join(classes.select("sign", "rid"), "sign").select("fp", "rid"), "marks")
    firsts = written(marks.groupBy("fp").agg(F.min("rid").alias("first"), F.count("*").alias("n")), "prints")
    labels = connected_components(linked(firsts, radius))
    of = firsts.join(labels, F.col("fp") == F.col("node"), "left").select("fp", "first", "n", F.coalesce("label", "fp").alias("label"))
    named = written(of.join(of.groupBy("label").agg(F.min("first").alias("a")), "label").select("fp", "a", "n"), "print-components")
    return spread_join(marks, named, ["fp"], "n").where("a != rid").select("a", F.col("rid").alias("b"))


def representatives(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", small: int = SMALL, chunk: int = CHUNK, radius: int | None = None) -> DataFrame:
    """One row of each component of near copies in ``docs``, with its columns: the one with the least id.

    With a ``radius`` SimHash fingerprints (those of op7) that differ in so many bits or fewer link their texts too.

    Null and empty texts are copies of each other.  Rows are told apart by a number, so null and repeated ids do no
    harm: that of their file and place where ``docs`` are read from Parquet, else one given when they are written once."""
    spark = docs.sparkSession
    prepare(spark)
    columns = docs.columns
    marked = numbered(docs.select(*(F.col(c).alias(f"c{i}") for i, c in enumerate(columns))), docs, "marked")
    texts = marked.select("rid", F.col(f"c{columns.index(text_col)}").cast("string").alias("text"))
    of_id = F.col(f"c{columns.index(id_col)}").cast("long").alias("id")
    signs = marked.select("rid", F.col(f"c{columns.index(text_col)}").cast("string").alias("text"), of_id).mapInArrow(_signs(radius is not None), "rid long, none boolean, id long, sign binary, fp long")
    signs = written(signs, "signs")
    first = F.min(F.struct("none", "id", "rid"))
    classes = signs.groupBy("sign").agg(first.alias("first"), F.min("rid").alias("rid"))
    near = links(texts, small, chunk)
    if radius is not None:
        near = near.unionByName(print_links(signs, classes, radius))
    labels = connected_components(near)
    stay = classes.join(labels, F.col("rid") == F.col("node"), "left").groupBy(F.coalesce("label", "rid").alias("of")).agg(F.min("first").alias("first")).select(F.col("first.rid").alias("rid"))
    gone = written(signs.select("rid").join(stay, "rid", "left_anti"), "gone")
    removed(signs)
    return without(marked, gone).select(*(F.col(f"c{i}").alias(c) for i, c in enumerate(columns)))
