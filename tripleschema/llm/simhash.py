"""SimHash near-duplicates, compared in bit slices.

Fingerprints are linked if they differ in at most three bits.  Cut into five bands, two such fingerprints agree in two
whole bands at least, so each distinct fingerprint is put into ten buckets of two bands each, and comparing within
buckets finds every link.  A bucket stores its fingerprints as 64 bit planes; one pass over the planes updates 64
distances per machine word in carry-save counters, and a block of lanes is left as soon as all of them are too far.
Buckets over CHUNK fingerprints are cut into chunks that are compared pair by pair in tasks of their own.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations, repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tripleschema.llm.common import prepare, removed, slices, spread_join, written
from tripleschema.llm.components import connected_components

BANDS = ((0, 13), (13, 13), (26, 13), (39, 13), (52, 12))  # first bit and width
RADIUS = 3
CHUNK = 2048
SMALL = 48  # buckets up to this size are compared together, pair by pair
LANES = 1 << 17  # pairs compared at a time
WIDE = 256  # bits of a wide fingerprint
FULL = np.uint64(0xFFFFFFFFFFFFFFFF)


# -- fingerprints


def fingerprint(text: str | None, shingle: int = 3, seed: int = 42) -> int:
    """Majority of the bits of the hashes of all word shingles (ASCII lower case); 0 without words."""
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    grams = [b" ".join(words)] if len(words) < shingle else map(b" ".join, zip(*(words[i:] for i in range(shingle)), strict=False))
    h = np.fromiter(map(xxhash.xxh64_intdigest, grams, repeat(seed)), dtype=">u8")
    count = np.zeros(64, np.int64)
    for i in range(0, len(h), 1 << 16):
        part = h[i : i + (1 << 16)]
        count += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int32)
    return int.from_bytes(np.packbits(2 * count > len(h)).tobytes(), "big")


def _fingerprints(shingle: int, seed: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches):
            fp = np.array([fingerprint(t, shingle, seed) for t in part.column(1).to_pylist()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(fp)], ["doc_id", "fp"])

    return run


def _with_fingerprints(text_at: int, shingle: int = 3, seed: int = 42):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, text=text_at):
            fp = np.array([fingerprint(t, shingle, seed) for t in part.column(text_at).to_pylist()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([*part.columns, pa.array(fp)], [*part.schema.names, "fp"])

    return run


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3, seed: int = 42) -> DataFrame:
    """``doc_id, fp`` (the 64 bits as a signed long) of whole texts, one row for each row; null texts have no words."""
    prepare(docs.sparkSession)
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(_fingerprints(shingle, seed), "doc_id long, fp long")


# -- comparison


def bit_planes(values: np.ndarray) -> np.ndarray:
    """64 rows, one for each bit; lane i of a row is that bit of value i, padded to whole words."""
    bits = np.unpackbits(np.ascontiguousarray(values, ">u8").view(np.uint8).reshape(-1, 8), axis=1)
    packed = np.packbits(bits.T, axis=1)
    out = np.zeros((64, -(-packed.shape[1] // 8) * 8), np.uint8)
    out[:, : packed.shape[1]] = packed
    return out.view(np.uint64)


def near_lanes(differ, shape: tuple[int, ...], radius: int = RADIUS, planes: int = 64) -> np.ndarray:
    """Words with a one in each lane whose count over the planes ``differ(k)`` is at most ``radius``.

    The count is kept in bit-sliced digits and a sticky overflow.  The planes are left once all lanes are beyond."""
    digits = [np.zeros(shape, np.uint64) for _ in range(max(1, radius.bit_length()))]
    over = np.zeros(shape, np.uint64)

    def far() -> np.ndarray:
        more, same = over, np.full(shape, FULL)
        for i in range(len(digits) - 1, -1, -1):
            if radius >> i & 1:
                same = same & digits[i]
            else:
                more, same = more | same & digits[i], same & ~digits[i]
        return more

    for k in range(planes):
        carry = differ(k)
        for i, digit in enumerate(digits):
            digits[i], carry = digit ^ carry, digit & carry
        over |= carry
        if k % 8 == 7 and k >= radius and (far() == FULL).all():
            return np.zeros(shape, np.uint64)
    return ~far()


def wide_fingerprint(hashes: np.ndarray) -> np.ndarray:
    """Majority bits of a set of 64-bit hashes in WIDE bits, as bytes: more bits tell middling similarities apart."""
    out = np.zeros(WIDE // 8, np.uint8)
    for j in range(WIDE // 64):
        x = (hashes ^ np.uint64(0xD6E8FEB86659FD93 * (j + 1) % (1 << 64))) * np.uint64(0x9E3779B97F4A7C15)
        x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
        x ^= x >> np.uint64(32)
        count = np.zeros(64, np.int64)
        for i in range(0, len(x), 1 << 16):
            part = x[i : i + (1 << 16)]
            count += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int32)
        out[8 * j : 8 * j + 8] = np.packbits(2 * count > len(x))
    return out


def wide_planes(prints: np.ndarray) -> np.ndarray:
    """WIDE rows of lanes, one lane for each of the fingerprints (rows of bytes)."""
    packed = np.packbits(np.unpackbits(prints, axis=1).T, axis=1)
    out = np.zeros((WIDE, -(-packed.shape[1] // 8) * 8), np.uint8)
    out[:, : packed.shape[1]] = packed
    return out.view(np.uint64)


def near_wide(planes: np.ndarray, asks: np.ndarray, n: int, radius: int) -> np.ndarray:
    """For each fingerprint of ``asks``, which of the n lanes differ from it in at most ``radius`` bits."""
    flip = np.unpackbits(asks, axis=1).T.astype(np.uint64) * FULL
    return _lanes(near_lanes(lambda k: planes[k][None, :] ^ flip[k][:, None], (len(asks), planes.shape[1]), radius, WIDE), n)


def _lanes(words: np.ndarray, n: int) -> np.ndarray:
    return np.unpackbits(words.view(np.uint8), axis=-1)[..., :n].astype(bool)


def near_pairs(left: np.ndarray, right: np.ndarray, radius: int = RADIUS, block: int = 64) -> np.ndarray:
    """Which of the pairs (left[i], right[i]) are within the radius; blocks of ``block`` words stop early."""
    out = np.zeros(len(left), bool)
    for i in range(0, len(left), LANES):
        planes = bit_planes(left[i : i + LANES] ^ right[i : i + LANES])
        for w in range(0, planes.shape[1], block):
            part = planes[:, w : w + block]
            a = i + w * 64
            b = min(len(left), a + part.shape[1] * 64)
            out[a:b] = _lanes(near_lanes(lambda k, p=part: p[k], part.shape[1:], radius), b - a)
    return out


class Forest:
    """Union-find over the fingerprints of a batch."""

    def __init__(self):
        self.up: dict[int, int] = {}

    def root(self, x: int) -> int:
        up = self.up
        while (p := up.get(x, x)) != x:
            up[x] = x = up.get(p, p)
        return x

    def link(self, a: int, b: int) -> bool:
        """Whether this joined two trees."""
        a, b = self.root(a), self.root(b)
        if a == b:
            return False
        self.up[max(a, b)] = min(a, b)
        return True


def _big(fp: np.ndarray, side: np.ndarray, crossed: bool, radius: int) -> Iterator[tuple[int, int]]:
    """Links of one large bucket: its planes against its fingerprints, in blocks of queries."""
    lanes = np.flatnonzero(side == 0) if crossed else np.arange(len(fp))
    asks = np.flatnonzero(side == 1) if crossed else lanes
    if not len(lanes) or not len(asks):
        return
    planes, tree = bit_planes(fp[lanes]), np.arange(len(fp))  # tree: a member that stands for each row's tree
    for i in range(0, len(asks), 128):
        q = asks[i : i + 128]
        flip = np.unpackbits(bit_planes(fp[q]).view(np.uint8), axis=1)[:, : len(q)].astype(np.uint64) * FULL
        near = near_lanes(lambda k, f=flip: planes[k][None, :] ^ f[k][:, None], (len(q), planes.shape[1]), radius)
        for row, hits in zip(q, _lanes(near, len(lanes)), strict=True):
            met = lanes[hits]
            met = met[tree[met] != tree[row]]
            for other, at in zip(*np.unique(tree[met], return_index=True), strict=True):
                yield int(fp[row]), int(fp[met[at]])
                tree[tree == other] = tree[row]


def _compare(radius: int):
    def links(t: np.ndarray, fp: np.ndarray, side: np.ndarray, crossed: np.ndarray) -> list[tuple[int, int]]:
        """t: number of the run of each row, rising."""
        starts = np.flatnonzero(np.r_[True, t[1:] != t[:-1]])
        size = np.diff(np.r_[starts, len(t)])
        forest, out = Forest(), []
        for s, n in zip(starts[size > SMALL], size[size > SMALL], strict=True):
            out += _big(fp[s : s + n], side[s : s + n], bool(crossed[s]), radius)
        small = np.repeat(size <= SMALL, size)
        for lag in range(1, SMALL):
            i = np.flatnonzero(small[:-lag] & (t[:-lag] == t[lag:])) if lag < len(t) else np.empty(0, np.int64)
            if not len(i):
                break
            i = i[~crossed[i] | (side[i] != side[i + lag])]
            i = i[near_pairs(fp[i], fp[i + lag], radius)]
            out += [(a, b) for a, b in zip(fp[i].tolist(), fp[i + lag].tolist(), strict=True) if forest.link(a, b)]
        return out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        rows = 0

        def flush(whole: bool) -> Iterator[pa.RecordBatch]:
            nonlocal held, rows
            cols = [np.concatenate(c) for c in zip(*held, strict=True)]
            change = np.r_[True, (cols[0][1:] != cols[0][:-1]) | (cols[1][1:] != cols[1][:-1]) | (cols[2][1:] != cols[2][:-1])]
            cut = len(change) if whole else int(np.flatnonzero(change)[-1])  # the last run may go on
            held, rows = [tuple(c[cut:] for c in cols)], len(change) - cut
            if cut:
                found = links(np.cumsum(change[:cut]), cols[3][:cut].view(np.uint64), cols[4][:cut], cols[5][:cut].astype(bool))
                a, b = (np.array([x[k] for x in found], np.uint64).view(np.int64) for k in (0, 1))
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["a", "b"])

        for batch in batches:
            if batch.num_rows:
                held.append(tuple(batch.column(k).to_numpy(zero_copy_only=False) for k in range(6)))
                rows += batch.num_rows
                if rows >= 1 << 16:
                    yield from flush(False)
        if rows:
            yield from flush(True)

    return run


def linked(distinct: DataFrame, radius: int = RADIUS, chunk: int = CHUNK) -> DataFrame:
    """Links ``(a, b)`` that connect all of the distinct fingerprints ``fp`` which differ in 1 to ``radius`` bits.

    Each bucket gives the links of a spanning forest, never all its pairs: a path of links joins any two near ones."""
    prepare(distinct.sparkSession)
    if not 0 <= radius <= 3:
        raise ValueError("the radius is 0 to 3")
    part = [F.shiftrightunsigned("fp", 64 - first - width).bitwiseAND((1 << width) - 1) for first, width in BANDS]
    keys = F.array(*(F.struct(F.lit(t).alias("t"), F.shiftleft(part[i], 13).bitwiseOR(part[j]).alias("key")) for t, (i, j) in enumerate(combinations(range(len(BANDS)), 2))))
    keyed = distinct.select("fp", F.explode(keys).alias("k")).select("k.t", "k.key", "fp")
    shared = keyed.groupBy("t", "key").agg(F.count("*").alias("n")).where("n > 1").withColumn("c", F.ceil(F.col("n") / chunk).cast("int"))
    own = F.pmod(F.xxhash64("fp"), F.col("c")).cast("int")
    placed = keyed.join(shared, ["t", "key"]).withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("c") - 1)))
    placed = placed.select("t", "key", (F.least("own", "other") * F.col("c") + F.greatest("own", "other")).cast("long").alias("block"), "fp", (F.col("own") > F.col("other")).cast("int").alias("side"), (F.col("own") != F.col("other")).cast("int").alias("crossed"))
    run = _compare(radius)
    return placed.repartition("t", "key", "block").sortWithinPartitions("t", "key", "block", "fp").mapInArrow(run, "a long, b long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = RADIUS) -> DataFrame:
    """One row per row of ``docs``: ``doc_id, fp, component_id``, the least doc_id that links lead to (itself included).

    Null and empty texts have the fingerprint zero and are linked like others.  Rows without an id belong to the
    component of their fingerprint (null if nothing in it has an id) and links through them count.  Repeated rows stay.
    Equal fingerprints are one node, so a large group of copies costs one comparison.  An empty table gives no rows.
    """
    marks = written(fingerprints(docs, id_col, text_col), "fingerprints")
    classes = written(marks.groupBy("fp").agg(F.min("doc_id").alias("least_id"), F.count("*").alias("n")), "classes")
    labels = connected_components(linked(classes, radius))
    of = classes.join(labels, F.col("fp") == F.col("node"), "left").select("fp", "least_id", "n", F.coalesce("label", "fp").alias("label"))
    least = of.groupBy("label").agg(F.min("least_id").alias("component_id"))
    named = written(of.join(least, "label").select("fp", "component_id", "n"), "components")
    removed(classes)
    return spread_join(marks, named, ["fp"], "n").select("doc_id", "fp", "component_id")


def representatives(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = RADIUS) -> DataFrame:
    """One row of each component of ``docs``, with its columns: the one with the least id.

    Only fingerprints and ids are grouped.  Each fingerprint's component names one row by a number given when the
    documents and fingerprints are written once side by side, so null and repeated ids do no harm; the text itself is
    filtered where it is, by a join on the numbers of the rows that stay."""
    prepare(docs.sparkSession)
    columns = docs.columns
    rows = docs.select(*(F.col(c).alias(f"c{i}") for i, c in enumerate(columns)))
    at = columns.index(text_col)
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in rows.schema) + ", fp long"
    marked = written(rows.mapInArrow(_with_fingerprints(at), schema).withColumn("rid", F.monotonically_increasing_id()), "marked")
    of_id = F.col(f"c{columns.index(id_col)}")
    slim = marked.select("fp", "rid", of_id.cast("long").alias("id"))
    first = F.min(F.struct(F.col("id").isNull().alias("none"), "id", "rid"))
    classes = written(slim.groupBy("fp").agg(first.alias("first")), "classes")
    labels = connected_components(linked(classes, radius))
    stay = classes.join(labels, F.col("fp") == F.col("node"), "left").groupBy(F.coalesce("label", "fp").alias("label")).agg(F.min("first").alias("first")).select(F.col("first.rid").alias("rid"))
    kept = marked.join(stay, "rid", "left_semi")
    return kept.select(*(F.col(f"c{i}").alias(c) for i, c in enumerate(columns)))
