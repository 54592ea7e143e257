"""Benchmark decontamination by the q-gram lemma.

A benchmark text of m characters that occurs in a document with at most e edits shares at least m + 1 - q(e + 1) of its
q-grams with it, on diagonals (place in the document minus place in the text) that differ by at most 2e.  Documents are
searched for the q-grams of all benchmark texts in one vectorised pass; shared ones are counted in overlapping bands of
diagonals; a band that meets the bound is verified by an alignment within it and within its document.  Nothing that the
bound keeps is dropped, so the result is exactly the occurrences within the edit budget, whatever stands beside a row.

Characters are letters and digits in lower case; all others are left out on both sides.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tripleschema.llm.common import prepare, slices, used

Q = 8
RATE = 0.1  # edits for each character of the benchmark text
BLOCK_CHARS = 8_000_000  # benchmark characters in the memory of a task; a larger benchmark is searched in blocks
FILTER_BITS = 22
EXPANDED = 4_000_000  # places of shared q-grams that are counted at a time
SLICE = 1 << 20  # bytes of text that are searched at a time: their letters, places and q-grams take some thirty times as much
_TURN = np.uint64(0x9E3779B97F4A7C15)
_GAP = 0x10FFFF  # stands between documents and in no text
_FAR = np.int32(1 << 20)


@lru_cache(maxsize=1)
def _alnum() -> np.ndarray:
    return np.array([chr(c).isalnum() for c in range(0x110000)])


def letters(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Code points of the letters and digits in lower case, and their places in the text."""
    low = text.lower()
    if len(low) != len(text):  # a few capitals have longer lower cases
        low = "".join(c.lower() if len(c.lower()) == 1 else c for c in text)
    points = np.frombuffer(low.encode("utf-32-le", "surrogatepass"), "<u4")
    at = np.flatnonzero(_alnum()[points])
    return points[at], at


def gram_hashes(points: np.ndarray, q: int = Q) -> np.ndarray:
    n = len(points) - q + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    wide = points.astype(np.uint64)
    h = wide[:n].copy()
    for j in range(1, q):
        h *= _TURN
        h += wide[j : j + n]
    return h * _TURN


def budget(m: int, q: int = Q, rate: float = RATE) -> int:
    """Edits allowed for a text of m characters: as many as leave one shared q-gram at least."""
    return max(0, min(int(rate * m), (m - q) // q))


class Index:
    """The q-grams of a block of benchmark texts."""

    def __init__(self, items: list[tuple[int, str]], q: int = Q, rate: float = RATE):
        self.q = q
        kept, self.short = [], {}  # short: items by their letters
        for i, t in items:
            p = letters(t or "")[0]
            if len(p) >= q:
                kept.append((i, p))
            elif len(p):
                self.short.setdefault(p.tobytes(), []).append(i)
        self.ids = [i for i, _ in kept]
        self.points = [p for _, p in kept]
        self.edits = np.array([budget(len(p), q, rate) for p in self.points], np.int64)
        self.need = np.array([len(p) + 1 - q * (e + 1) for p, e in zip(self.points, self.edits.tolist(), strict=True)], np.int64)
        grams = [gram_hashes(p, q) for p in self.points]
        h = np.concatenate(grams) if grams else np.zeros(0, np.uint64)
        item = np.repeat(np.arange(len(grams)), [len(g) for g in grams])
        place = np.concatenate([np.arange(len(g)) for g in grams]) if grams else np.zeros(0, np.int64)
        order = np.argsort(h, kind="stable")
        self.item, self.place = item[order], place[order]
        self.grams, first, self.n = np.unique(h[order], return_index=True, return_counts=True)
        self.first = first
        self.seen = np.zeros(1 << FILTER_BITS, bool)
        self.seen[self.grams >> np.uint64(64 - FILTER_BITS)] = True

    def regions(self, points: np.ndarray, start: np.ndarray) -> list[tuple[int, int, int]]:
        """(row, item, first diagonal of the band) that meet the bound of the lemma; rows begin at ``start`` in ``points``,
        and diagonals are counted within a row, so that what else is searched makes no difference."""
        h = gram_hashes(points, self.q)
        at = np.flatnonzero(self.seen[h >> np.uint64(64 - FILTER_BITS)])
        if not len(at) or not len(self.grams):
            return []
        k = np.minimum(np.searchsorted(self.grams, h[at]), len(self.grams) - 1)
        hit = self.grams[k] == h[at]
        at, k = at[hit], k[hit]
        row = np.searchsorted(start, at, "right") - 1
        longest = max(map(len, self.points))
        limit, items = int(np.diff(start).max()) + 2 * longest + 3, len(self.ids)
        keys, counts = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        cut = np.searchsorted(np.cumsum(self.n[k]), np.arange(0, int(self.n[k].sum()) + EXPANDED, EXPANDED))
        for i, j in zip(cut, [*cut[1:], len(k)], strict=True):  # a frequent q-gram stands for many places
            kk, n = k[i:j], self.n[k[i:j]]
            if not len(kk):
                continue
            entry = np.repeat(self.first[kk], n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            item = self.item[entry]
            diagonal = np.repeat(at[i:j] - start[row[i:j]], n) - self.place[entry] + longest  # not negative
            band = diagonal // (2 * self.edits[item] + 1) + 1
            key = (np.repeat(row[i:j], n) * items + item) * limit + band
            key, count = np.unique(np.concatenate([key, key - 1]), return_counts=True)
            keys.append(key)
            counts.append(count)
        key, of = np.unique(np.concatenate(keys), return_inverse=True)
        count = np.bincount(of, weights=np.concatenate(counts), minlength=len(key)).astype(np.int64)
        row, item, band = key // limit // items, key // limit % items, key % limit - 1
        good = count >= self.need[item]
        return list(zip(row[good].tolist(), item[good].tolist(), (band[good] * (2 * self.edits[item[good]] + 1) - longest).tolist(), strict=True))


def banded(pattern: np.ndarray, text: np.ndarray, lo: int, hi: int, most: int, free_start: bool) -> tuple[int, int] | None:
    """(edits, end in the text) of the best alignment of the whole pattern within diagonals ``lo`` to ``hi``."""
    width = hi - lo + 1
    j = np.arange(lo, hi + 1)
    ramp = np.arange(width, dtype=np.int32)
    padded = np.full(len(text) + len(pattern) + width + abs(lo) + 2, _GAP + 1, np.int64)
    shift = max(0, -lo)
    padded[shift : shift + len(text)] = text
    row = np.where((j >= 0) & (j <= len(text)), 0 if free_start else np.abs(j), _FAR).astype(np.int32)
    for i, c in enumerate(pattern.tolist()):
        step = row + (padded[lo + i + shift : lo + i + shift + width] != c)
        step[:-1] = np.minimum(step[:-1], row[1:] + 1)
        j = j + 1
        step[(j < 0) | (j > len(text))] = _FAR
        row = np.minimum.accumulate(step - ramp) + ramp
        if row.min() > most:
            return None
    row[(j < 0) | (j > len(text))] = _FAR
    b = int(row.argmin())
    return (int(row[b]), int(j[b])) if row[b] <= most else None


def occurrences(index: Index, texts: list[str | None]) -> list[tuple[int, int, int, int, int]]:
    """(row, item id, edits, start, stop) of all benchmark texts in the texts; places are code points of the row's text.

    An item is reported once for each region of a text; overlapping finds of one item give the best one.  An item with
    under q letters is found where it is all that a text has."""
    read = [letters(t or "") for t in texts]
    gap = np.array([_GAP], np.uint32)
    parts = [x for p, _ in read for x in (p, gap)]
    start = np.cumsum([0, *(len(p) + 1 for p, _ in read)])
    points = np.concatenate(parts) if parts else np.zeros(0, np.uint32)
    found: dict[tuple[int, int], set[tuple[int, int, int]]] = {}
    for row, item, diagonal in index.regions(points, start):
        pattern, e, text = index.points[item], int(index.edits[item]), read[row][0]
        wide = 2 * (2 * e + 1)
        a, b = max(0, diagonal - e), min(len(text), diagonal + wide + len(pattern) + e)
        got = banded(pattern, text[a:b], diagonal - e - a, diagonal + wide + e - a, e, True)
        if got is None:
            continue
        edits, end = got
        back = banded(pattern[::-1], text[a : a + end][::-1], -e, e, e, False)
        found.setdefault((row, item), set()).add((edits, a + end - (back[1] if back else len(pattern)), a + end))
    out = []
    for (row, item), finds in found.items():
        taken: list[tuple[int, int]] = []
        for edits, a, b in sorted(finds):
            if all(b <= x or y <= a for x, y in taken):
                taken.append((a, b))
                at = read[row][1]
                out.append((row, index.ids[item], edits, int(at[a]), int(at[b - 1]) + 1))
    for row, (p, at) in enumerate(read) if index.short else ():
        if 0 < len(p) < index.q:
            out += [(row, i, 0, int(at[0]), int(at[-1]) + 1) for i in index.short.get(p.tobytes(), ())]
    return sorted(out)


@lru_cache(maxsize=1)
def _index(items: tuple, q: int, rate: float) -> Index:
    return Index(list(items), q, rate)


def _search(blocks, q: int, rate: float, text_at: int, report: bool):
    """``report``: one row for each find; else the rows without any."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        used(_index)
        index = _index(blocks.value, q, rate)
        for part in slices(batches, text=text_at, limit=SLICE):
            found = occurrences(index, part.column(text_at).to_pylist())
            if report:
                ids = part.column(0).to_pylist()
                cols = [[ids[r] for r, *_ in found], *([x[k] for x in found] for k in range(1, 5))]
                kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32()]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], ["doc_id", "item_id", "n_edits", "start", "stop"])
            else:
                keep = np.ones(part.num_rows, bool)
                keep[[r for r, *_ in found]] = False
                yield part.filter(pa.array(keep))

    return run


def benchmark_blocks(benchmark: DataFrame, item_col: str = "item_id", text_col: str = "text", limit: int = BLOCK_CHARS) -> Iterator[tuple]:
    """The benchmark texts in blocks whose size is checked before they are collected."""
    rows = benchmark.select(F.col(item_col).cast("long").alias("item"), F.col(text_col).cast("string").alias("text")).where("text is not null").distinct()
    total = rows.agg(F.sum(F.length("text"))).first()[0] or 0
    n = -(-total // limit)
    for k in range(n):
        block = rows if n == 1 else rows.where(F.pmod(F.xxhash64("text"), F.lit(n)) == k)
        yield tuple(sorted((r.item, r.text) for r in block.collect()))


def contaminated(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", q: int = Q, rate: float = RATE, limit: int = BLOCK_CHARS) -> DataFrame:
    """One row for each benchmark text found in a document: ``doc_id, item_id, n_edits, start, stop``.

    A narrow pass over whole documents for each block of the benchmark.  Null and empty texts hold nothing; benchmark
    texts with under ``q`` letters and digits match only documents that have no other letters; equal benchmark texts under different
    ids are all reported; an empty benchmark or table gives no rows; extra columns are not read."""
    prepare(docs.sparkSession)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    schema = "doc_id long, item_id long, n_edits int, start int, stop int"
    out = None
    for block in benchmark_blocks(benchmark, limit=limit):
        part = rows.mapInArrow(_search(docs.sparkSession.sparkContext.broadcast(block), q, rate, 1, True), schema)
        out = part if out is None else out.unionByName(part)
    return out if out is not None else docs.sparkSession.createDataFrame([], schema)


def decontaminated(docs: DataFrame, benchmark: DataFrame, text_col: str = "text", q: int = Q, rate: float = RATE, limit: int = BLOCK_CHARS) -> DataFrame:
    """The rows of ``docs`` that hold no benchmark text, all columns as they were."""
    prepare(docs.sparkSession)
    for block in benchmark_blocks(benchmark, limit=limit):
        docs = docs.mapInArrow(_search(docs.sparkSession.sparkContext.broadcast(block), q, rate, docs.columns.index(text_col), False), docs.schema)
    return docs
