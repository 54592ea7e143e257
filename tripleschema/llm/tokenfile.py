"""Token files: canonical Huffman blocks with checkpoints, and flat blocks that are scanned for separators.

Compressed format.  A Parquet table of independent blocks (any reader of the store can open it, a lost task writes its
blocks again) and a table with the code length of each id.  A block holds consecutive whole documents:

    part, block      place of the block; blocks in this order hold documents in ascending id order
    doc_ids, lengths the documents and their numbers of ids
    first            ids of this part before the block
    bit_at           bit offset of each document, which starts at a whole byte, and
    marks            bit offset of every EVERY-th id within each document
    payload          the codes

Codes are canonical (by length, then id), so the lengths alone give them, and at most LONGEST bits long (more only for
more than 2**LONGEST ids), so a table of two to that power decodes one id in one step.  All checkpoints of a block are decoded side by side.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tripleschema.llm import bpe
from tripleschema.llm.common import SLICE_BYTES, delete, prepare, shared_dir, slices, used

LONGEST = 16  # bits of a code
EVERY = 128  # ids between checkpoints
BLOCK = 1 << 18  # ids in a block, unless one document has more
PART = 1 << 23  # ids in a part, about
PARTS = 100_000  # parts at most
KEPT = 500_000  # words that a worker remembers, some forty bytes each
FLAT = 1 << 15  # bytes of a flat block: readers hold some thousand rows at a time


# -- codes


def code_lengths(counts: dict[int, int], longest: int = LONGEST) -> dict[int, int]:
    """Optimal code lengths of at most ``longest`` bits (package-merge); with too many ids for that, of as many as they need."""
    items = sorted((n, i) for i, n in counts.items() if n > 0)
    longest = max(longest, (len(items) - 1).bit_length())
    if len(items) < 2:
        return {i: 1 for _, i in items}
    weight = np.array([n for n, _ in items], np.int64)
    # a row of weights for each bit; a package is a pair of the row before, and taking it takes both
    rows: list[tuple[np.ndarray, np.ndarray]] = []
    level = weight
    for _ in range(longest - 1):
        order = np.argsort(level, kind="stable")
        rows.append((order, level))
        sortd = level[order]
        pairs = sortd[: len(sortd) // 2 * 2].reshape(-1, 2).sum(axis=1)
        level = np.concatenate([weight, pairs])
    rows.append((np.argsort(level, kind="stable"), level))
    length = np.zeros(len(items), np.int64)
    take = 2 * len(items) - 2
    for order, _ in reversed(rows):
        chosen = order[:take]
        single = chosen[chosen < len(items)]
        length[single] += 1
        take = 2 * int((chosen >= len(items)).sum())
    return {i: int(n) for (_, i), n in zip(items, length, strict=True)}


class Code:
    """Tables of a canonical code."""

    def __init__(self, lengths: dict[int, int]):
        ids = np.array(sorted(lengths, key=lambda i: (lengths[i], i)), np.int64)
        size = np.array([lengths[i] for i in ids.tolist()], np.int64)
        self.longest = max([LONGEST, *lengths.values()])
        width = 1 << self.longest
        span = width >> size  # how many table entries start with the code
        start = np.cumsum(span) - span
        if len(ids) and start[-1] + span[-1] > width:
            raise ValueError("code lengths break the prefix rule")
        n = int(ids.max()) + 1 if len(ids) else 0
        self.bits, self.code = np.zeros(n, np.uint64), np.zeros(n, np.uint64)
        self.bits[ids], self.code[ids] = size, start >> (self.longest - size)
        self.id_at, self.bits_at = np.zeros(width, np.uint32), np.ones(width, np.int64)
        used = int(span.sum())
        self.id_at[:used], self.bits_at[:used] = np.repeat(ids, span), np.repeat(size, span)

    def encode(self, docs: list[np.ndarray]) -> tuple[bytes, np.ndarray, np.ndarray]:
        """Payload, bit offset of each document, bit offsets of all checkpoints in order."""
        count = np.array([len(d) for d in docs], np.int64)
        ids = np.concatenate(docs) if docs else np.zeros(0, np.int64)
        bits = self.bits[ids]
        end = np.cumsum(bits.astype(np.int64))
        doc_end = np.r_[0, end][np.cumsum(count)]
        doc_bits = np.diff(np.r_[0, doc_end])
        whole = -(-doc_bits // 8) * 8
        bit_at = np.cumsum(whole) - whole
        shift = bit_at - (doc_end - doc_bits)
        at = end - bits.astype(np.int64) + np.repeat(shift, count)
        n_words = int(whole.sum()) // 32 + 2
        words = np.zeros(n_words, np.uint64)
        if len(ids):
            word, offset = at >> 5, (at & 31).astype(np.uint64)
            spread = self.code[ids] << (np.uint64(64) - bits - offset)
            first = np.flatnonzero(np.r_[True, word[1:] != word[:-1]])
            words[word[first]] += np.add.reduceat(spread >> np.uint64(32), first)
            words[word[first] + 1] += np.add.reduceat(spread & np.uint64(0xFFFFFFFF), first)
        inside = np.arange(len(ids)) - np.repeat(np.cumsum(count) - count, count)
        return words.astype(">u4").tobytes()[: int(whole.sum()) // 8], bit_at, at[inside % EVERY == 0]

    def decode(self, payload: bytes, count: np.ndarray, marks: np.ndarray) -> np.ndarray:
        """All ids of a block: every checkpoint is a lane, all lanes step together."""
        words = np.frombuffer(payload + b"\0" * (-len(payload) % 4 + 8), ">u4").astype(np.uint64)
        pair = (words[:-1] << np.uint64(32)) | words[1:]
        lanes = -(-count // EVERY)
        last = np.cumsum(lanes) - 1
        n = np.full(len(marks), EVERY, np.int64)
        n[last[lanes > 0]] = (count - (lanes - 1) * EVERY)[lanes > 0]
        out = np.zeros((EVERY, len(marks)), np.uint32)
        order = np.argsort(-n, kind="stable")  # lanes that end early are at the end
        at, left = marks[order].astype(np.int64), n[order]
        top = np.uint64(64 - self.longest)
        for k in range(EVERY):
            live = int(np.searchsorted(-left, -k, "left"))
            if not live:
                break
            p = at[:live]
            key = ((pair[p >> 5] << (p & 31).astype(np.uint64)) >> top).astype(np.int64)
            out[k, :live] = self.id_at[key]
            at[:live] += self.bits_at[key]
        lane = np.empty((len(marks), EVERY), np.uint32)
        lane[order] = out.T
        return lane[np.arange(EVERY)[None, :] < n[:, None]]


@lru_cache(maxsize=2)
def _codes(lengths: tuple[tuple[int, int], ...]) -> Code:
    return Code(dict(lengths))


def _code(lengths: tuple[tuple[int, int], ...]) -> Code:
    used(_codes)
    return _codes(lengths)


# -- tokenising with the library


class ColumnTokeniser:
    """Ids of a column of texts, with the library run on new words only.

    In plain texts (Latin letters, no white space next to white space, no apostrophes) words start where the kind of
    character changes, except behind a space; so the words of a whole slice are found by comparing each byte's kind with
    the one before.  Arrow numbers the distinct words, the library encodes those not seen before, and the ids of all
    texts are one gather.  Other texts are encoded one by one."""

    #: Texts that are not plain.
    ODD = r"[^\x00-\x7f\x{c0}-\x{2af}]|[\x{d7}\x{f7}']|[\t-\r ][\t-\r ]"
    LETTER, NUMBER, OTHER, WHITE, SPACE = range(5)

    def __init__(self, path: str, width: int):
        self.words = bpe.library_encoder(path, width)
        self.width = width
        self.forget()
        self.kind = np.full(256, self.OTHER, np.int8)
        self.kind[[c for c in range(128) if chr(c).isalpha()]] = self.LETTER
        self.kind[128:] = self.LETTER  # in plain texts, all bytes beyond ASCII belong to letters
        self.kind[48:58] = self.NUMBER
        self.kind[9:14] = self.WHITE
        self.kind[32] = self.SPACE

    def forget(self) -> None:
        """What is kept: words, where their ids are in the pool, and how many."""
        self.kept = pa.array([], pa.string())
        self.start, self.size, self.pool = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, f"<u{self.width}")

    def places(self, found: pa.StringArray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(start, number) of the ids of each word in a pool of ids; new words are encoded and remembered."""
        at = pc.index_in(found, value_set=self.kept)
        fresh = found.filter(at.is_null())
        ids, count = self.words.encode_column(fresh)
        new = at.is_null().to_numpy(zero_copy_only=False)
        at = at.fill_null(0).to_numpy(zero_copy_only=False)
        start, size = np.empty(len(found), np.int64), np.empty(len(found), np.int64)
        start[~new], size[~new] = self.start[at[~new]], self.size[at[~new]]
        begin = len(self.pool) + np.cumsum(count) - count
        start[new], size[new] = begin, count
        pool = np.concatenate([self.pool, ids])
        brief = pc.less_equal(pc.binary_length(fresh), bpe.LONG)
        keep = brief.to_numpy(zero_copy_only=False)
        if len(self.kept) + len(fresh) > KEPT or len(pool) > 8 * KEPT:
            self.forget()  # and begin again with the words of now
        elif keep.all():
            self.kept, self.pool = pa.concat_arrays([self.kept, fresh]), pool
            self.start, self.size = np.r_[self.start, begin], np.r_[self.size, count]
        else:
            at = np.repeat(keep, count)
            self.kept, self.pool = pa.concat_arrays([self.kept, fresh.filter(brief)]), np.concatenate([self.pool, ids[at]])
            self.start, self.size = np.r_[self.start, len(pool) - len(ids) + np.cumsum(count[keep]) - count[keep]], np.r_[self.size, count[keep]]
        return start, size, pool

    def encode(self, texts: pa.Array, specials: bool, end: bytes = b"") -> pa.Array:
        """A binary column of packed ids, each with ``end`` behind it."""
        texts, n = pc.fill_null(texts, ""), len(texts)
        odd = pc.match_substring_regex(texts, self.ODD)
        for s in self.words.special if specials else ():
            odd = pc.or_(odd, pc.match_substring(texts, s))
        slow = np.flatnonzero(odd.to_numpy(zero_copy_only=False))
        plain = pc.if_else(odd, "", texts).cast(pa.large_string())
        edge = np.frombuffer(plain.buffers()[1], np.int64)[plain.offset : plain.offset + n + 1]
        low, high = (int(edge[0]), int(edge[-1])) if n else (0, 0)
        raw = plain.buffers()[2]
        kind = self.kind[np.frombuffer(raw, np.uint8)[low:high]] if high > low else np.zeros(0, np.int8)
        starts = kind >= self.WHITE
        starts[1:] |= (kind[1:] != kind[:-1]) & (kind[:-1] != self.SPACE)
        edge = edge - low
        starts[edge[:-1][edge[:-1] < high - low]] = True
        at = np.flatnonzero(starts)
        offsets = pa.py_buffer(np.r_[at, high - low].astype(np.int32))
        flat = pa.Array.from_buffers(pa.string(), len(at), [None, offsets, raw.slice(low, high - low) if raw else None]).dictionary_encode()
        found = flat.dictionary
        start, size, pool = self.places(found)
        further = [end, *(ids + end for ids in self.words.encode_texts([texts[i].as_py() for i in slow.tolist()], specials))]
        more = np.fromiter(map(len, further), np.int64, len(further)) // self.width
        start = np.r_[start, len(pool) + np.cumsum(more) - more].astype(np.int32)
        size = np.r_[size, more].astype(np.int32)
        pool = np.concatenate([pool, np.frombuffer(b"".join(further), pool.dtype)])
        last = np.full(n, len(found), np.int32)
        last[slow] = len(found) + 1 + np.arange(len(slow))
        where = np.searchsorted(at, edge[1:])
        index = np.insert(flat.indices.to_numpy(zero_copy_only=False), where, last)
        count = size[index]
        stop = np.cumsum(count, dtype=np.int32)
        gather = np.repeat(start[index] - (stop - count), count)
        gather += np.arange(len(gather), dtype=np.int32)
        ids = pool[gather]
        ends = stop[where + np.arange(n)].astype(np.int64) * self.width
        return pa.Array.from_buffers(pa.large_binary(), n, [None, pa.py_buffer(np.r_[0, ends].astype(np.int64)), pa.py_buffer(ids)])


_tokeniser = lru_cache(maxsize=2)(ColumnTokeniser)


def column_tokeniser(path: str, width: int) -> ColumnTokeniser:
    used(_tokeniser)
    used(bpe.library_encoder)
    return _tokeniser(path, width)


def _tokenise(path: str, end_id: int | None, width: int, specials: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = column_tokeniser(path, width)
        end = enc.words.pack([end_id]) if end_id is not None else b""
        for part in slices(batches, limit=2 * SLICE_BYTES):
            yield pa.RecordBatch.from_arrays([part.column(0), enc.encode(part.column(1), specials, end).cast(pa.binary())], ["doc_id", "ids"])

    return run


def id_width(tokenizer_path: str, *further: int | None) -> int:
    """Bytes that an id needs."""
    from tokenizers import Tokenizer

    top = max([Tokenizer.from_file(tokenizer_path).get_vocab_size(with_added_tokens=True) - 1, *(i for i in further if i is not None)])
    return 2 if top < 1 << 16 else 4


def tokenised(docs: DataFrame, tokenizer_path: str, end_id: int | None, width: int, id_col: str = "doc_id", text_col: str = "text", specials: bool = True) -> DataFrame:
    """``doc_id, ids`` of whole texts, packed in ``width`` bytes, with ``end_id`` at the end of each document."""
    prepare(docs.sparkSession)
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(_tokenise(tokenizer_path, end_id, width, specials), "doc_id long, ids binary")


def _count(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(0, np.int64)
        for batch in slices(batches, text=0):
            ids = np.frombuffer(b"".join(x for x in batch.column(0).to_pylist() if x), f"<u{width}")
            more = np.bincount(ids, minlength=len(total))
            more[: len(total)] += total
            total = more
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], ["id", "n"])

    return run


def global_counts(tokens: DataFrame, width: int) -> dict[int, int]:
    """Occurrences of each id in the whole corpus; there are no more ids than the vocabulary has."""
    each = tokens.select("ids").mapInArrow(_count(width), "id long, n long").groupBy("id").agg(F.sum("n").alias("n"))
    return {r.id: r.n for r in each.collect()}


# -- the compressed file


def _code_docs(code: tuple, width: int, bounds):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c, tops = _code(code), bounds.value
        for part in slices(batches, limit=1 << 20):  # the arrays of the coder take some fifty bytes for each of an id
            ids, n, coded, marks = [np.frombuffer(x, f"<u{width}") for x in part.column(1).to_pylist()], [], [], []
            payload, bit_at, mark = c.encode(ids)
            stop = [*(bit_at[1:] // 8).tolist(), len(payload)]
            lanes = np.cumsum([-(-len(d) // EVERY) for d in ids])
            for k, d in enumerate(ids):
                n.append(len(d))
                coded.append(payload[bit_at[k] // 8 : stop[k]])
                marks.append((mark[lanes[k] - -(-len(d) // EVERY) : lanes[k]] - bit_at[k]).astype("<u4").tobytes())
            number = [bisect_left(tops, (i is not None, i or 0, r)) for i, r in zip(part.column(0).to_pylist(), part.column(2).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(number, pa.int32()), part.column(0), part.column(2), pa.array(n, pa.int64()), pa.array(coded, pa.binary()), pa.array(marks, pa.binary())], ["part", "doc_id", "row", "n", "coded", "marks"])

    return run


_BLOCK = "part int, block int, first long, n_ids long, doc_ids array<long>, lengths array<long>, bit_at array<long>, marks binary, payload binary"


def _assemble(block: int):
    """Blocks from coded documents that are sorted by part and id; every part has all its documents in one task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, number, first = None, 0, 0
        doc_ids, lengths, coded, marks, bits = [], [], [], [], [0]

        def flush() -> pa.RecordBatch:
            nonlocal number, first
            total = sum(lengths)
            row = [part, number, first, total, list(doc_ids), list(lengths), bits[:-1], b"".join(marks), b"".join(coded)]
            number, first = number + 1, first + total
            for x in (doc_ids, lengths, coded, marks):
                x.clear()
            bits[:] = [0]
            kinds = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.binary(), pa.binary()]
            return pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip(row, kinds, strict=True)], [c.split()[0] for c in _BLOCK.split(", ")])

        size = 0
        for batch in batches:
            for p, i, n, c, m in zip(*(batch.column(k).to_pylist() for k in (0, 1, 3, 4, 5)), strict=True):
                if lengths and (p != part or size + n > block):
                    yield flush()
                    size = 0
                if p != part:
                    part, number, first = p, 0, 0
                size += n
                doc_ids.append(i)
                lengths.append(n)
                marks.append((np.frombuffer(m, "<u4").astype("<u8") + np.uint64(bits[-1])).tobytes())
                coded.append(c)
                bits.append(bits[-1] + 8 * len(c))
        if lengths:
            yield flush()

    return run


def write_tokens(docs: DataFrame, tokenizer_path: str, path: str, end_id: int | None = 2, id_col: str = "doc_id", text_col: str = "text", block: int = BLOCK) -> None:
    """Write the compressed token file of ``docs`` under ``path``: ``blocks`` and ``code``.

    The ids are made once and kept in the shared folder, counted, coded document by document, and only the coded
    documents are dealt out by ranges of doc_id and row (the ranges come from the ids alone, so nothing is coded twice,
    and rows that share an id or have none are dealt out too).  Null texts are empty; null ids come first; repeated ids
    stay in any order among themselves; an empty table gives a file without blocks."""
    spark = docs.sparkSession
    width = id_width(tokenizer_path, end_id)
    with_codec = tokenised(docs, tokenizer_path, end_id, width, id_col, text_col).withColumn("row", F.monotonically_increasing_id())
    at = f"{shared_dir(spark)}/{path.rstrip('/').rsplit('/', 1)[-1]}-ids"
    with_codec.write.option("compression", "zstd").parquet(at)
    tokens = spark.read.schema(with_codec.schema).parquet(at)
    counts = global_counts(tokens, width)
    code = tuple(sorted(code_lengths(counts).items()))
    total = sum(counts.values())
    parts = max(1, -(-total // max(PART, total // PARTS)))
    top = F.max(F.struct(F.col("doc_id").isNotNull().alias("known"), F.coalesce("doc_id", F.lit(0)).alias("doc_id"), "row")).alias("top")
    tops = tokens.select("doc_id", "row").repartitionByRange(parts, F.col("doc_id").asc_nulls_first(), "row").groupBy(F.spark_partition_id()).agg(top)
    bounds = spark.sparkContext.broadcast(sorted(tuple(r.top) for r in tops.collect())[:-1])  # one for each part
    coded = tokens.mapInArrow(_code_docs(code, width, bounds), "part int, doc_id long, row long, n long, coded binary, marks binary")
    placed = coded.repartition("part").sortWithinPartitions("part", F.col("doc_id").asc_nulls_first(), "row")
    placed.mapInArrow(_assemble(block), _BLOCK).write.option("compression", "uncompressed").parquet(f"{path}/blocks")
    spark.createDataFrame(list(code), "id long, bits int").coalesce(1).write.parquet(f"{path}/code")
    delete(spark, at)


def _read(code: tuple, from_col: int, with_ids: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = _code(code)
        for batch in batches:
            for row in (batch.slice(i, 1).to_pylist()[0] for i in range(batch.num_rows)):
                count = np.array(row["lengths"], np.int64)
                ids = c.decode(row["payload"], count, np.frombuffer(row["marks"], "<u8").astype(np.int64)).astype("<u4")
                stop = np.cumsum(count)
                raw = ids.tobytes()
                docs = [raw[4 * (b - n) : 4 * b] for n, b in zip(count.tolist(), stop.tolist(), strict=True)]
                cols = [pa.array([row["part"]] * len(docs), pa.int32()), pa.array(row["doc_ids"], pa.int64()), pa.array(row["first"] + stop - count), pa.array(count), pa.array([zlib.crc32(d) for d in docs], pa.int64())]
                names = ["part", "doc_id", "start", "n_tokens", "ids_crc32"]
                if with_ids:
                    cols.append(pa.array(docs, pa.binary()))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(cols, names)

    return run


def read_tokens(spark: SparkSession, path: str, with_ids: bool = False) -> DataFrame:
    """``doc_id, start, n_tokens, ids_crc32`` (and ``ids``) of each document, decoded from the file.

    ``start`` counts the ids of all documents before: those before in its part, and the sizes of the parts before,
    summed over a table with one row for each part."""
    prepare(spark)
    code = tuple(sorted((r.id, r.bits) for r in spark.read.schema("id long, bits int").parquet(f"{path}/code").collect()))
    blocks = spark.read.schema(_BLOCK).parquet(f"{path}/blocks")
    parts = blocks.groupBy("part").agg(F.sum("n_ids").alias("n"))
    before = {}
    total = 0
    for r in sorted(parts.collect()):  # one row for each written file
        before[r.part], total = total, total + r.n
    offset = spark.createDataFrame(list(before.items()), "part int, before long")
    read = blocks.select("part", "first", "doc_ids", "lengths", "marks", "payload").mapInArrow(_read(code, 0, with_ids), "part int, doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids binary" * with_ids)
    return read.join(F.broadcast(offset), "part").withColumn("start", F.col("start") + F.col("before")).drop("part", "before")


# -- flat files and the separator scan


def _flatten(path: str, end_id: int, width: int, block: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        enc = column_tokeniser(path, width)
        end, file = enc.words.pack([end_id]), TaskContext.get().partitionId()
        rest, number, doc = b"", 0, 0
        names = ["file", "block", "payload", "first", "doc_ids"]

        def row(payload: bytes | None, n: int, ids: list | None) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([file], pa.int32()), pa.array([n], pa.int32()), pa.array([payload], pa.binary()), pa.array([doc], pa.int64()), pa.array([ids], pa.list_(pa.int64()))], names)

        for part in slices(batches, limit=2 * SLICE_BYTES):
            coded = memoryview(enc.encode(part.column(1), False, end).buffers()[2])
            ids = part.column(0).to_pylist()
            yield row(None, -1, ids)
            doc += len(ids)
            cut = min(len(coded), block - len(rest)) if rest else 0
            rest += coded[:cut]
            if len(rest) == block:
                yield row(rest, number, None)
                number, rest = number + 1, b""
            while len(coded) - cut >= block:
                yield row(bytes(coded[cut : cut + block]), number, None)
                number, cut = number + 1, cut + block
            rest += coded[cut:]
        if rest:
            yield row(rest, number, None)

    return run


def write_flat(docs: DataFrame, tokenizer_path: str, path: str, end_id: int, id_col: str = "doc_id", text_col: str = "text", block_bytes: int = FLAT) -> int:
    """Write ``docs`` as flat streams of ids, one for each task, cut into blocks wherever a block is full: no index.

    Beside them stands the order of the documents in each stream.  Strings of special tokens are encoded as ordinary
    text, so ``end_id`` only ever ends a document.  Returns the bytes of an id."""
    prepare(docs.sparkSession)
    width = id_width(tokenizer_path, end_id)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    rows = rows.mapInArrow(_flatten(tokenizer_path, end_id, width, block_bytes), "file int, block int, payload binary, first long, doc_ids array<long>")
    rows.write.option("compression", "zstd").parquet(path)
    return width


def _separators(end_id: int, width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for file, block, payload in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True):
                ids = np.frombuffer(payload, f"<u{width}")
                at = np.flatnonzero(ids == end_id)
                inner = np.diff(at) - 1
                yield pa.RecordBatch.from_arrays(
                    [pa.array([v], t) for v, t in ((file, pa.int32()), (block, pa.int32()), (len(ids), pa.int64()), (len(at), pa.int64()), (int(at[0]) if len(at) else None, pa.int64()), (int(at[-1]) if len(at) else None, pa.int64()), (inner.tolist(), pa.list_(pa.int64())))],
                    ["file", "block", "n_ids", "n_ends", "first_end", "last_end", "inner"],
                )

    return run


def separator_scan(flat: DataFrame, end_id: int, width: int) -> DataFrame:
    """``file, nth, n_tokens`` of every document in flat blocks ``file, block, payload``, separators not counted.

    Each block is searched by itself.  A prefix scan over the blocks of a file then gives the place of each block, the
    number of separators before it and the place of the last one, which is where its first document began."""
    from pyspark.sql import Window

    prepare(flat.sparkSession)
    ends = flat.select("file", "block", "payload").mapInArrow(_separators(end_id, width), "file int, block int, n_ids long, n_ends long, first_end long, last_end long, inner array<long>")
    w = Window.partitionBy("file").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    ends = ends.withColumn("at", F.coalesce(F.sum("n_ids").over(w), F.lit(0)))
    ends = ends.withColumn("nth", F.coalesce(F.sum("n_ends").over(w), F.lit(0))).withColumn("open", F.coalesce(F.max(F.col("at") + F.col("last_end")).over(w) + 1, F.lit(0)))
    sizes = F.concat(F.array(F.col("at") + F.col("first_end") - F.col("open")), "inner")
    return ends.where("n_ends > 0").select("file", "nth", F.posexplode(sizes).alias("k", "n_tokens")).select("file", (F.col("nth") + F.col("k")).alias("nth"), "n_tokens")


def token_counts(docs: DataFrame, tokenizer_path: str, path: str, end_id: int, id_col: str = "doc_id", text_col: str = "text", block_bytes: int = FLAT) -> DataFrame:
    """``doc_id, file, nth, n_tokens`` of each row, counted by scanning the flat file that is written under ``path``.

    Null and empty texts have no tokens, null and repeated ids keep a row each, and an empty table gives no rows."""
    width = write_flat(docs, tokenizer_path, path, end_id, id_col, text_col, block_bytes)
    flat = docs.sparkSession.read.schema("file int, block int, payload binary, first long, doc_ids array<long>").parquet(path)
    order = flat.where("block < 0").select("file", "first", F.posexplode("doc_ids").alias("k", "doc_id")).select("file", (F.col("first") + F.col("k")).alias("nth"), "doc_id")
    return order.join(separator_scan(flat.where("block >= 0"), end_id, width), ["file", "nth"]).select("doc_id", "file", "nth", "n_tokens")
