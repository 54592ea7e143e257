"""Helpers that the training-data operators share."""

from __future__ import annotations

import ctypes
import gc
import os
import re
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from pathlib import Path

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from py4j.protocol import Py4JError
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that a Python worker holds as Python objects at a time.
SLICE_BYTES = 4 << 20
#: Rows of a key beyond which a join spreads it, and how many such keys there can be.
HOT_ROWS = 500_000
HOT_KEYS = 2_000
#: Bits of a membership bitmap at most (32 MB).
MOST_BITS = 1 << 28
#: Bytes of rows that Spark hands to a Python worker at a time: it holds each batch twice beside its heap, the worker once.
BATCH_BYTES = 4 << 20
#: Rows of a few numbers in a file of a table whose size is known.
FILE_ROWS = 500_000
#: Files whose rows are numbered by file and place, at most.
FILES = 200_000
#: Rows that go, up to which their numbers are broadcast.
DROPPED = 4_000_000

_LIBC = ctypes.CDLL(None)
_ROOT = str(Path(__file__).resolve().parents[2])


def prepare(spark: SparkSession) -> None:
    """Let Python workers find this package where the driver found it (harmless if it is installed), and hand them rows in
    batches of BATCH_BYTES where the session does not say otherwise."""
    env = spark.sparkContext.environment
    have = [p for p in (env.get("PYTHONPATH") or os.environ.get("PYTHONPATH", "")).split(os.pathsep) if p]
    if _ROOT not in have:
        env["PYTHONPATH"] = os.pathsep.join([_ROOT, *have])
    batch = "spark.sql.execution.arrow.maxBytesPerBatch"
    if spark.conf.get(batch, None) is None:
        spark.conf.set(batch, str(BATCH_BYTES))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors see: ``spark.checkpoint.dir``.  A local master gets a temporary one where it is unset."""
    conf = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if conf:
        return conf.rstrip("/")
    known = spark.sparkContext._jsc.sc().getCheckpointDir()
    if known.isDefined():
        return known.get().rstrip("/")
    if not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    own = f"file://{tempfile.mkdtemp(prefix='tripleschema-')}"
    spark.sparkContext.setCheckpointDir(own)
    return own


_made: list[str] = []  # folders of written tables, in order


@contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """Delete at the end what was written meanwhile by ``written``; results must have been written by then."""
    start = len(_made)
    yield
    for path in _made[start:]:
        delete(spark, path)
    del _made[start:]


def written(df: DataFrame, name: str, rows: int | None = None) -> DataFrame:
    """``df`` written once to the shared folder and read back: cuts the lineage, survives lost executors.

    If it is known to have at most ``rows`` rows of a few numbers, it is written in as few files as they need."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    (df if rows is None else df.coalesce(rows // FILE_ROWS + 1)).write.parquet(path)
    _made.append(path)
    relieve(spark)
    out = spark.read.schema(df.schema).parquet(path)
    out.kept_at = path
    return out


def delete(spark: SparkSession, path: str) -> None:
    place = spark._jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)


def removed(*tables: DataFrame) -> None:
    """Delete written tables that nothing reads any more."""
    for t in tables:
        delete(t.sparkSession, t.kept_at)


_turn = 0  # tasks that this worker has begun
_uses: dict = {}  # cached function -> the task that last used it


def used(cached) -> None:
    """Note that the task uses what a function with a cache holds (an encoder, an index).  Workers live on for stages of
    other kinds: what only earlier tasks have used goes before something new is made, and when a task begins without it."""
    new = cached not in _uses
    _uses[cached] = _turn
    if new and _drop(_turn):
        give_back()


def _drop(since: int) -> bool:
    """Whether something was held that no task since that one has used."""
    idle = [cached for cached, last in _uses.items() if last < since]
    for cached in idle:
        cached.cache_clear()
        del _uses[cached]
    return bool(idle)


def _begin() -> None:
    """A task reads its first rows; what it needs from the start it has noted by ``used``."""
    global _turn
    if _drop(_turn):
        gc.collect()
        give_back()
    _turn += 1


def give_back() -> None:
    """Return memory that Arrow and the C library hold but do not use, as a worker's memory counts against its executor."""
    pa.default_memory_pool().release_unused()
    if hasattr(_LIBC, "malloc_trim"):
        _LIBC.malloc_trim(0)


def slices(batches: Iterator[pa.RecordBatch], text: int = 1, limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut batches into runs of rows of at most ``limit`` bytes of column ``text`` (one row at least).

    After each run the worker gives back what it does not need."""
    _begin()
    for batch in batches:
        col = batch.column(text)
        size = pc.fill_null(pc.binary_length(col), 0).to_pylist()
        start = total = 0
        for i, n in enumerate(size):
            if total + n > limit and i > start:
                yield batch.slice(start, i - start)
                give_back()
                start, total = i, 0
            total += n
        if start < batch.num_rows:
            yield batch.slice(start)
            give_back()


def relieve(spark: SparkSession, collect: bool = False) -> str:
    """Return memory that the driver holds but does not use: its Python's, what the C library keeps for its JVM (compilers,
    buffers), and with ``collect`` what the heap has grown by.  Gives what the JVM says; nothing where it is none that can."""
    give_back()
    jvm = spark._jvm
    if collect:
        jvm.java.lang.System.gc()
    try:
        server = jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer()
        invoke = next(m for m in jvm.java.lang.Class.forName("javax.management.MBeanServer").getMethods() if m.getName() == "invoke")
        given = spark.sparkContext._gateway.new_array(jvm.java.lang.Object, 4)
        given[0], given[1] = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap"
        return str(invoke.invoke(server, given))
    except Py4JError:  # another JVM, or one before 17.0.9
        return ""


# -- joins whose keys may be hot


def spread_join(left: DataFrame, right: DataFrame, keys: list[str], n: str, hot_rows: int = HOT_ROWS) -> DataFrame:
    """Inner join with a written table that has each key once and in ``n`` the rows that ``left`` has of it.

    Keys with over ``hot_rows`` rows (and over a HOT_KEYS-th of all) are joined where their rows are: there are under
    HOT_KEYS of them, so that side is broadcast.  All others are shuffled.  ``n`` is not returned."""
    top, total = right.agg(F.max(n), F.sum(n)).first()
    bound = max(hot_rows, (total or 0) // HOT_KEYS)
    if (top or 0) <= bound:
        return left.join(right.drop(n), keys)
    hot = F.broadcast(right.where(F.col(n) > bound))
    cold = left.join(hot.select(keys), keys, "left_anti").join(right.where(F.col(n) <= bound).drop(n), keys)
    return left.join(hot.drop(n), keys).unionByName(cold)


# -- membership


def hash_longs(values: np.ndarray) -> np.ndarray:
    """What the SQL function xxhash64 gives for longs, as unsigned numbers."""
    u = np.uint64
    p1, p2, p3, p4, p5 = u(0x9E3779B185EBCA87), u(0xC2B2AE3D27D4EB4F), u(0x165667B19E3779F9), u(0x85EBCA77C2B2AE63), u(0x27D4EB2F165667C5)
    turn = lambda x, k: (x << u(k)) | (x >> u(64 - k))
    with np.errstate(over="ignore"):
        h = (u(42) + p5 + u(8)) ^ (turn(values.astype(np.int64).view(u) * p2, 31) * p1)
        h = turn(h, 27) * p1 + p4
        h = (h ^ (h >> u(33))) * p2
        h = (h ^ (h >> u(29))) * p3
        return h ^ (h >> u(32))


def member_bits(keys: DataFrame, n: int, most: int = MOST_BITS) -> np.ndarray | None:
    """A bitmap that has a bit set for each of the ``n`` longs in the only column of ``keys``, sixteen bits for each at least.

    Built by aggregation and at most ``most`` bits long; None if the keys need more."""
    if 16 * n > most:
        return None
    bits = max(1 << 15, 1 << (16 * n).bit_length())
    at = F.xxhash64(F.col(keys.columns[0]).cast("long")).bitwiseAND(bits - 1) + 1
    rows = keys.select(at.alias("at")).groupBy(F.bitmap_bucket_number("at").alias("part")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("at")).alias("bits")).collect()
    out = np.zeros(bits // 8, np.uint8)
    for r in rows:
        out[(r.part - 1) * 4096 : r.part * 4096] = np.frombuffer(bytes(r.bits), np.uint8)[: len(out)]
    return out


def may_be_in(bits: np.ndarray, values: np.ndarray) -> np.ndarray:
    """Which of the values may be members: all members, and few others."""
    at = (hash_longs(values) & np.uint64(8 * len(bits) - 1)).astype(np.int64)
    return (bits[at >> 3] >> (at & 7).astype(np.uint8) & 1).astype(bool)


def only_members(rows: DataFrame, keys: DataFrame, most: int = DROPPED) -> DataFrame:
    """``rows`` less most of those whose first column, a long, is not in the only column of ``keys``, a written table of
    distinct ones: told where the rows are, by the keys themselves up to ``most``, beyond that by a bitmap of checked
    size.  Where that would be too large all rows stay; a join has to decide in any case."""
    n, name = keys.count(), rows.columns[0]
    if n <= most:
        return rows.join(F.broadcast(keys.toDF(name)), name, "left_semi").select(*rows.columns)
    bits = member_bits(keys, n)
    if bits is None:
        return rows
    bits = rows.sparkSession.sparkContext.broadcast(bits)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array(may_be_in(bits.value, batch.column(0).to_numpy(zero_copy_only=False))))

    return rows.mapInArrow(run, rows.schema)


# -- row numbers


def without(rows: DataFrame, gone: DataFrame) -> DataFrame:
    """``rows`` less those whose ``rid`` is in the written table ``gone``, which is broadcast up to DROPPED rows."""
    return rows.join(F.broadcast(gone) if gone.count() <= DROPPED else gone, "rid", "left_anti")


def numbered(rows: DataFrame, of: DataFrame, name: str) -> DataFrame:
    """``rows``, a projection of ``of``, with a number ``rid`` for each row that is the same in every reading.

    It is the file and the place in it where ``of`` is read from Parquet files, else one given when the rows are written
    once."""
    spark, files = of.sparkSession, None
    if "_metadata#" in of._jdf.queryExecution().analyzed().metadataOutput().mkString(" ") and not any(c.lower() == "_metadata" for c in of.columns):
        try:
            at = rows.select("*", F.col("_metadata.file_path").alias("__file"), F.col("_metadata.row_index").alias("__row"))
            files = of.select(F.col("_metadata.file_path").alias("f")).distinct().limit(FILES + 1).collect()
        except AnalysisException:  # files of another kind
            pass
    if files is None or len(files) > FILES:
        return written(rows.withColumn("rid", F.monotonically_increasing_id()), name)
    files = sorted(r[0] for r in files)
    number = spark.createDataFrame(pa.table({"__file": pa.array(files, pa.string()), "__number": pa.array(range(len(files)), pa.int64())}))  # rows of Python objects would start further workers
    return at.join(F.broadcast(number), "__file").withColumn("rid", F.shiftleft("__number", 40).bitwiseOR(F.col("__row"))).drop("__file", "__row", "__number")
