"""Intermediate tables that survive lost executors."""

from __future__ import annotations

import os
import re
import tempfile
import uuid
from collections.abc import Iterable
from pathlib import Path

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType


#: Rows of a table that the driver keeps, at most.
LOCAL_ROWS = 5_000

_ROOT = str(Path(__file__).resolve().parents[2])


def prepare(spark: SparkSession) -> None:
    """Let Python workers find this package where the driver found it (harmless if it is installed)."""
    env = spark.sparkContext.environment
    have = [p for p in (env.get("PYTHONPATH") or os.environ.get("PYTHONPATH", "")).split(os.pathsep) if p]
    if _ROOT not in have:
        env["PYTHONPATH"] = os.pathsep.join([_ROOT, *have])


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors see: ``spark.checkpoint.dir``.  A local master gets a temporary one where it is unset."""
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


def written(df: DataFrame, name: str, by: str | None = None) -> DataFrame:
    """``df`` written once and read back, in a folder for each value of ``by`` if given."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    (df.write.partitionBy(by) if by else df.write).parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.kept_at = path
    return out


def settled(df: DataFrame, name: str, most: int = LOCAL_ROWS) -> DataFrame:
    """``df`` computed once: kept on the driver if it has at most ``most`` rows, as rule sets and patterns mostly do, else
    written."""
    rows = df.limit(most + 1).toArrow()
    return df.sparkSession.createDataFrame(rows, df.schema) if rows.num_rows <= most else written(df, name)


def removed(*tables: DataFrame) -> None:
    """Delete written tables that nothing reads any more."""
    for t in tables:
        spark = t.sparkSession
        place = spark._jvm.org.apache.hadoop.fs.Path(t.kept_at)
        place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)


def local(spark: SparkSession, rows: Iterable[tuple], schema: str) -> DataFrame:
    """A small table from the driver, of which the planner knows the size (rule sets, patterns, fixtures)."""
    kind = to_arrow_schema(StructType.fromDDL(schema))
    rows = list(rows)
    columns = [pa.array([r[i] for r in rows], f.type) for i, f in enumerate(kind)]
    return spark.createDataFrame(pa.table(columns, schema=kind))
