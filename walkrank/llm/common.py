"""Helpers shared by the text operators: row mapping over Arrow batches and the shared work folder."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType, _parse_datatype_string

from ..config import importable

#: Rows handled at once inside an Arrow batch; it bounds the Python objects alive in a worker.
SLICE_ROWS = 256


def work_dir(spark: SparkSession) -> str:
    """The folder that all executors share: spark.checkpoint.dir, or a temporary one where it is unset and all run here (tests)."""
    conf = spark.sparkContext.getConf()
    top = spark.conf.get("spark.checkpoint.dir", None) or conf.get("spark.checkpoint.dir", None)
    if not top:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        top = getattr(spark.sparkContext, "_walkrank_tmp", None) or "file://" + tempfile.mkdtemp(prefix="walkrank-")
        spark.sparkContext._walkrank_tmp = top
    return f"{top}/walkrank"


#: Paths of the tables written inside each open `scratch`.
_open: list[list[str]] = []


def written(df: DataFrame, name: str, by: str | None = None) -> DataFrame:
    """df as a table written to the shared folder and read again: lineage ends, and a lost executor costs nothing. by: a
    column that has a folder for each value."""
    path = f"{work_dir(importable(df.sparkSession))}/{name}-{uuid.uuid4().hex}"
    (df.write.partitionBy(by) if by else df.write).parquet(path)
    if _open:
        _open[-1].append(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._walkrank_path = path
    return out


def deleted(spark: SparkSession, path: str) -> None:
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def discard(*tables: DataFrame) -> None:
    """Deletes tables made by `written` that nothing will read again."""
    for df in tables:
        deleted(df.sparkSession, df._walkrank_path)


@contextmanager
def scratch(spark: SparkSession):
    """Deletes at its end what operators have written inside, but for tables given to `keep`: for results that have been
    computed by then."""
    _open.append([])
    try:
        yield
    finally:
        for path in _open.pop():
            deleted(spark, path)


def keep(df: DataFrame) -> DataFrame:
    """A table made by `written`, which the scratch that is open leaves to the one around it."""
    inner = _open[-1]
    inner.remove(df._walkrank_path)
    if len(_open) > 1:
        _open[-2].append(df._walkrank_path)
    return df


def clear(spark: SparkSession) -> None:
    """Deletes all tables that operators have written to the shared folder; results not yet read are lost."""
    deleted(spark, work_dir(spark))


def arrow_schema(ddl: str) -> tuple[StructType, pa.Schema]:
    kind = _parse_datatype_string(ddl)
    return kind, to_arrow_schema(kind)


def map_rows(df: DataFrame, setup: Callable[[], Callable], ddl: str) -> DataFrame:
    """One output row (a tuple in the order of ddl) for each row of df. setup runs once in each task."""
    importable(df.sparkSession)
    kind, schema = arrow_schema(ddl)

    def run(batches):
        one = setup()
        for batch in batches:
            for at in range(0, batch.num_rows, SLICE_ROWS):
                part = batch.slice(at, SLICE_ROWS)
                out = [one(*row) for row in zip(*(c.to_pylist() for c in part.columns), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True), schema, strict=True)], schema=schema)

    return df.mapInArrow(run, kind)


def flat_map_rows(df: DataFrame, setup: Callable[[], Callable], ddl: str, most: int = 20_000) -> DataFrame:
    """Any number of output rows for each row of df: what setup() returns yields tuples. Batches hold about `most` rows."""
    importable(df.sparkSession)
    kind, schema = arrow_schema(ddl)

    def pack(out):
        return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True), schema, strict=True)], schema=schema)

    def run(batches):
        many, out = setup(), []
        for batch in batches:
            for at in range(0, batch.num_rows, SLICE_ROWS):
                part = batch.slice(at, SLICE_ROWS)
                for row in zip(*(c.to_pylist() for c in part.columns), strict=True):
                    for x in many(*row):
                        out.append(x)
                        if len(out) >= most:
                            yield pack(out)
                            out = []
        if out:
            yield pack(out)

    return df.mapInArrow(run, kind)


def documents(spark: SparkSession, sf_dir: str, table: str = "documents") -> DataFrame:
    return importable(spark).read.parquet(f"{sf_dir}/{table}.parquet")


def text_of(column: str = "text") -> Column:
    return F.coalesce(F.col(column), F.lit(""))
