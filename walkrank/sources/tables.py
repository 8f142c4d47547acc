"""Reading tables and edge lists. Columns are named, so scans are pruned."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StringType, StructField, StructType, TimestampType

from ..config import importable

EDGE = StructType([StructField("src", LongType()), StructField("dst", LongType())])
MUTATION = StructType([StructField("src", LongType()), StructField("dst", LongType()), StructField("op", StringType()), StructField("ts", TimestampType()), StructField("seq", LongType())])


def table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    rows = importable(spark).read.parquet(f"{sf_dir}/{name}.parquet")
    return rows.select(*columns) if columns else rows


def edges_parquet(spark: SparkSession, path: str, src: str = "src", dst: str = "dst") -> DataFrame:
    return spark.read.parquet(path).select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst"))


def edges_orc(spark: SparkSession, path: str, src: str = "src", dst: str = "dst") -> DataFrame:
    return spark.read.orc(path).select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst"))


def edges_csv(spark: SparkSession, path: str, sep: str = "\t", header: bool = False) -> DataFrame:
    return spark.read.schema(EDGE).csv(path, sep=sep, header=header, comment="#").dropna()


def edges_text(spark: SparkSession, path: str) -> DataFrame:
    """Two whole numbers a line, apart by any white space; lines that start with # or % are comments."""
    lines = spark.read.text(path).where(~F.trim("value").rlike("^[#%]") & (F.trim("value") != ""))
    parts = F.split(F.trim("value"), r"\s+")
    return lines.select(F.try_element_at(parts, F.lit(1)).try_cast("long").alias("src"), F.try_element_at(parts, F.lit(2)).try_cast("long").alias("dst")).dropna()


def edges_bucketed(spark: SparkSession, name: str) -> DataFrame:
    return spark.table(name).select("src", "dst")


def mutations_json(spark: SparkSession, path: str) -> DataFrame:
    """A log of edge changes, one JSON object a line."""
    return spark.read.schema(MUTATION).json(path)
