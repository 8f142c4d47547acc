"""A ranking kept current under a stream of edge changes.

Each micro-batch is one batch of the dynamic algorithm and one version in the store. A micro-batch that comes again
after a restart finds its number there and does nothing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..operators.dynamic import EdgeBatch, KatzState, apply_batch
from ..sources import store
from ..sources.tables import MUTATION


def mutation_stream(spark: SparkSession, path: str, per_trigger: int | None = None) -> DataFrame:
    """A folder of Parquet files of edge changes."""
    reader = spark.readStream.schema(MUTATION)
    if per_trigger:
        reader = reader.option("maxFilesPerTrigger", per_trigger)
    return reader.parquet(path)


def deduplicated(changes: DataFrame, late: str = "1 hour") -> DataFrame:
    """Without changes that repeat one of the same edge, kind and number within the time that late ones may take."""
    return changes.withWatermark("ts", late).dropDuplicatesWithinWatermark(["src", "dst", "op", "seq"])


def windowed_edges(changes: DataFrame, width: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Changes counted by edge and event-time window."""
    return changes.withWatermark("ts", late).groupBy(F.window("ts", width, slide or width), "src", "dst").agg(F.count_if(F.col("op") == "insert").alias("inserts"), F.count_if(F.col("op") == "delete").alias("deletes"))


def session_edges(changes: DataFrame, gap: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Changes counted by source and session."""
    return changes.withWatermark("ts", late).groupBy("src", F.session_window("ts", gap)).agg(F.count("*").alias("changes"))


def split_late(changes: DataFrame, late: str = "1 hour") -> tuple[DataFrame, DataFrame]:
    """Of a micro-batch the changes on time and those that come later than `late` behind the newest of their batch."""
    newest = changes.agg(F.max("ts").alias("_newest"))
    both = changes.crossJoin(F.broadcast(newest)).withColumn("_late", F.col("ts") < F.col("_newest") - F.expr(f"interval {late}"))
    pick = lambda c: both.where(c).drop("_newest", "_late")
    return pick(~F.coalesce("_late", F.lit(False))), pick(F.col("_late"))


def changes_of(batch: DataFrame) -> EdgeBatch:
    return EdgeBatch(batch.where("src is not null and dst is not null and op in ('insert', 'delete')").select("src", "dst", "op", F.coalesce("seq", F.lit(0).cast("long")).alias("seq")))


class RankingStream:
    """The state in a store, moved on by micro-batches. The driver that wrote the latest version has it still; any other
    loads it."""

    def __init__(self, root: str, keep_versions: int = 3, late: str | None = None):
        """late: changes that come later than that behind their micro-batch go to the folder late of the store instead."""
        self.root, self.keep, self.late = root, keep_versions, late
        self._last: KatzState | None = None

    def initialise(self, state: KatzState) -> None:
        self._last = store.save(state, self.root)

    def _state(self, spark: SparkSession) -> tuple[KatzState, int]:
        known = store.versions(spark, self.root)
        row = known.orderBy(F.desc("version")).first() if known is not None else None
        if row is None:
            raise ValueError("the store has no state")
        if self._last is None or self._last.version != row.version:
            self._last = store.load(spark, self.root, row.version)[0]
        return self._last, row.batch

    def state(self, spark: SparkSession) -> KatzState:
        return self._state(spark)[0]

    def apply(self, batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        state, last = self._state(spark)
        if number <= last:
            return
        if self.late:
            batch, behind = split_late(batch, self.late)
            behind.write.mode("overwrite").parquet(f"{self.root}/late/batch={number}")
        before = state.graph.placed
        self._last = store.save(apply_batch(state, changes_of(batch)), self.root, number)
        if self._last.graph.placed.edges is not before.edges:
            before.release()
        if self.keep:
            store.compact(spark, self.root, self.keep)

    def start(self, changes: DataFrame, checkpoint: str, available_now: bool = False) -> StreamingQuery:
        writer = changes.writeStream.foreachBatch(self.apply).option("checkpointLocation", checkpoint)
        return (writer.trigger(availableNow=True) if available_now else writer).start()

    def top(self, spark: SparkSession, k: int) -> DataFrame:
        return self.state(spark).result().ranking(k)
