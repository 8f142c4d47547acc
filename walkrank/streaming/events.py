"""Edge changes from events: who acts next after whom."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from ..config import importable
from ..workloads.graphs import follow_rows

CHANGE = "src long, dst long, op string, ts timestamp, seq long"


def event_changes(events: DataFrame) -> DataFrame:
    """Of a table of events (event_id, ts, user_id, event_type): each user to the next one; an error takes the edge away."""
    moves = follow_rows(events.select("event_id", "ts", "user_id", "event_type")).where("user_id <> next_user")
    op = F.when(F.col("event_type") == "error", "delete").otherwise("insert")
    return moves.select(F.col("user_id").alias("src"), F.col("next_user").alias("dst"), op.alias("op"), F.col("ts").cast("timestamp").alias("ts"), F.col("event_id").alias("seq"))


def standing(changes: DataFrame) -> DataFrame:
    """The edges that are there after all changes, by the last of each edge."""
    last = changes.groupBy("src", "dst").agg(F.max_by("op", F.struct("ts", "seq")).alias("op"))
    return last.where("op = 'insert'").select("src", "dst")


#: What keeps the state of the lanes; the session must name it before the stream starts.
STATE_STORE = ("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")


class LastUser(StatefulProcessor):
    """The user of a lane's last event."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.last = handle.getValueState("last", "user long")

    def handleInputRows(self, key: tuple, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        events = pd.concat(list(rows)).sort_values(["ts", "event_id"])
        users = events.user_id.tolist()
        before = [self.last.get()[0] if self.last.exists() else None, *users[:-1]]
        self.last.update((int(users[-1]),))
        out = pd.DataFrame({"src": before, "dst": users, "op": ["delete" if t == "error" else "insert" for t in events.event_type], "ts": events.ts.tolist(), "seq": events.event_id.tolist()})
        out = out[out.src.notna() & (out.src != out.dst)]
        yield out.astype({"src": "int64", "dst": "int64", "seq": "int64"})

    def close(self) -> None:
        pass


def lane_changes(events: DataFrame, lane: str, late: str = "1 hour") -> DataFrame:
    """The same for a stream, in lanes (any column) that are followed each on its own: the state of a lane is its last
    user. Rows need ts (timestamp), event_id, user_id and event_type; those later than `late` are left out. The session
    needs STATE_STORE."""
    importable(events.sparkSession)
    kept = events.withWatermark("ts", late)
    return kept.groupBy(lane).transformWithStateInPandas(LastUser(), CHANGE, "Append", "None")
