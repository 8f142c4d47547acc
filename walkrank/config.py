"""Fixed choices of the engine, and the session's shared folder."""

from __future__ import annotations

import os
import tempfile
from pathlib import Path

from pyspark.sql import SparkSession

#: Levels after which a run gives up and says so.
MAX_LEVELS = 200
#: Edges (or nodes) up to which a graph is small, and those of one of its partitions.
SMALL_ROWS, PARTITION_ROWS = 4_000_000, 250_000
#: Edges of one target that lie in a row, as a power of two.
PACK_BITS = 12
#: Nodes that a task's fast map of sums has room for at most, as a power of two (some 30 bytes each).
SUM_BITS = 21
#: Rows of a change that are sent to all executors rather than shuffled.
BROADCAST_ROWS = 100_000
#: Rows of the top of a ranking that the driver looks at.
DRIVER_ROWS = 100_000
#: Share of the nodes beyond which a level is counted anew rather than changed, and rows up to which it is changed anyway.
FRONTIER_CAP, FRONTIER_ROWS = 0.2, 50_000
#: Ids pack a kind and a key.
KEY_BITS = 40


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors share: what spark.checkpoint.dir says, or a temporary one where it is unset and all run here."""
    sc = spark.sparkContext
    top = sc.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if not top:
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        top = "file://" + tempfile.mkdtemp(prefix="walkrank-")
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(top)
    return top


def importable(spark: SparkSession) -> SparkSession:
    """Lets Python workers import this package from where the driver has it (else it must come by --py-files)."""
    env, here = spark.sparkContext.environment, str(Path(__file__).resolve().parent.parent)
    paths = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
    if here not in paths:
        env["PYTHONPATH"] = os.pathsep.join([*paths, here])
    return spark
