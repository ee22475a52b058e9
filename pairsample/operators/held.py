"""Results that are held outside a plan, and the room of finished steps."""

from __future__ import annotations

import gc
import time

from pyspark.sql import DataFrame, SparkSession


def checkpointed(rows: DataFrame) -> DataFrame | None:
    """The rows written once to the checkpoint folder of the cluster, so that they can be counted before they are used; None where there is no such folder."""
    return rows.checkpoint() if rows.sparkSession.sparkContext.getCheckpointDir() else None


def release(spark: SparkSession) -> None:
    """Let Spark remove the shuffle files of finished steps, which otherwise stay until the driver happens to collect its garbage."""
    # what the first round frees may hold more
    for _ in range(2):
        gc.collect()
        spark._jvm.System.gc()
        time.sleep(0.2)
