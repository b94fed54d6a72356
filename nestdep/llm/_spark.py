"""Small Spark helpers of this subpackage: tables and batches; scratch space is that of the library."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession

from ..sources.tables import forget_frame, scratch, written

__all__ = ["bounded_batches", "forget_frame", "give_back", "scratch", "table", "written"]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


BATCH_BYTES = 2 << 20


def bounded_batches(spark: SparkSession) -> None:
    """Let Arrow batches hold 2 MB at most: workers and the JVM keep several of them in memory."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    try:
        now = int(re.sub(r"[^0-9].*", "", spark.conf.get(key)))
    except Exception:  # a version without this setting
        return
    if now <= 0 or now > BATCH_BYTES:
        spark.conf.set(key, str(BATCH_BYTES))


def give_back(spark: SparkSession) -> None:
    """Ask the executors' JVMs for one full collection, after which they give free heap back to the system.

    A JVM's heap stays as large as it ever was, and Python workers then find no
    room beside it.  One short task a core; an executor that gets none keeps its heap.
    """
    n = max(1, spark.sparkContext.defaultParallelism)
    spark.range(0, n, 1, n).selectExpr("reflect('java.lang.System', 'gc') AS done").write.format("noop").mode("overwrite").save()
