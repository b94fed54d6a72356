"""Metadata of growing collections with Structured Streaming.

Masks of values only grow, so merging them is idempotent.  An inclusion may be
broken by a new left value and repaired by a new right value; a functional
dependency is only ever broken: once refuted it stays so.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming import StreamingQuery

from ..operators.inclusion import mask_columns, mask_words, name_dependencies, pair_counts, signatures, value_masks
from ..sources.tables import scratch


def stream_documents(spark: SparkSession, path: str, schema: T.StructType, kind: str = "parquet", per_trigger: int = 1) -> DataFrame:
    reader = spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).format(kind)
    files = spark.read.schema(schema).format(kind).load(path).inputFiles()
    name = path.rstrip("/").rsplit("/", 1)[-1]
    if len(files) == 1 and files[0].rstrip("/").endswith(f"/{name}"):  # a stream reads folders: name the one file in its folder
        return reader.option("pathGlobFilter", name).load(path.rstrip("/").rsplit("/", 1)[0])
    return reader.load(path)


def profile_stream(events: DataFrame, ts: str, key: str, size: str = "1 day", slide: str | None = None, late: str = "1 day") -> DataFrame:
    """Rows and values per tumbling or sliding window; rows beyond the watermark are dropped."""
    window = F.window(ts, size, slide) if slide else F.window(ts, size)
    out = events.withWatermark(ts, late).groupBy(window.alias("w"), key).agg(F.count(F.lit(1)).alias("n"), F.approx_count_distinct("value").alias("about_values"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), key, "n", "about_values")


def sessions(events: DataFrame, ts: str, key: str, gap: str = "1 day", late: str = "1 day") -> DataFrame:
    """Sessions of a key: rows closer than the gap belong together."""
    source = events.withWatermark(ts, late) if events.isStreaming else events
    out = source.groupBy(F.session_window(ts, gap).alias("w"), key).agg(F.count(F.lit(1)).alias("n"))
    return out.select(key, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def stream_masks(cells: DataFrame, ts: str, size: str, late: str, n_paths: int = 62) -> DataFrame:
    """value -> path mask (words m0, m1, ...) per window, from a stream of cells with a time."""
    w = F.window(ts, size).alias("w")
    return cells.withWatermark(ts, late).groupBy(w, "value").agg(*mask_columns(n_paths))


def late_rows(query: StreamingQuery) -> int:
    """Rows that the watermark dropped, over all batches whose progress the query still holds."""
    return sum(op.numRowsDroppedByWatermark for p in query.recentProgress for op in p.stateOperators)


class MetadataState:
    """Masks of all values seen so far, in a folder that outlives the application.

    Each batch adds the masks of its own values as one folder named by its
    number, so a batch that comes again replaces itself and its cost does not
    grow with the state.  Every `compact_every` folders are merged into one that
    names the range it covers; folders it covers are deleted afterwards, and
    ignored if a stop left them there.  A new state on the same folder goes on
    where the last one ended.
    """

    def __init__(self, spark: SparkSession, names: list[str], root: str | None = None, compact_every: int = 16) -> None:
        self.spark, self.names, self.compact_every = spark, names, compact_every
        self.root = root or scratch(spark, "masks")
        where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self.root)
        self.files = where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())

    def _path(self, name: str):
        return self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self.root}/{name}")

    def parts(self) -> list[tuple[int, int, str]]:
        """(first, last, folder) of the committed folders that no other one covers."""
        if not self.files.exists(self._path("")):
            return []
        found = []
        for status in self.files.listStatus(self._path("")):
            name = status.getPath().getName()
            m = re.fullmatch(r"masks-(\d+)-(\d+)", name)
            if m and self.files.exists(self._path(f"{name}/_SUCCESS")):
                found.append((int(m[1]), int(m[2]), name))
        return sorted(p for p in found if not any(o[0] <= p[0] and p[1] <= o[1] and o[2] != p[2] for o in found))

    def merge(self, cells: DataFrame, batch_id: int) -> None:
        """For foreachBatch."""
        parts = self.parts()
        if any(lo <= batch_id <= hi and lo < hi for lo, hi, _ in parts):
            return  # merged long ago
        value_masks(cells, len(self.names)).write.mode("overwrite").parquet(f"{self.root}/masks-{batch_id:09d}-{batch_id:09d}")
        parts = self.parts()
        if len(parts) >= self.compact_every:
            self.compact(parts)

    def compact(self, parts: list[tuple[int, int, str]] | None = None) -> None:
        parts = parts or self.parts()
        if len(parts) > 1:
            self.masks().write.mode("overwrite").parquet(f"{self.root}/masks-{parts[0][0]:09d}-{parts[-1][1]:09d}")
            for _, _, name in parts:
                self.files.delete(self._path(name), True)

    def masks(self) -> DataFrame:
        parts = self.parts()
        words = [f"m{w}" for w in range(mask_words(len(self.names)))]
        schema = ", ".join(["value string", *(f"{w} long" for w in words)])
        if not parts:
            return self.spark.createDataFrame([], schema)
        rows = self.spark.read.schema(schema).parquet(*[f"{self.root}/{name}" for _, _, name in parts])
        return rows.groupBy("value").agg(*[F.bit_or(w).alias(w) for w in words])

    def dependencies(self, theta: float = 1.0) -> DataFrame:
        n = len(self.names)
        return name_dependencies(pair_counts(signatures(self.masks(), n), n), self.names, theta)


def mine_stream(spark: SparkSession, path: str, schema: T.StructType, to_cells, names: list[str], kind: str = "parquet", root: str | None = None, checkpoint: str | None = None) -> MetadataState:
    """Read all files of a folder as a stream and return the state after the last batch.

    With the same root and checkpoint a later call reads only what is new.
    """
    state = MetadataState(spark, names, root)
    query = (
        stream_documents(spark, path, schema, kind).writeStream.trigger(availableNow=True).option("checkpointLocation", checkpoint or scratch(spark, "stream"))
        .foreachBatch(lambda batch, i: state.merge(to_cells(batch), i)).start()
    )
    query.awaitTermination()
    return state


def write_stream(df: DataFrame, path: str, mode: str = "append"):
    return df.writeStream.outputMode(mode).option("checkpointLocation", scratch(df.sparkSession, "stream")).format("parquet").start(path)
