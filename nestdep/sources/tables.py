"""Sources and sinks: parquet tables, JSON documents, stores of cells and dependencies."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def load(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None, schema: T.StructType | None = None) -> DataFrame:
    """A table; a given (pruned) schema also prunes nested leaves in the scan."""
    reader = spark.read.schema(schema) if schema is not None else spark.read
    df = reader.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def scratch_root(spark: SparkSession) -> str:
    """The application's own folder in the one that all executors share (spark.checkpoint.dir).

    Where the session names none, a folder of this machine does for a local
    master only; on a cluster it would lose data, so that is an error.  The
    application's folder is deleted when the driver's interpreter ends.
    """
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="nestdep-")
        spark.sparkContext.setCheckpointDir(base)
    root = f"{base.rstrip('/')}/nestdep-{spark.sparkContext.applicationId}"
    if root not in _ROOTS:
        _ROOTS.add(root)
        atexit.register(_forget_quietly, spark, root)
    return root


_ROOTS: set[str] = set()


def scratch(spark: SparkSession, what: str) -> str:
    """A fresh path for intermediate results."""
    return f"{scratch_root(spark)}/{what}-{uuid.uuid4().hex}"


def forget(spark: SparkSession, path: str) -> None:
    """Delete scratch files that nothing reads any more."""
    place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(place, True)


def _forget_quietly(spark: SparkSession, path: str) -> None:
    try:
        forget(spark, path)
    except Exception:  # the JVM is gone: the folder stays for whoever cleans the shared one
        pass


def forget_frame(df: DataFrame) -> None:
    """Delete the files behind a frame made by `written`."""
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        forget(df.sparkSession, folder)


def written(df: DataFrame, what: str) -> DataFrame:
    """Cut the lineage of an iterative result: write it to the shared folder and read it again."""
    path = scratch(df.sparkSession, what)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def read_documents(spark: SparkSession, path: str, schema: T.StructType | None = None, mode: str = "PERMISSIVE") -> DataFrame:
    """JSON lines; give a schema at scale, as inferring one is a full pass."""
    reader = spark.read.option("mode", mode).option("columnNameOfCorruptRecord", "_corrupt")
    if schema is not None:
        reader = reader.schema(T.StructType([*schema.fields, T.StructField("_corrupt", T.StringType())]) if mode == "PERMISSIVE" else schema)
    return reader.json(path)


def json_schema(df: DataFrame, column: str) -> str:
    """The merged schema of the JSON texts of a column, in one pass."""
    return df.select(F.schema_of_variant_agg(F.try_parse_json(F.col(column)))).first()[0]


def parse_documents(df: DataFrame, column: str, schema: T.StructType | str | None = None) -> DataFrame:
    """Replace a column of JSON texts by what they hold."""
    if schema is None:
        schema = json_schema(df, column).replace("OBJECT<", "STRUCT<")
    return df.withColumn(column, F.from_json(F.col(column), schema))


def write_cells(cells: DataFrame, path: str) -> None:
    """Cells by path, sorted by value: mining again needs no new walk."""
    cells.repartition("path_id").sortWithinPartitions("path_id", "value").write.mode("overwrite").partitionBy("path_id").parquet(path)


def read_cells(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def write_dependencies(deps: DataFrame, path: str, run_id: str) -> None:
    deps.withColumn("run_id", F.lit(run_id)).write.mode("append").partitionBy("run_id").parquet(path)


def drain(df: DataFrame) -> None:
    """Run a plan and keep nothing."""
    df.write.format("noop").mode("overwrite").save()
