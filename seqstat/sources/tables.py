"""Reading and writing tables with fixed schemas, samples, and staged results in the cluster's shared folder."""

from __future__ import annotations

import atexit
import contextlib
import gc
import shutil
import tempfile
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: The given tables.
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")

_own_folder: list[str] = []
_scratch: list[list[str]] = []


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A table, pruned to ``columns`` at the scan."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read(spark: SparkSession, fmt: str, path: str, schema: str) -> DataFrame:
    """csv, json, orc, parquet or text with an explicit schema: nothing is inferred."""
    reader = spark.read.schema(schema)
    return (reader.option("header", True) if fmt == "csv" else reader).format(fmt).load(path)


def write_stats(stats: DataFrame, path: str, mode: str = "errorifexists") -> None:
    """Statistics partitioned by length, so that a reader of one length reads no other."""
    stats.write.mode(mode).partitionBy("n").parquet(path)


def write_bucketed(dictionary: DataFrame, name: str, buckets: int = 64) -> None:
    """A dictionary as a table bucketed by term, for joins without an exchange where it is too large to broadcast."""
    dictionary.write.mode("overwrite").bucketBy(buckets, "term").sortBy("term").saveAsTable(name)


def write_corpus(corpus: DataFrame, path: str, files: int = 256) -> None:
    corpus.repartition(files).write.parquet(path)


def register(spark: SparkSession, sf_dir: str) -> list[str]:
    """Temporary views of all given tables."""
    for name in TABLES:
        table(spark, sf_dir, name).createOrReplaceTempView(name)
    return list(TABLES)


def sample(df: DataFrame, percent: int, key: str = "doc_id") -> DataFrame:
    """A repeatable random part of the documents: 25, 50 or 75 percent by the md5 of the key."""
    limit = f"{256 * percent // 100:02x}"
    return df if percent >= 100 else df.where(F.substring(F.md5(F.col(key).cast("string")), 1, 2) < limit)


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir as the session has it; where it is unset, a temporary folder of our own in local mode alone."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    if not _own_folder:
        _own_folder.append(tempfile.mkdtemp(prefix="seqstat-"))
        atexit.register(shutil.rmtree, _own_folder[0], ignore_errors=True)
    return f"file://{_own_folder[0]}"


def stage(df: DataFrame, name: str, keep: bool = False) -> DataFrame:
    """Materialise ``df`` once in the shared folder and read it back: iterations keep no lineage, and no executor's disk matters.

    In a block of ``scratch`` the table goes when the block ends; one to ``keep`` goes with the block around it, if there is one.
    """
    path = f"{shared_folder(df.sparkSession)}/seqstat/{name}-{uuid.uuid4().hex}"
    if len(_scratch) > keep:
        _scratch[-1 - keep].append(path)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


@contextlib.contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """Remove the tables that were staged in this block when it ends, and let Spark drop the shuffle files of its finished jobs."""
    _scratch.append([])
    try:
        yield
    finally:
        jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
        for name in _scratch.pop():
            path = jvm.org.apache.hadoop.fs.Path(name)
            path.getFileSystem(conf).delete(path, True)
        gc.collect()
        jvm.System.gc()
