"""Written tables that cut the lineage of iterations and survive lost executors."""

from __future__ import annotations

import re
import tempfile
import uuid

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    """A new path under the checkpoint folder of the session, in a folder of this application.

    A session without one gets a temporary folder in local mode, where driver and executors are one
    process; on a cluster that is an error, since executors would not see each other's files.
    """
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="stratasum-")
        spark.sparkContext.setCheckpointDir(base)
    return f"{base.rstrip('/')}/steps/{spark.sparkContext.applicationId}/{uuid.uuid4().hex}"


def keep(df: DataFrame) -> DataFrame:
    """df, written as Parquet and read again."""
    path = shared_folder(df.sparkSession)
    df.write.parquet(path)
    return _read(df, path)


def _read(df: DataFrame, path: str) -> DataFrame:
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._kept_at = path
    return out


def observed(seen: Observation) -> dict:
    """What an observation has seen. Spark leaves out parts of a plan that are sure to be empty, and with them what watches them: that saw nothing."""
    try:
        return seen.get
    except Py4JJavaError:
        return {}


def write_counted(df: DataFrame, path: str) -> int:
    """Writes df and gives the number of its rows, which the writing job counts."""
    seen = Observation()
    df.observe(seen, F.count(F.lit(1)).alias("n")).write.parquet(path)
    return int(observed(seen).get("n", 0))


def keep_counted(df: DataFrame) -> tuple[DataFrame, int]:
    """df written and read again, and how many rows it has, in one job."""
    path = shared_folder(df.sparkSession)
    n = write_counted(df, path)
    return _read(df, path), n


def discard(df: DataFrame) -> None:
    """Removes what `keep` or `place_by` wrote for df; nothing may read df after that."""
    spark, path = df.sparkSession, getattr(df, "_kept_at", None)
    if getattr(df, "_kept_as", None):
        spark.sql(f"DROP TABLE IF EXISTS {df._kept_as}")
    if path:
        _delete(spark, path)


def discard_all(spark: SparkSession) -> None:
    """Removes all tables that this application has kept. For the end of a job, when its results are elsewhere."""
    _delete(spark, shared_folder(spark).rpartition("/")[0])


def _delete(spark: SparkSession, path: str) -> None:
    place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(place, True)


def place_by(df: DataFrame, *columns: str) -> DataFrame:
    """df dealt once by its join key, for reuse in all steps: a bucketed table, so that joins on the key do not shuffle it again."""
    spark, path = df.sparkSession, shared_folder(df.sparkSession)
    name = f"placed_{path.rpartition('/')[2]}"
    buckets = int(spark.conf.get("spark.sql.shuffle.partitions"))
    df.repartition(buckets, *columns).write.bucketBy(buckets, *columns).sortBy(*columns).option("path", path).format("parquet").saveAsTable(name)
    out = spark.table(name)
    out._kept_at, out._kept_as = path, name
    return out
