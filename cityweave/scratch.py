"""Cutting lineage: tables written to the folder that all executors share."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def root(spark: SparkSession) -> str:
    """The folder named in spark.checkpoint.dir; only without that setting, and on a local master, a local one."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not named:
        named = spark.sparkContext.getCheckpointDir()
    if not named:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        named = tempfile.mkdtemp(prefix="cityweave-")
        spark.sparkContext.setCheckpointDir(named)
    return named


_swept: set[str] = set()


def _delete(spark: SparkSession, path: str) -> None:
    place = spark._jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)


def sweep(spark: SparkSession) -> None:
    """Removes all that this application has written here. Also runs when the driver ends, if its session is still there."""
    if spark.sparkContext._jsc is not None:
        _delete(spark, f"{root(spark).rstrip('/')}/cityweave/{spark.sparkContext.applicationId}")


class Scratch:
    """Names written tables of one run, below a folder of the application, and removes those that are no longer read."""

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        application = spark.sparkContext.applicationId
        self.base = f"{root(spark).rstrip('/')}/cityweave/{application}/{label}-{uuid.uuid4().hex}"
        self.count = 0
        if application not in _swept:
            _swept.add(application)
            atexit.register(_quietly, spark)

    def keep(self, df: DataFrame, *drop: str) -> DataFrame:
        """Writes df and returns it as read back; `drop`: paths whose readers have ended."""
        path = f"{self.base}/{self.count}"
        self.count += 1
        df.write.mode("overwrite").option("compression", "zstd").parquet(path)
        for old in drop:
            self.remove(old)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._scratch_path = path
        return out

    def remove(self, what: str | DataFrame) -> None:
        _delete(self.spark, what if isinstance(what, str) else what._scratch_path)


def _quietly(spark: SparkSession) -> None:
    try:
        sweep(spark)
    except Exception:  # the session has ended before the driver; its folder stays
        pass


def free_shuffles(spark: SparkSession) -> None:
    """Lets Spark delete shuffle files of plans that nothing refers to any more."""
    import gc

    gc.collect()
    spark._jvm.System.gc()
