"""Sessions: a default one for tests and tools, and making the package known to workers."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.errors import utils
from pyspark.sql import SparkSession

_PACKAGE = Path(__file__).resolve().parent


def local_session(cores: int | str = "*", **conf: str) -> SparkSession:
    """A local session as the tests use it; on a cluster the session comes from outside."""
    base = {
        "spark.sql.shuffle.partitions": "8",
        "spark.sql.session.timeZone": "UTC",
        "spark.ui.enabled": "false",
        "spark.driver.memory": "8g",
        "spark.driver.host": "127.0.0.1",
        "spark.ui.showConsoleProgress": "false",
    }
    spark = SparkSession.builder.master(f"local[{cores}]").config(map=base | conf).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def ship(spark: SparkSession) -> None:
    """Sends the package to the workers, unless their path has it already."""
    sc = spark.sparkContext
    if str(_PACKAGE.parent) in os.environ.get("PYTHONPATH", "").split(os.pathsep) or getattr(sc, "_cityweave_shipped", False):
        return
    archive = Path(tempfile.mkdtemp(prefix="cityweave-")) / "cityweave.zip"
    with zipfile.ZipFile(archive, "w") as z:
        for f in _PACKAGE.rglob("*.py"):
            z.write(f, f.relative_to(_PACKAGE.parent))
    sc.addPyFile(str(archive))
    sc._cityweave_shipped = True


def broadcast_by_measure(spark: SparkSession) -> None:
    """Lets joins broadcast a side only by its size as measured while they run.

    Geometry is made from keys, and kept tables are compressed, so what a plan
    says of a side's size before it runs can be a hundredth of the truth, and
    the driver would hold all of it. Sides that the code marks as small are
    still broadcast at once.
    """
    planned, measured = "spark.sql.autoBroadcastJoinThreshold", "spark.sql.adaptive.autoBroadcastJoinThreshold"
    if spark.conf.get("spark.sql.adaptive.enabled") != "true" or (most := spark.conf.get(planned)) in ("-1", "-1b"):
        return
    if spark.conf.get(measured, None) is None:
        spark.conf.set(measured, most)
    spark.conf.set(planned, "-1")


def plan_without_call_sites(spark: SparkSession) -> None:
    """Stops noting the calling line with each column expression: plans here have tens of thousands, and each note asks the JVM several times.

    A session that sets spark.python.sql.dataFrameDebugging.enabled itself, which can't be set later, keeps what it says.
    """
    if not spark.sparkContext.getConf().contains("spark.python.sql.dataFrameDebugging.enabled") and hasattr(utils, "_enable_debugging_cache"):
        utils._enable_debugging_cache = False
