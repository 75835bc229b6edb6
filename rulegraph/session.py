"""The session: settings for tests and local work, and shipping this package to Python workers."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession


def local_session(cores: int | str = 8, partitions: int = 8, memory: str = "8g", name: str = "rulegraph") -> SparkSession:
    """A local session for tests and the bench; on a cluster the session is given."""
    spark = (
        SparkSession.builder.master(f"local[{cores}]").appName(name)
        .config("spark.sql.shuffle.partitions", str(partitions))
        .config("spark.sql.adaptive.enabled", "true")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", memory)
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def ship(spark: SparkSession) -> SparkSession:
    """Gives Python workers this package (once for each application), whatever their folder or path is.

    Shuffle files go as soon as the action that wrote them ends: what is used again is staged, and disk holds one action's shuffles.
    """
    spark.conf.set("spark.sql.classic.shuffleDependency.fileCleanup.enabled", "true")
    sc = spark.sparkContext
    if getattr(sc, "_rulegraph_shipped", False):
        return spark
    package = Path(__file__).resolve().parent
    target = os.path.join(tempfile.mkdtemp(prefix="rulegraph-"), "rulegraph_package.zip")
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as out:
        for file in sorted(package.rglob("*.py")):
            out.write(file, file.relative_to(package.parent))
    sc.addPyFile(target)
    sc._rulegraph_shipped = True
    return spark
