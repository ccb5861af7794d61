"""Session defaults."""

from __future__ import annotations

import os
import sys

from pyspark.sql import SparkSession


def session(app: str = "motifloom", cores: int = 8, partitions: int = 8, memory: str = "8g", **extra: str) -> SparkSession:
    """A local session with the engine's defaults; on a cluster pass these settings to spark-submit."""
    os.environ.setdefault("PYSPARK_PYTHON", sys.executable)
    conf = {
        "spark.sql.shuffle.partitions": str(partitions),
        "spark.sql.adaptive.enabled": "true",
        "spark.sql.adaptive.skewJoin.enabled": "true",
        "spark.sql.session.timeZone": "UTC",
        "spark.sql.execution.arrow.pyspark.enabled": "true",
        "spark.sql.cbo.joinReorder.enabled": "false",
        "spark.driver.memory": memory,
        "spark.ui.enabled": "false",
        "spark.ui.showConsoleProgress": "false",
    } | extra
    builder = SparkSession.builder.master(f"local[{cores}]").appName(app)
    for key, value in conf.items():
        builder = builder.config(key, value)
    spark = builder.getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark
