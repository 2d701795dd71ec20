"""A session for local use; on a cluster the engine works with the session it is given."""

from __future__ import annotations

from pyspark.sql import SparkSession


def local(cores: int = 8, partitions: int = 8) -> SparkSession:
    conf = {"spark.sql.shuffle.partitions": str(partitions), "spark.ui.enabled": "false", "spark.sql.session.timeZone": "UTC", "spark.driver.memory": "8g", "spark.ui.showConsoleProgress": "false", "spark.scheduler.mode": "FAIR"}
    spark = SparkSession.builder.master(f"local[{cores}]").appName("coherent").config(map=conf).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark
