"""Tables, operator files and saved systems."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

OPERATOR = "sys string, row int, col int, re double, im double"
CONFIG = "sys string, N int, steps int, period double, gamma double, params map<string,double>"


def table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def read_operator(spark: SparkSession, path: str, kind: str = "parquet") -> DataFrame:
    """An operator from coordinate triples in parquet, orc, json or csv; bad records are an error."""
    return spark.read.format(kind).schema(OPERATOR).option("mode", "FAILFAST").load(path)


def read_config(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(CONFIG).option("mode", "FAILFAST").json(path)


def parse_config(df: DataFrame, column: str) -> DataFrame:
    """Configurations from a JSON column."""
    return df.select(F.from_json(column, CONFIG).alias("c")).select("c.*")


def save_system(system: DataFrame, path: str, kind: str = "parquet") -> None:
    """(sys, part, s, n, x) partitioned by system and part; steps of the work meet here and can be resumed."""
    system.write.mode("overwrite").partitionBy("sys", "part").format(kind).save(path)


def load_system(spark: SparkSession, path: str, sys: str | None = None, part: str | None = None, kind: str = "parquet") -> DataFrame:
    """A saved system; `sys` and `part` prune partitions."""
    d = spark.read.format(kind).schema("s long, n long, x double, sys string, part string").load(path)
    if sys is not None:
        d = d.where(F.col("sys") == sys)
    if part is not None:
        d = d.where(F.col("part") == part)
    return d.select("sys", "part", "s", "n", "x")
