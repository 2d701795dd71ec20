"""Helpers shared by the corpus operators: table access, durable intermediates, distributed ranking."""

from __future__ import annotations

import atexit
import functools
import operator
import shutil
import tempfile
import uuid
from collections.abc import Callable

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: Separators of plain words: the six ASCII white-space characters.
WORD = r"[^\x20\x09-\x0D]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir, or a temporary one where none is set (tests, one machine)."""
    sc = spark.sparkContext
    told = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if not told:
        told = "file://" + tempfile.mkdtemp(prefix="coherent-")
        atexit.register(shutil.rmtree, told.removeprefix("file://"), True)
        sc.setCheckpointDir(told)
    return told.rstrip("/")


def fresh_path(spark: SparkSession, tag: str) -> str:
    """A new path in the shared folder, deleted when the application ends."""
    path = f"{shared_dir(spark)}/coherent-llm/{tag}-{uuid.uuid4().hex}"
    there = spark._jvm.org.apache.hadoop.fs.Path(path)
    there.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).deleteOnExit(there)
    return path


def durable(df: DataFrame, tag: str) -> DataFrame:
    """Write to the shared folder and read again: cuts the lineage and survives lost executors."""
    spark, path = df.sparkSession, fresh_path(df.sparkSession, tag)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def ascii_lower(text: Column) -> Column:
    """Lower-case A-Z only; every other character stays."""
    return F.translate(text, UPPER, LOWER)


def partitions(spark: SparkSession) -> int:
    return max(8, int(spark.conf.get("spark.sql.shuffle.partitions")))


def any_of(conditions: list[Column]) -> Column:
    return functools.reduce(operator.or_, conditions)


def ranked(df: DataFrame, by: list[str], order: list[Column], bucket: Column, out: str) -> DataFrame:
    """Add `out`: the rank from 0 of each row among those of equal `by`, in `order`, with no group in one task.

    `bucket` must be an integer that never falls along `order` and takes a bounded number of values (a few
    thousand). Rows are numbered within (by, bucket); the offset of a bucket is a running sum over bucket counts,
    which has at most so many rows a group however long the table is.
    """
    b = df.withColumn("_bucket", bucket)
    counts = b.groupBy(*by, "_bucket").agg(F.count(F.lit(1)).alias("_n"))
    before = Window.partitionBy(*[F.col(c) for c in by]).orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select(
        *[F.col(c).alias(f"_k{i}") for i, c in enumerate(by)], F.col("_bucket").alias("_b"),
        F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_before"),
    )
    within = F.row_number().over(Window.partitionBy(*[F.col(c) for c in by], F.col("_bucket")).orderBy(*order))
    on = functools.reduce(operator.and_, [F.col(c).eqNullSafe(F.col(f"_k{i}")) for i, c in enumerate(by)], F.col("_bucket") == F.col("_b"))
    return (
        b.withColumn("_within", within)
        .join(offsets, on)
        .withColumn(out, F.col("_before") + F.col("_within") - 1)
        .drop("_bucket", "_b", "_before", "_within", *[f"_k{i}" for i in range(len(by))])
    )


def range_bucketed(df: DataFrame, key: str, buckets: int, out: str) -> DataFrame:
    """Add `out`: a bucket number that never falls as `key` (long) rises; nulls get the last bucket.

    Bounds are approximate quantiles, so the driver holds `buckets` numbers and nothing else.
    """
    from pyspark.ml.feature import Bucketizer

    cuts = df.select(F.col(key).cast("double").alias("k")).where("k is not null").approxQuantile("k", [i / buckets for i in range(1, buckets)], 0.25 / buckets)
    splits = [float("-inf"), *sorted({c for c in cuts}), float("inf")]
    if len(splits) < 3:
        return df.withColumn(out, F.when(F.col(key).isNull(), 1).otherwise(0).cast("int"))
    d = df.withColumn("_key_d", F.coalesce(F.col(key).cast("double"), F.lit(0.0)))
    d = Bucketizer(splits=splits, inputCol="_key_d", outputCol="_key_b").transform(d)
    return d.withColumn(out, F.when(F.col(key).isNull(), len(splits)).otherwise(F.col("_key_b")).cast("int")).drop("_key_d", "_key_b")


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """`body` of `value`, which is computed once a row however often `body` uses it and wherever the optimizer moves it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def whole(texts: pa.Array) -> pa.Array:
    """`texts` without nulls and in buffers of its own: Arrow's lower-case kernels misread slices of large strings."""
    return pc.fill_null(texts, "").take(pa.array(range(len(texts)), pa.int64())).cast(pa.large_string())
