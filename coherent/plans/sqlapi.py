"""Temporary views of basis, elements and structure constants for SQL users."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from coherent.operators import basis, structure


def register(spark: SparkSession, n: int, **frames: DataFrame) -> None:
    """Views basis_n, elem_n, sc_n for n levels, and each frame under its name."""
    basis.catalogue(spark, n).createOrReplaceTempView(f"basis_{n}")
    basis.elements(spark, n).createOrReplaceTempView(f"elem_{n}")
    structure.tensor(spark, n).createOrReplaceTempView(f"sc_{n}")
    for name, df in frames.items():
        df.createOrReplaceTempView(name)


def drift(spark: SparkSession, n: int, view: str) -> DataFrame:
    return spark.sql(f"SELECT h.sys, c.s, c.n, SUM(h.re * c.alpha) AS x FROM {view} h JOIN sc_{n} c ON c.m = h.idx GROUP BY h.sys, c.s, c.n HAVING ABS(SUM(h.re * c.alpha)) > 1e-12")
