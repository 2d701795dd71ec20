"""The orthonormal basis of traceless Hermitian matrices: symmetric (S), antisymmetric (J) and diagonal (D) elements.

Indices run from 1: S pairs, then J pairs, then D. A pair j < k has number (k-1)(k-2)/2 + j, whatever the level count.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from coherent.functions.checks import levels

ROOT_HALF = 0.5**0.5


def pairs(n: int) -> int:
    return n * (n - 1) // 2


def size(n: int) -> int:
    return n * n - 1


def pair_number(j: Column, k: Column) -> Column:
    return (F.expr("0L") + (k - 1) * (k - 2) / 2 + j).cast("long")


def index_of(fam: str, j: Column, k: Column, n: int) -> Column:
    """Linear index of an element; for family D, `j` is its number l."""
    if fam == "D":
        return (F.lit(2 * pairs(n)) + j).cast("long")
    return (F.lit(0 if fam == "S" else pairs(n)) + pair_number(j, k)).cast("long")


def located(df: DataFrame, idx: str, n: int) -> DataFrame:
    """Add fam, j, k of the element `idx` (for D: j = l and k = l + 1). Integer arithmetic only; no join."""
    half = pairs(n)
    i = F.col(idx)
    p = F.when(i <= half, i).otherwise(i - half)
    guess = F.floor((F.lit(3.0) + F.sqrt(F.lit(8.0) * p - 7)) / 2).cast("long")  # largest k with (k-1)(k-2)/2 < p
    k = F.when((guess - 1) * (guess - 2) / 2 >= p, guess - 1).when(guess * (guess - 1) / 2 < p, guess + 1).otherwise(guess)
    diagonal = i > 2 * half
    return (
        df.withColumn("fam", F.when(i <= half, "S").when(diagonal, "D").otherwise("J"))
        .withColumn("k", F.when(diagonal, i - 2 * half + 1).otherwise(k).cast("int"))
        .withColumn("j", F.when(diagonal, i - 2 * half).otherwise(p - ((F.col("k") - 1) * (F.col("k") - 2) / 2)).cast("int"))
    )


def catalogue(spark: SparkSession, n: int) -> DataFrame:
    """idx, fam, j, k of all elements."""
    return located(spark.range(1, size(levels(n)) + 1).withColumnRenamed("id", "idx"), "idx", n)


def elements_of(cat: DataFrame) -> DataFrame:
    """The nonzero cells (row, col, re, im) of the elements in `cat` (fam, j, k and any other columns)."""
    rest = [c for c in cat.columns if c not in ("fam", "j", "k")]
    cell = lambda r, c, re, im: F.struct(r.cast("int").alias("row"), c.cast("int").alias("col"), F.lit(re).cast("double").alias("re"), F.lit(im).cast("double").alias("im"))
    j, k = F.col("j"), F.col("k")
    norm = F.sqrt(j * (j + 1.0))
    cells = (
        F.when(F.col("fam") == "S", F.array(cell(j, k, ROOT_HALF, 0.0), cell(k, j, ROOT_HALF, 0.0)))
        .when(F.col("fam") == "J", F.array(cell(j, k, 0.0, -ROOT_HALF), cell(k, j, 0.0, ROOT_HALF)))
        .otherwise(F.transform(F.sequence(F.lit(1), j + 1), lambda a: F.struct(a.cast("int").alias("row"), a.cast("int").alias("col"), (F.when(a <= j, 1.0).otherwise(-j) / norm).alias("re"), F.lit(0.0).alias("im"))))
    )
    return cat.select(*rest, F.explode(cells).alias("_c")).select(*rest, "_c.*")


def elements(spark: SparkSession, n: int) -> DataFrame:
    """idx, row, col, re, im of every basis element: about 2.5 n^2 rows."""
    return elements_of(catalogue(spark, n))


def diagonal(l: Column, a: Column) -> Column:  # noqa: E741
    """Entry a of the diagonal element l."""
    return F.when(a <= l, F.lit(1.0)).when(a == l + 1, -l.cast("double")).otherwise(0.0) / F.sqrt(l * (l + 1.0))
