"""Structure constants: alpha (antisymmetric), beta (symmetric), zeta = alpha + i beta.

The closed forms below produce every nonzero of a plane from the index of the plane alone, so the tensors are never stored: a vector
of coefficients generates the planes of its own nonzeros, and nothing is shuffled before the contraction's sum.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from coherent.operators import basis

#: Families on the edges (ab, bc, ac) of a triangle a < b < c, which tensor, and its sign.
TRIANGLE = (
    ("S", "S", "S", "beta", 1.0), ("S", "J", "J", "beta", 1.0), ("J", "S", "J", "beta", 1.0), ("J", "J", "S", "beta", -1.0),
    ("S", "S", "J", "alpha", 1.0), ("S", "J", "S", "alpha", -1.0), ("J", "S", "S", "alpha", -1.0), ("J", "J", "J", "alpha", -1.0),
)


def _row(n: Column, s: Column, alpha: Column | float, beta: Column | float) -> Column:
    f = lambda x: (F.lit(x) if isinstance(x, float) else x).cast("double")
    return F.struct(n.cast("long").alias("n"), s.cast("long").alias("s"), f(alpha).alias("alpha"), f(beta).alias("beta"))


def planes(vec: DataFrame, n: int, m: str = "idx") -> DataFrame:
    """For each row of `vec`, the nonzeros (n, s, alpha, beta) of the plane of its index `m`; other columns are kept."""
    keep = vec.columns
    v = basis.located(vec.withColumnRenamed("j", "_user_j") if "j" in keep else vec, m, n)
    keep = [c for c in v.columns if c not in ("fam", "j", "k")]
    S = lambda j, k: basis.index_of("S", j, k, n)
    J = lambda j, k: basis.index_of("J", j, k, n)
    D = lambda l: basis.index_of("D", l, l, n)
    off = v.where("fam <> 'D'")

    # Triangles: the third vertex c with the pair (j, k); the pair is edge 1, 2 or 3 of the sorted triangle.
    t = off.select(*keep, "fam", "j", "k", F.explode(F.sequence(F.lit(1), F.lit(n))).alias("c")).where("c <> j AND c <> k")
    pos = F.when(F.col("c") > F.col("k"), 1).when(F.col("c") < F.col("j"), 2).otherwise(3)
    a, b, c = F.least("j", "k", "c"), None, F.greatest("j", "k", "c")
    b = F.col("j") + F.col("k") + F.col("c") - a - c
    t = t.select(*keep, "fam", pos.alias("pos"), a.alias("a"), b.alias("b"), c.alias("c"))
    number = {0: basis.pair_number(F.col("a"), F.col("b")), 1: basis.pair_number(F.col("b"), F.col("c")), 2: basis.pair_number(F.col("a"), F.col("c"))}
    at = lambda i: F.when(F.col("pos") == 1, number[i % 3]).when(F.col("pos") == 2, number[(i + 1) % 3]).otherwise(number[(i + 2) % 3])
    # Per position and family, what the two edges after it may be (in cyclic order: an even permutation).
    half = basis.pairs(n)
    options = None
    for p in (1, 2, 3):
        for own in "SJ":
            rows = [(0 if f[p % 3] == "S" else half, 0 if f[(p + 1) % 3] == "S" else half, f[4] * basis.ROOT_HALF * (f[3] == "alpha"), f[4] * basis.ROOT_HALF * (f[3] == "beta")) for f in TRIANGLE if f[p - 1] == own]
            table = F.array(*[F.struct(F.lit(x).alias("f"), F.lit(y).alias("g"), F.lit(float(u)).alias("u"), F.lit(float(w)).alias("w")) for x, y, u, w in rows])
            on = (F.col("pos") == p) & (F.col("fam") == own)
            options = F.when(on, table) if options is None else options.when(on, table)
    t = t.select(*keep, at(1).alias("p1"), at(2).alias("p2"), F.explode(options).alias("o"))
    first, second, u, w = F.col("o.f") + F.col("p1"), F.col("o.g") + F.col("p2"), F.col("o.u"), F.col("o.w")
    triangles = t.select(*keep, F.explode(F.array(_row(first, second, u, w), _row(second, first, -u, w))).alias("_x")).select(*keep, "_x.*")

    # Pairs: an off-diagonal element with its partner and each diagonal element that separates or holds its levels.
    j, k, l = F.col("j"), F.col("k"), F.col("l")
    p = off.select(*keep, "fam", "j", "k", F.explode(F.sequence(F.greatest(F.lit(1), F.col("j") - 1), F.lit(n - 1))).alias("l"))
    less, more = basis.diagonal(l, j) - basis.diagonal(l, k), basis.diagonal(l, j) + basis.diagonal(l, k)
    own, other = F.when(F.col("fam") == "S", S(j, k)).otherwise(J(j, k)), F.when(F.col("fam") == "S", J(j, k)).otherwise(S(j, k))
    sign = F.when(F.col("fam") == "S", 1.0).otherwise(-1.0)
    p = p.select(*keep, F.explode(F.array(_row(other, D(l), sign * less, 0.0), _row(D(l), other, -sign * less, 0.0), _row(own, D(l), 0.0, more), _row(D(l), own, 0.0, more))).alias("_x")).select(*keep, "_x.*")

    # Diagonal planes: both elements of every pair of levels it tells apart or holds, and the other diagonal elements.
    d = v.where("fam = 'D'").withColumn("l", F.col("j")).drop("j", "k")
    dp = d.select(*keep, "l", F.explode(F.sequence(F.lit(2), F.lit(n))).alias("k"))
    # A diagonal plane has O(n^2) rows where others have O(n): its (l, k) are dealt out before they are multiplied, at most n^2 small rows.
    dp = dp.repartition(int(vec.sparkSession.conf.get("spark.sql.shuffle.partitions")), "l", "k")
    dp = dp.select(*keep, "l", "k", F.explode(F.sequence(F.lit(1), F.least(F.col("k") - 1, F.col("l") + 1))).alias("j"))
    dp = dp.select(*keep, F.explode(F.array(_row(S(j, k), J(j, k), less, 0.0), _row(J(j, k), S(j, k), -less, 0.0), _row(S(j, k), S(j, k), 0.0, more), _row(J(j, k), J(j, k), 0.0, more))).alias("_x")).select(*keep, "_x.*")
    y = F.col("y")
    w = lambda u: 2.0 / F.sqrt(u * (u + 1.0))
    dd = d.select(*keep, "l", F.explode(F.sequence(F.lit(1), F.lit(n - 1))).alias("y"))
    dd = dd.select(*keep, F.explode(F.when(y > l, F.array(_row(D(l), D(y), 0.0, w(y)), _row(D(y), D(l), 0.0, w(y)))).when(y < l, F.array(_row(D(y), D(y), 0.0, w(l)))).otherwise(F.array(_row(D(l), D(l), 0.0, (1.0 - l) * w(l))))).alias("_x")).select(*keep, "_x.*")
    every = triangles.unionByName(p).unionByName(dp).unionByName(dd)
    return every.where((F.abs("alpha") > 1e-12) | (F.abs("beta") > 1e-12))


def tensor(spark: SparkSession, n: int, m_range: tuple[int, int] | None = None) -> DataFrame:
    """m, n, s, alpha, beta over all planes, or those of an index range (ends included)."""
    lo, hi = m_range or (1, basis.size(n))
    return planes(spark.range(lo, hi + 1).withColumnRenamed("id", "m"), n, "m")


def alpha(spark: SparkSession, n: int, m_range: tuple[int, int] | None = None) -> DataFrame:
    return tensor(spark, n, m_range).where("abs(alpha) > 1e-12").select("m", "n", "s", "alpha")


def beta(spark: SparkSession, n: int, m_range: tuple[int, int] | None = None) -> DataFrame:
    return tensor(spark, n, m_range).where("abs(beta) > 1e-12").select("m", "n", "s", "beta")


def by_trace(elem: DataFrame) -> DataFrame:
    """The tensors by definition, from traces of triple products: two equi-joins. Quartic in the diagonal; for small n."""
    e = lambda i: elem.select(*[F.col(c).alias(f"{c}{i}") for c in ("idx", "row", "col", "re", "im")])
    two = e(1).join(e(2), F.col("col1") == F.col("row2"))
    re, im = F.expr("re1*re2-im1*im2"), F.expr("re1*im2+im1*re2")
    two = two.select("idx1", "idx2", "row1", "col2", re.alias("re"), im.alias("im"))
    three = two.join(e(3), (F.col("col2") == F.col("row3")) & (F.col("row1") == F.col("col3")))
    x, y = F.expr("re*re3-im*im3"), F.expr("re*im3+im*re3")
    t = three.groupBy("idx1", "idx2", "idx3").agg(F.sum(x).alias("x"), F.sum(y).alias("y"))  # Tr(F1 F2 F3)
    swapped = t.select(F.col("idx2").alias("idx1"), F.col("idx1").alias("idx2"), "idx3", (-F.col("x")).alias("x2"), (-F.col("y")).alias("y2"))
    both = t.join(swapped, ["idx1", "idx2", "idx3"], "full").na.fill(0.0)
    # Tr(F3 [F1, F2]) = x + x2 + i (y + y2); alpha is -i times it, beta is the sum with the other sign.
    return both.select(F.col("idx1").alias("m"), F.col("idx2").alias("n"), F.col("idx3").alias("s"), (F.col("y") + F.col("y2")).alias("alpha"), (F.col("x") - F.col("x2")).alias("beta")).where("abs(alpha) > 1e-12 OR abs(beta) > 1e-12")


def materialise(spark: SparkSession, path: str, n: int, blocks: int = 8) -> DataFrame:
    """The stored-tensor variant: Parquet partitioned by blocks of the first index, each block written on its own."""
    m = basis.size(n)
    t = tensor(spark, n).withColumn("block", F.floor((F.col("m") - 1) * blocks / m).cast("int"))
    t.write.mode("overwrite").partitionBy("block").parquet(path)
    return spark.read.parquet(path)


def counts(n: int) -> tuple[int, int]:
    """Numbers of nonzeros of alpha and beta."""
    return 5 * n**3 - 9 * n**2 - 2 * n + 6, 6 * n**3 - (21 * n**2 + 7 * n) // 2 + 1
