"""Structure constants as a generated data source and as a table function: for SQL users and small level counts."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import types as T
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.functions import udtf


def plane_rows(m: int, n: int):
    """(n, s, alpha, beta) nonzeros of plane m for n levels, by traces in numpy."""
    import numpy as np

    f = elements(n)
    a = f[m - 1]
    # Tr(F_s F_m F_n) for all n and s
    left = np.einsum("ab,nbc,sca->ns", a, f, f, optimize=True)
    right = np.einsum("nab,bc,sca->ns", f, a, f, optimize=True)
    alpha, beta = (-1j * (left - right)).real, (left + right).real
    for i, j in zip(*np.nonzero((abs(alpha) > 1e-12) | (abs(beta) > 1e-12)), strict=True):
        yield int(i) + 1, int(j) + 1, float(alpha[i, j]), float(beta[i, j])


def elements(n: int):
    """All basis elements as dense matrices, in index order."""
    import numpy as np

    s, j, d = [], [], []
    for k in range(1, n):
        for i in range(k):
            e = np.zeros((n, n), complex)
            e[i, k] = e[k, i] = 0.5**0.5
            s.append(e)
            e = np.zeros((n, n), complex)
            e[i, k], e[k, i] = -1j * 0.5**0.5, 1j * 0.5**0.5
            j.append(e)
    for i in range(1, n):
        d.append(np.diag([1.0] * i + [-i] + [0.0] * (n - i - 1)).astype(complex) / (i * (i + 1)) ** 0.5)
    return np.array(s + j + d)


class _Range(InputPartition):
    def __init__(self, lo: int, hi: int) -> None:
        self.lo, self.hi = lo, hi


class _Reader(DataSourceReader):
    def __init__(self, n: int, parts: int) -> None:
        self.n, self.parts = n, parts

    def partitions(self):
        m = self.n * self.n - 1
        cuts = [1 + i * m // self.parts for i in range(self.parts + 1)]
        return [_Range(a, b) for a, b in zip(cuts, cuts[1:], strict=False) if a < b]

    def read(self, partition):
        for m in range(partition.lo, partition.hi):
            for row in plane_rows(m, self.n):
                yield (m, *row)


class StructureConstants(DataSource):
    """spark.read.format("structure_constants").option("levels", n).load(), one input partition an index range."""

    @classmethod
    def name(cls) -> str:
        return "structure_constants"

    def schema(self) -> str:
        return "m bigint, n bigint, s bigint, alpha double, beta double"

    def reader(self, schema):
        return _Reader(int(self.options["levels"]), int(self.options.get("partitions", "4")))


PLANE = T.StructType([T.StructField("n", T.LongType()), T.StructField("s", T.LongType()), T.StructField("alpha", T.DoubleType()), T.StructField("beta", T.DoubleType())])


@udtf(returnType=PLANE)
class StructurePlane:
    """structure_plane(m, levels) for LATERAL joins."""

    def eval(self, m: int, levels: int):
        yield from plane_rows(m, levels)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(StructureConstants)
    spark.udtf.register("structure_plane", StructurePlane)
