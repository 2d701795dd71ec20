"""Model generators: driven two-site bosons, dense random rate matrices, chains of local dissipators, decay of a qubit."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from coherent.operators import basis

#: Fixed values of the experiments.
J, U, E, A, GAMMA, PERIOD = -1.0, 2.2, -1.0, -1.5, 0.1, 2 * math.pi


def _op(rows: DataFrame, cells: list[tuple[Column, Column, Column]]) -> DataFrame:
    """Cells (row, col, value) of each row, zero values left out."""
    entries = F.array(*[F.struct(r.cast("int").alias("row"), c.cast("int").alias("col"), v.cast("double").alias("re")) for r, c, v in cells])
    out = rows.select("sys", F.explode(entries).alias("x")).select("sys", "x.row", "x.col", "x.re", F.lit(0.0).alias("im"))
    return out.where("abs(re) > 1e-12")


def dimer(levels: DataFrame, n: int, j: float = J, u: float = U, e: float = E, pump: str = "antisymmetric") -> tuple[DataFrame, DataFrame, DataFrame]:
    """(H0, H1, jump operator) from `levels` (sys, level 1..n); level a + 1 has a bosons on site two.

    H0 holds hopping, interaction and the static offset e; H1 is the offset operator that the modulation multiplies. The
    pump `antisymmetric` takes the odd mode to the even one; `printed` is the Hermitian variant.
    """
    bosons = n - 1
    two = F.col("level").cast("double") - 1  # products of levels pass the int range from 46342 levels on
    one = F.lit(bosons) - two
    up, stays = F.sqrt((two + 1.0) * one), two < bosons
    hop = F.when(stays, up).otherwise(0.0)
    inter = 2 * u / bosons * (one * (one - 1) + two * (two - 1))
    here, nxt = F.col("level"), F.col("level") + 1
    offset = two - one
    h0 = _op(levels, [(here, nxt, -j * hop), (nxt, here, -j * hop), (here, here, inter + e * offset)])
    h1 = _op(levels, [(here, here, offset)])
    # With sites 1, 2: (b1^+ + b2^+)(b1 - b2) = n1 - n2 - b1^+ b2 + b2^+ b1, and (b1^+ + b2^+)(b1 + b2) = n1 + n2 + both hops.
    if pump == "antisymmetric":
        jump = _op(levels, [(here, here, -offset), (nxt, here, hop), (here, nxt, -hop)])
    elif pump == "printed":
        jump = _op(levels, [(here, here, F.lit(float(bosons))), (nxt, here, hop), (here, nxt, hop)])
    else:
        raise ValueError(f"no pump named {pump}")
    return h0, h1, jump


def dimer_weight(n: int, gamma: float = GAMMA) -> float:
    return gamma / (n - 1)


def square_wave(t: Column, e: float = 0.0, a: float = 1.0, period: float = PERIOD, phase: str = "plus_first") -> Column:
    """e + a in one half of the period and e - a in the other."""
    first = F.pmod(t, F.lit(period)) < period / 2
    sign = F.when(first, 1.0).otherwise(-1.0)
    return F.lit(e) + F.lit(a) * (sign if phase == "plus_first" else -sign)


def square_drive(spark: SparkSession, sys: str, a: float = A, period: float = PERIOD, phase: str = "plus_first") -> DataFrame:
    s = 1.0 if phase == "plus_first" else -1.0
    return spark.createDataFrame([(sys, 0.0, period / 2, s * a), (sys, period / 2, period, -s * a)], "sys string, t0 double, t1 double, eps double")


def uniform(key: Column, part: int) -> Column:
    """A portable uniform in (0, 1) from 8 hexadecimal digits of the md5 of `key`."""
    return (F.conv(F.substring(F.md5(key), 1 + 8 * part, 8), 16, 10).cast("double") + 0.5) / 4294967296.0


def gaussian_cells(spark: SparkSession, n: int, systems: DataFrame, seed: str = "rates") -> DataFrame:
    """sys, row, col, re, im: independent complex normals of an M x M matrix for each system of `systems` (sys)."""
    m = basis.size(n)
    cells = systems.select("sys", F.explode(F.sequence(F.lit(1), F.lit(m))).alias("row")).select("sys", "row", F.explode(F.sequence(F.lit(1), F.lit(m))).alias("col"))
    key = F.concat_ws(":", F.lit(seed), "sys", F.col("row").cast("string"), F.col("col").cast("string"))
    r, angle = F.sqrt(-F.log(uniform(key, 0))), 2 * math.pi * uniform(key, 1)
    return cells.select("sys", "row", "col", (r * F.cos(angle)).alias("re"), (r * F.sin(angle)).alias("im"))


def rates_of(cells: DataFrame, n: int) -> DataFrame:
    """sys, j, k, re, im: G G^+ scaled to trace n, by a join on the inner index."""
    a = cells.select("sys", F.col("row").alias("j"), "col", F.col("re").alias("x"), F.col("im").alias("y"))
    b = cells.select("sys", F.col("row").alias("k"), "col", "re", "im")
    w = a.join(b, ["sys", "col"]).groupBy("sys", "j", "k").agg(F.sum(F.expr("x*re+y*im")).alias("re"), F.sum(F.expr("y*re-x*im")).alias("im"))
    t = cells.groupBy("sys").agg(F.sum(F.expr("re*re+im*im")).alias("_t"))
    return w.join(t, "sys").select("sys", F.col("j").cast("long").alias("j"), F.col("k").cast("long").alias("k"), (n * F.col("re") / F.col("_t")).alias("re"), (n * F.col("im") / F.col("_t")).alias("im"))


def random_rates(spark: SparkSession, n: int, systems: DataFrame, seed: str = "rates", local: bool = False) -> DataFrame:
    """Random rate matrices of trace n; `local` forms each in one task with a matrix product, for larger M."""
    cells = gaussian_cells(spark, n, systems, seed)
    if not local:
        return rates_of(cells, n)
    m = basis.size(n)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        g = np.zeros((m, m), complex)
        g[pdf["row"] - 1, pdf["col"] - 1] = pdf["re"] + 1j * pdf["im"]
        w = g @ g.conj().T
        w *= n / np.trace(w).real
        j, k = np.indices((m, m)) + 1
        return pd.DataFrame({"sys": pdf["sys"].iloc[0], "j": j.ravel(), "k": k.ravel(), "re": w.real.ravel(), "im": w.imag.ravel()})

    return cells.groupBy("sys").applyInPandas(run, "sys string, j long, k long, re double, im double")


def diagonalise_rates(rates: DataFrame, n: int, tol: float = 1e-10) -> tuple[DataFrame, DataFrame]:
    """(coefficients sys, op, idx, re, im; weights sys, op, gamma) of jump operators with rates = sum gamma l l^+."""
    m = basis.size(n)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        k = np.zeros((m, m), complex)
        k[pdf["j"] - 1, pdf["k"] - 1] = pdf["re"] + 1j * pdf["im"]
        gamma, l = np.linalg.eigh((k + k.conj().T) / 2)  # noqa: E741
        rows = [pd.DataFrame({"sys": pdf["sys"].iloc[0], "op": p, "gamma": gamma[p], "idx": np.arange(1, m + 1), "re": l[:, p].real, "im": l[:, p].imag}) for p in range(m) if gamma[p] > tol]
        return pd.concat(rows) if rows else pd.DataFrame({"sys": [], "op": [], "gamma": [], "idx": [], "re": [], "im": []})

    d = rates.groupBy("sys").applyInPandas(run, "sys string, op int, gamma double, idx long, re double, im double")
    return d.select("sys", "op", "idx", "re", "im"), d.select("sys", "op", "gamma").distinct()


def chain(sites: DataFrame, count: int, body: int, boundary: str = "open") -> tuple[DataFrame, DataFrame]:
    """(jump operators sys, op, row, col, re, im; weights) of a spin chain: one lowering of `body` neighbours a site.

    `sites` has (sys, site 0..count-1, gamma). The operator at a site acts on `body` bits from it, and as the identity on the others:
    a join-free embedding by bit arithmetic on the 2^count levels. Open ends leave out windows that would pass the end.
    """
    last = count if boundary == "ring" else count - body + 1
    s = sites.where(F.col("site") < last)
    mask = F.lit(0).cast("long")
    for b in range(body):
        mask = mask + F.expr(f"shiftleft(1L, cast(pmod(site + {b}, {count}) AS int))")
    states = s.select("sys", F.col("site").cast("int").alias("op"), "gamma", mask.alias("mask"), F.explode(F.sequence(F.lit(0), F.lit((1 << count) - 1))).alias("z"))
    hit = states.where(F.col("z").cast("long").bitwiseAND(F.col("mask")) == F.col("mask"))
    jumps = hit.select("sys", "op", (F.col("z") - F.col("mask") + 1).cast("int").alias("row"), (F.col("z") + 1).alias("col"), F.lit(1.0).alias("re"), F.lit(0.0).alias("im"))
    return jumps, s.select("sys", F.col("site").cast("int").alias("op"), "gamma")


def random_chain(sites: DataFrame, count: int, body: int, seed: str = "chain", boundary: str = "open", mode: str = "jump") -> tuple[DataFrame, DataFrame]:
    """(jump operators sys, op, row, col, re, im; weights) of a chain of random local dissipators, one for each window of `body` sites.

    `jump`: a window has one operator, a complex normal matrix on its 2^body levels. `rates`: it has a random rate matrix, G G^+ of
    trace 2^body, taken as the 4^body - 1 jump operators that are G's columns over the local basis. Local operators are made
    traceless; weights are the sites' gamma. They act as the identity elsewhere: a cell of a local operator is one on every
    setting of the other bits, found by bit arithmetic. `sites` has (sys, site 0..count-1, gamma); numbers follow from `seed`.
    """
    if mode not in ("jump", "rates") or body not in (1, 2, 3) or body > count:
        raise ValueError("mode is jump or rates, body 1 to 3 and at most the number of sites")
    size, last = 1 << body, count if boundary == "ring" else count - body + 1
    s = sites.where(F.col("site") < last).select("sys", F.col("site").cast("int").alias("site"), "gamma")
    key = lambda *c: F.concat_ws(":", F.lit(seed), "sys", *[F.col(x).cast("string") for x in c])
    normal = lambda k: (F.sqrt(-F.log(uniform(k, 0))) * F.cos(2 * math.pi * uniform(k, 1)), F.sqrt(-F.log(uniform(k, 0))) * F.sin(2 * math.pi * uniform(k, 1)))
    spread = lambda d, name, lo, hi: d.select("*", F.explode(F.sequence(F.lit(lo), F.lit(hi))).alias(name))
    if mode == "jump":
        cells = spread(spread(s, "p", 1, size), "q", 1, size)
        re, im = normal(key("site", "p", "q"))
        local = cells.select("sys", "site", F.lit(0).alias("nr"), "p", "q", re.alias("re"), im.alias("im"))
    else:
        m = basis.size(size)
        g = spread(spread(s, "idx", 1, m), "nr", 1, m)
        re, im = normal(key("site", "idx", "nr"))
        g = g.select("sys", "site", "idx", "nr", re.alias("x"), im.alias("y"))
        norm = g.groupBy("sys", "site").agg(F.sqrt(size / F.sum(F.expr("x*x+y*y"))).alias("c"))
        e = basis.elements(sites.sparkSession, size).select("idx", F.col("row").alias("p"), F.col("col").alias("q"), "re", "im")
        local = g.join(norm, ["sys", "site"]).join(e, "idx").groupBy("sys", "site", "nr", "p", "q").agg(F.sum(F.expr("c*(x*re-y*im)")).alias("re"), F.sum(F.expr("c*(x*im+y*re)")).alias("im"))
    mean = local.where("p = q").groupBy("sys", "site", "nr").agg((F.sum("re") / size).alias("t"), (F.sum("im") / size).alias("u"))
    local = local.join(mean, ["sys", "site", "nr"]).select("sys", "site", "nr", "p", "q", F.expr("re - if(p = q, t, 0.0D)").alias("re"), F.expr("im - if(p = q, u, 0.0D)").alias("im"))
    # Bit b of a local level is bit (site + b) mod count of the chain's; the other count - body bits run over all settings, filling the gaps.
    place = lambda value: sum((F.expr(f"shiftleft(shiftright(cast({value} - 1 AS bigint), {b}) & 1L, cast(pmod(site + {b}, {count}) AS int))") for b in range(1, body)), F.expr(f"shiftleft(cast({value} - 1 AS bigint) & 1L, cast(pmod(site, {count}) AS int))"))
    rest = spread(local.withColumn("_p", place("p")).withColumn("_q", place("q")), "_z", 0, (1 << (count - body)) - 1)
    others = sum((F.expr(f"shiftleft(shiftright(cast(_z AS bigint), {b}) & 1L, cast(pmod(site + {body + b}, {count}) AS int))") for b in range(count - body)), F.lit(0).cast("long"))
    rest = rest.withColumn("_o", others)
    per = 1 if mode == "jump" else basis.size(size)
    op = (F.col("site") * per + F.greatest(F.col("nr") - 1, F.lit(0))).cast("int")
    jumps = rest.select("sys", op.alias("op"), (F.col("_p") + F.col("_o") + 1).cast("int").alias("row"), (F.col("_q") + F.col("_o") + 1).cast("int").alias("col"), "re", "im")
    weights = spread(s, "nr", 0, per - 1).select("sys", (F.col("site") * per + F.col("nr")).cast("int").alias("op"), "gamma")
    return jumps, weights


def decaying_qubit(spark: SparkSession, omega: float, gamma: float) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(H, jump operator, weights) of the hand example."""
    h = spark.createDataFrame([("qubit", 1, 1, omega / 2, 0.0), ("qubit", 2, 2, -omega / 2, 0.0)], "sys string, row int, col int, re double, im double")
    l = spark.createDataFrame([("qubit", 0, 1, 2, 1.0, 0.0)], "sys string, op int, row int, col int, re double, im double")  # noqa: E741
    return h, l, spark.createDataFrame([("qubit", 0, gamma)], "sys string, op int, gamma double")
