"""Every method as a query on the given tables, next to the SQL of another route."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from coherent.functions import cplx
from coherent.operators import assemble, baselines, basis, expand, integrate, linalg, measures, models, partition, spectrum, structure, validate
from coherent.plans import oracles as o
from coherent.plans import sqlapi, workloads
from coherent.sources import io, structure_source
from coherent.sources.store import fresh_path, keep
from coherent.streaming import drives

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
c6 = cplx.clean
r6 = o.r6


def coefficients(op: DataFrame, n: int) -> DataFrame:
    """The expansion, kept: a few rows that every branch of the planes reads."""
    return keep(expand.expand(op, n), "coefficients")


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return add


def seconds(ts: Column) -> Column:
    """Seconds since 1970, of timestamps with or without a zone."""
    return F.unix_micros(ts.cast("timestamp")) / 1e6


def sparse(df: DataFrame, *keys: str | Column, values: tuple[str, ...] = ("x",)) -> DataFrame:
    """Nonzeros above the tolerance, rounded."""
    kept = None
    for v in values:
        kept = (F.abs(F.col(v)) > 1e-9) if kept is None else kept | (F.abs(F.col(v)) > 1e-9)
    return df.where(kept).select(*keys, *[c6(F.col(v)).alias(v) for v in values])


def system_sql(body: str, inner: str) -> str:
    return f"WITH {body} SELECT s, n, {r6('x')} AS x FROM ({inner}) WHERE abs(x) > 1e-9"


# -- basis


@query("basis_catalogue", f"WITH {o.elem(5)} SELECT p AS idx, 'S' AS fam, j, k FROM pr UNION ALL SELECT p + 10, 'J', j, k FROM pr UNION ALL SELECT i + 20, 'D', i, i + 1 FROM lev WHERE i < 5")
def basis_catalogue(spark, d):
    n = io.table(spark, d, "region").count()
    return basis.catalogue(spark, n).select("idx", "fam", F.col("j").cast("long").alias("j"), F.col("k").cast("long").alias("k"))


@query("basis_elements", f"WITH {o.elem(25)} SELECT idx, r AS row, c AS col, {r6('re')} AS re, {r6('im')} AS im FROM elem")
def basis_elements(spark, d):
    e = basis.elements(spark, io.table(spark, d, "nation").count())
    return e.select("idx", F.col("row").cast("long").alias("row"), F.col("col").cast("long").alias("col"), c6(F.col("re")).alias("re"), c6(F.col("im")).alias("im"))


@query("basis_gram", f"WITH {o.elem(5)}, {o.flow()}, {o.flow_h(5)} SELECT idx AS i, idx AS j, {r6('re * re')} AS re, 0.0::DOUBLE AS im FROM ({o.expand_sql('h')}) WHERE re * re > 1e-9")
def basis_gram(spark, d):
    """Of the basis elements, each times its coefficient in the flow's Hamiltonian: squares on the diagonal, and nothing else."""
    h, _, _, n = workloads.flow_system(spark, d)
    v = coefficients(h, n).select("idx", F.col("re").alias("c"))
    e = basis.elements(spark, n).join(v, "idx").select("idx", "row", "col", F.expr("re*c").alias("re"), F.expr("im*c").alias("im"))
    return validate.basis_gram(e).select("i", "j", c6(F.col("re")).alias("re"), c6(F.col("im")).alias("im"))


# -- operators from tables


def _cells(level: str, inner: str) -> str:
    return f"WITH {o.flow(level)}, {inner}"


@query("flow_cells", f"WITH {o.flow('nation')} SELECT r AS row, c AS col, {r6('v')} AS re FROM flow")
def flow_cells(spark, d):
    return workloads.flow(spark, d, "nation").select(F.col("row").cast("long").alias("row"), F.col("col").cast("long").alias("col"), c6(F.col("re")).alias("re"))


@query("flow_h", f"WITH {o.flow()}, {o.flow_h(5)} SELECT r AS row, c AS col, {r6('re')} AS re, {r6('im')} AS im FROM h WHERE abs(re) > 1e-9 OR abs(im) > 1e-9")
def flow_h(spark, d):
    h, *_ = workloads.flow_system(spark, d)
    return sparse(h, F.col("row").cast("long").alias("row"), F.col("col").cast("long").alias("col"), values=("re", "im"))


@query("flow_jump", f"WITH {o.flow()}, {o.flow_h(5)} SELECT r AS row, c AS col, {r6('v')} AS re FROM l0 WHERE abs(v) > 1e-9")
def flow_jump(spark, d):
    _, l0, *_ = workloads.flow_system(spark, d)
    return sparse(l0, F.col("row").cast("long").alias("row"), F.col("col").cast("long").alias("col"), values=("re",))


def _vec(df: DataFrame) -> DataFrame:
    return sparse(df, "idx", values=("re", "im"))


def _vec_sql(body: str, op: str) -> str:
    return f"WITH {body} SELECT idx, {r6('re')} AS re, {r6('im')} AS im FROM ({o.expand_sql(op)}) WHERE abs(re) > 1e-9 OR abs(im) > 1e-9"


FLOW5 = f"{o.elem(5)}, {o.flow()}, {o.flow_h(5)}, {o.flow_jump()}"


@query("expand_h", _vec_sql(FLOW5, "h"))
def expand_h(spark, d):
    h, _, _, n = workloads.flow_system(spark, d)
    return _vec(coefficients(h, n))


@query("expand_jump", _vec_sql(FLOW5, "L"))
def expand_jump(spark, d):
    _, l0, _, n = workloads.flow_system(spark, d)
    return _vec(coefficients(l0, n))


@query("prefix_d", _vec_sql(f"{o.elem(25)}, {o.dimer_cells(25, 'nation', 'n_nationkey')}", "h0").replace(") WHERE abs(re) > 1e-9 OR abs(im) > 1e-9", ") WHERE idx > 600 AND (abs(re) > 1e-9 OR abs(im) > 1e-9)"))
def prefix_d(spark, d):
    h0, *_ = workloads.dimer(spark, d, "nation")
    return _vec(coefficients(h0, 25)).where("idx > 600")


@query("rebuild_roundtrip", f"WITH {o.flow()} SELECT r AS row, c AS col, {r6('v')} AS re FROM flow WHERE abs(v) > 1e-9")
def rebuild_roundtrip(spark, d):
    x = workloads.flow(spark, d)
    return sparse(expand.rebuild(coefficients(x, 5), expand.traces(x), 5), F.col("row").cast("long").alias("row"), F.col("col").cast("long").alias("col"), values=("re",))


LABEL = "x AS (SELECT quality + 1 AS r, toxic + 1 AS c, count(*)::DOUBLE AS v FROM labels JOIN documents USING (doc_id) GROUP BY ALL), rho AS (SELECT a.r::BIGINT AS r, b.r::BIGINT AS c, sum(a.v * b.v) / (SELECT sum(v * v) FROM x) AS re, 0.0::DOUBLE AS im FROM x a JOIN x b USING (c) GROUP BY a.r, b.r)"
LANG = f"x AS (SELECT list_position({o.LANG_LIST}, lang) AS r, source AS c, count(*)::DOUBLE AS v FROM documents WHERE list_contains({o.LANG_LIST}, lang) GROUP BY ALL), rho AS (SELECT a.r::BIGINT AS r, b.r::BIGINT AS c, sum(a.v * b.v) / (SELECT sum(v * v) FROM x) AS re, 0.0::DOUBLE AS im FROM x a JOIN x b USING (c) GROUP BY a.r, b.r)"


@query("qubit_vector", f"WITH {LABEL}, m AS (SELECT max(CASE WHEN r = 1 AND c = 1 THEN re END) AS p, max(CASE WHEN r = 2 AND c = 2 THEN re END) AS q, max(CASE WHEN r = 1 AND c = 2 THEN re END) AS z FROM rho) SELECT idx, {r6('x')} AS x FROM (SELECT 1::BIGINT AS idx, sqrt(2) * z AS x FROM m UNION ALL SELECT 3, (p - q) / sqrt(2) FROM m) WHERE abs(x) > 1e-9")
def qubit_vector(spark, d):
    return sparse(expand.initial_vector(workloads.gram(workloads.label_cells(spark, d)), 2), "idx")


@query("qutrit_expand", f"WITH {o.elem(3)}, {o.jumps_cte('turn3')} SELECT op, idx, {r6('re')} AS re, {r6('im')} AS im FROM (SELECT op, e.idx, sum(e.re * l.re - e.im * l.im) AS re, sum(e.re * l.im + e.im * l.re) AS im FROM elem e JOIN L l ON e.c = l.r AND e.r = l.c GROUP BY op, e.idx) WHERE abs(re) > 1e-9 OR abs(im) > 1e-9")
def qutrit_expand(spark, d):
    j, _ = workloads.turns(spark, d)
    return sparse(coefficients(j, 3), "op", "idx", values=("re", "im"))


@query("initial_vector", f"WITH {o.elem(4)}, {LANG} SELECT idx, {r6('re')} AS x FROM ({o.expand_sql('rho')}) WHERE abs(re) > 1e-9")
def initial_vector(spark, d):
    return sparse(expand.initial_vector(workloads.gram(workloads.lang_cells(spark, d)), 4), "idx")


@query("lang_density", f"WITH {LANG} SELECT r AS row, c AS col, {r6('re')} AS re FROM rho WHERE abs(re) > 1e-9")
def lang_density(spark, d):
    return sparse(workloads.gram(workloads.lang_cells(spark, d)), F.col("row").cast("long").alias("row"), F.col("col").cast("long").alias("col"), values=("re",))


EMBED = "e0 AS (SELECT label::VARCHAR AS sys, vec_id, unnest(embedding)::DOUBLE AS v, generate_subscripts(embedding, 1) AS r FROM embeddings), et AS (SELECT sys, sum(v * v) AS t FROM e0 GROUP BY sys), rho AS (SELECT a.sys, a.r::BIGINT AS r, b.r::BIGINT AS c, sum(a.v * b.v) / any_value(t) AS re, 0.0::DOUBLE AS im FROM e0 a JOIN e0 b ON a.sys = b.sys AND a.vec_id = b.vec_id JOIN et ON a.sys = et.sys GROUP BY a.sys, a.r, b.r)"


@query("embed_gram", f"WITH {EMBED} SELECT sys, r AS row, c AS col, {r6('re')} AS re FROM rho WHERE abs(re) > 1e-9")
def embed_gram(spark, d):
    return sparse(workloads.gram(workloads.embedding_cells(spark, d)), "sys", F.col("row").cast("long").alias("row"), F.col("col").cast("long").alias("col"), values=("re",))


# -- structure constants

TENSOR5 = f"{o.elem(5)}, {o.trace_tensor()}"


@query("alpha_plane", f"WITH {FLOW5}, {o.trace_tensor()}, hv AS ({o.expand_sql('h')}) SELECT m, n, s, {r6('re')} AS re, {r6('alpha')} AS alpha FROM sc JOIN hv ON m = idx WHERE abs(alpha) > 1e-9 AND abs(re) > 1e-9")
def alpha_plane(spark, d):
    """The planes of the flow's Hamiltonian, each beside its coefficient: the terms of the drift before their sum."""
    h, _, _, n = workloads.flow_system(spark, d)
    v = coefficients(h, n).where("abs(re) > 1e-9").select(F.col("idx").alias("m"), "re")
    return structure.alpha(spark, n).join(v, "m").select("m", "n", "s", c6(F.col("re")).alias("re"), c6(F.col("alpha")).alias("alpha"))


@query("beta_plane", f"WITH {FLOW5}, {o.trace_tensor()}, lv5 AS ({o.expand_sql('L')}) SELECT m, n, s, {r6('re')} AS re, {r6('im')} AS im, {r6('beta')} AS beta FROM sc JOIN lv5 ON m = idx WHERE abs(beta) > 1e-9 AND (abs(re) > 1e-9 OR abs(im) > 1e-9)")
def beta_plane(spark, d):
    """The planes of the flow's jump operator, each beside its coefficient."""
    _, l0, _, n = workloads.flow_system(spark, d)
    v = coefficients(l0, n).where("abs(re) > 1e-9 OR abs(im) > 1e-9").select(F.col("idx").alias("m"), "re", "im")
    return structure.beta(spark, n).join(v, "m").select("m", "n", "s", c6(F.col("re")).alias("re"), c6(F.col("im")).alias("im"), c6(F.col("beta")).alias("beta"))


@query("structure_closed_form", f"WITH {TENSOR5} SELECT m, n, s, {r6('alpha')} AS alpha, {r6('beta')} AS beta FROM sc WHERE (abs(alpha) > 1e-9 OR abs(beta) > 1e-9) AND m BETWEEN 7 AND 22")
def structure_closed_form(spark, d):
    return structure.tensor(spark, 5, (7, 22)).select("m", "n", "s", c6(F.col("alpha")).alias("alpha"), c6(F.col("beta")).alias("beta"))


@query("structure_by_trace", f"WITH {o.elem(4)}, {o.trace_tensor()} SELECT m, n, s, {r6('alpha')} AS alpha, {r6('beta')} AS beta FROM sc WHERE abs(alpha) > 1e-9 OR abs(beta) > 1e-9")
def structure_by_trace(spark, d):
    return structure.by_trace(basis.elements(spark, 4)).select("m", "n", "s", c6(F.col("alpha")).alias("alpha"), c6(F.col("beta")).alias("beta"))


@query("zeta_counts", "SELECT n::BIGINT AS levels, (5*n**3-9*n**2-2*n+6)::BIGINT AS alpha, (6*n**3-(21*n**2+7*n)/2+1)::BIGINT AS beta FROM range(2, 9) t(n)")
def zeta_counts(spark, d):
    parts = [structure.tensor(spark, n).agg(F.lit(n).cast("long").alias("levels"), F.count(F.when(F.abs("alpha") > 1e-9, 1)).alias("alpha"), F.count(F.when(F.abs("beta") > 1e-9, 1)).alias("beta")) for n in range(2, 9)]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


@query("plane_counts", f"WITH {TENSOR5} SELECT m, count(*) FILTER (WHERE abs(alpha) > 1e-9) AS alpha, count(*) FILTER (WHERE abs(beta) > 1e-9) AS beta FROM sc GROUP BY m")
def plane_counts(spark, d):
    return measures.plane_counts(spark, 5)


@query("contraction_tuples", f"WITH {o.elem(5)}, {o.trace_tensor()}, {o.jumps_cte('hop5')}, x AS (SELECT op, e.idx FROM elem e JOIN L l ON e.c = l.r AND e.r = l.c GROUP BY op, e.idx HAVING abs(sum(e.re * l.re - e.im * l.im)) > 1e-9 OR abs(sum(e.re * l.im + e.im * l.re)) > 1e-9), c AS (SELECT op, n, count(*) FILTER (WHERE abs(alpha) > 1e-9) AS a, count(*) FILTER (WHERE abs(beta) > 1e-9) AS b FROM sc JOIN x ON m = idx GROUP BY op, n) SELECT op, sum((a + b) * a)::BIGINT AS tuples FROM c GROUP BY op")
def contraction_tuples(spark, d):
    """Of each jump operator of the events' hops."""
    j, _ = workloads.hops(spark, d)
    return measures.contraction_tuples(spark, 5, coefficients(j, 5)).select("op", "tuples")


@query("support_union", f"WITH {TENSOR5} SELECT DISTINCT m, n, s FROM sc WHERE abs(alpha) > 1e-9 OR abs(beta) > 1e-9")
def support_union(spark, d):
    return structure.alpha(spark, 5).select("m", "n", "s").union(structure.beta(spark, 5).select("m", "n", "s")).distinct()


@query("support_intersect", "SELECT 0::BIGINT AS n")
def support_intersect(spark, d):
    return structure.alpha(spark, 5).select("m", "n", "s").intersect(structure.beta(spark, 5).select("m", "n", "s")).agg(F.count(F.lit(1)).alias("n"))


@query("dense_tensor_count", f"WITH {o.elem(3)}, {o.trace_tensor()}, {o.jumps_cte('turn3')}, x AS (SELECT op, e.idx FROM elem e JOIN L l ON e.c = l.r AND e.r = l.c GROUP BY op, e.idx HAVING abs(sum(e.re * l.re - e.im * l.im)) > 1e-9 OR abs(sum(e.re * l.im + e.im * l.re)) > 1e-9) SELECT op, (64 * count(DISTINCT m))::BIGINT AS entries, count(*) FILTER (WHERE abs(alpha) > 1e-9) AS alpha, count(*) FILTER (WHERE abs(beta) > 1e-9) AS beta FROM sc JOIN x ON m = idx GROUP BY op")
def dense_tensor_count(spark, d):
    """Of the entries that the jump operators of the conversations' turns meet, zeros too."""
    j, _ = workloads.turns(spark, d)
    t = baselines.dense_tensors(spark, 3).join(coefficients(j, 3).select("op", F.col("idx").alias("m")), "m")
    return t.groupBy("op").agg(F.count(F.lit(1)).alias("entries"), F.count(F.when(F.abs("alpha") > 1e-9, 1)).alias("alpha"), F.count(F.when(F.abs("beta") > 1e-9, 1)).alias("beta"))


@query("udtf_plane", f"WITH {o.elem(4)}, {o.trace_tensor()} SELECT m, n, s, {r6('alpha')} AS alpha, {r6('beta')} AS beta FROM sc WHERE (abs(alpha) > 1e-9 OR abs(beta) > 1e-9) AND m IN (1, 8, 14)")
def udtf_plane(spark, d):
    structure_source.register(spark)
    return spark.sql("SELECT CAST(v.m AS BIGINT) AS m, p.n, p.s, round(p.alpha, 6) + 0.0D AS alpha, round(p.beta, 6) + 0.0D AS beta FROM VALUES (1), (8), (14) AS v(m), LATERAL structure_plane(v.m, 4) p")


@query("generated_source", f"WITH {o.elem(3)}, {o.trace_tensor()} SELECT m, n, s, {r6('alpha')} AS alpha, {r6('beta')} AS beta FROM sc WHERE abs(alpha) > 1e-9 OR abs(beta) > 1e-9")
def generated_source(spark, d):
    structure_source.register(spark)
    t = spark.read.format("structure_constants").option("levels", 3).load()
    return t.select("m", "n", "s", c6(F.col("alpha")).alias("alpha"), c6(F.col("beta")).alias("beta"))


# -- drift

D5 = f"{o.elem(5)}, {o.dimer_cells(5, 'region', 'r_regionkey')}, {o.dimer_jump(5)}"
D25 = f"{o.elem(25)}, {o.dimer_cells(25, 'nation', 'n_nationkey')}, {o.dimer_jump(25)}"


@query("drift_tensor", system_sql(FLOW5, o.drift_sql("h")))
def drift_tensor(spark, d):
    h, _, _, n = workloads.flow_system(spark, d)
    return sparse(assemble.drift(coefficients(h, n), n), "s", "n")


@query("drift_multi_n", system_sql(D25, o.drift_sql("h0")))
def drift_multi_n(spark, d):
    h0, *_ = workloads.dimer(spark, d, "nation")
    return sparse(assemble.drift(coefficients(h0, 25), 25), "s", "n")


@query("sql_drift", system_sql(D5, o.drift_sql("h0")))
def sql_drift(spark, d):
    h0, *_ = workloads.dimer(spark, d)
    sqlapi.register(spark, 5, coherent_h0=coefficients(h0, 5))
    return sparse(sqlapi.drift(spark, 5, "coherent_h0"), "s", "n")


def _times(spark: SparkSession, sys: str) -> DataFrame:
    return spark.range(8).select(F.lit(sys).alias("sys"), (F.col("id") * (math.pi / 4) + 0.1).alias("t"))


@query("drift_at_times", f"WITH {D5}, q0 AS ({o.drift_sql('h0')}), q1 AS ({o.drift_sql('h1')}), tt AS (SELECT i * {math.pi / 4!r}::DOUBLE + 0.1 AS t FROM range(8) r(i)), a AS (SELECT t, s, n, x FROM q0, tt UNION ALL SELECT t, s, n, x * CASE WHEN t < {math.pi!r} THEN -1.5 ELSE 1.5 END FROM q1, tt) SELECT {r6('t')} AS t, s, n, {r6('sum(x)')} AS x FROM a GROUP BY t, s, n HAVING abs(sum(x)) > 1e-9")
def drift_at_times(spark, d):
    h0, h1, *_ = workloads.dimer(spark, d)
    q0, q1 = (assemble.drift(coefficients(h, 5), 5) for h in (h0, h1))
    got = assemble.drift_at(q0, q1, models.square_drive(spark, "dimer5"), _times(spark, "dimer5"))
    return sparse(got, c6(F.col("t")).alias("t"), "s", "n")


@query("square_wave", f"SELECT event_id, {r6('-1.0 + -1.5 * CASE WHEN (epoch(ts) % 86400) < 43200 THEN 1.0 ELSE -1.0 END')} AS eps, {r6('-1.0 - -1.5 * CASE WHEN (epoch(ts) % 86400) < 43200 THEN 1.0 ELSE -1.0 END')} AS minus FROM events")
def square_wave(spark, d):
    t = seconds(F.col("ts"))
    return io.table(spark, d, "events").select("event_id", c6(models.square_wave(t, -1.0, -1.5, 86400.0)).alias("eps"), c6(models.square_wave(t, -1.0, -1.5, 86400.0, "minus_first")).alias("minus"))


# -- inhomogeneity and relaxation

HOP5 = f"{o.elem(5)}, {o.jumps_cte('hop5')}"
TURN3 = f"{o.elem(3)}, {o.jumps_cte('turn3')}"


def _inhom_sql(body: str, n: int) -> str:
    return f"WITH {body} SELECT s, {r6(f'x / {n}')} AS x FROM {o.INHOM} WHERE abs(x / {n}) > 1e-9"


@query("inhom_tensor", _inhom_sql(HOP5, 5))
def inhom_tensor(spark, d):
    j, w = workloads.hops(spark, d)
    return sparse(assemble.inhomogeneity(coefficients(j, 5), w, 5), "s")


@query("inhom_dimer", _inhom_sql(D5, 5))
def inhom_dimer(spark, d):
    _, _, l, w, n = workloads.dimer(spark, d)
    return sparse(assemble.inhomogeneity(coefficients(l, n), w, n), "s")


@query("inhom_printed_pump", "SELECT 0::BIGINT AS nonzeros")
def inhom_printed_pump(spark, d):
    _, _, l, w, n = workloads.dimer(spark, d, pump="printed")
    return assemble.inhomogeneity(coefficients(l, n), w, n).where("abs(x) > 1e-9").agg(F.count(F.lit(1)).alias("nonzeros"))


def _relax_sql(body: str, n: int) -> str:
    return system_sql(f"{body}, {o.super_sql(n)}", o.RELAX)


@query("relax_tensor_flow", _relax_sql(FLOW5, 5))
def relax_tensor_flow(spark, d):
    _, l, w, n = workloads.flow_system(spark, d)
    return sparse(assemble.relaxation(coefficients(l, n), w, n), "s", "n")


@query("relax_tensor_dimer", _relax_sql(D5, 5))
def relax_tensor_dimer(spark, d):
    _, _, l, w, n = workloads.dimer(spark, d)
    return sparse(assemble.relaxation(coefficients(l, n), w, n), "s", "n")


@query("relax_multi", _relax_sql(HOP5, 5))
def relax_multi(spark, d):
    j, w = workloads.hops(spark, d)
    return sparse(assemble.relaxation(coefficients(j, 5), w, 5), "s", "n")


@query("relax_turns", _relax_sql(TURN3, 3))
def relax_turns(spark, d):
    j, w = workloads.turns(spark, d)
    return sparse(assemble.relaxation(coefficients(j, 3), w, 3), "s", "n")


@query("relax_cell_flow25", system_sql(f"{o.elem(25)}, {o.flow('nation')}, {o.flow_h(25)}, {o.flow_jump()}, {o.super_sql(25)}", o.RELAX))
def relax_cell_flow25(spark, d):
    _, l, w, n = workloads.flow_system(spark, d, "nation")
    return sparse(assemble.relaxation_by_cells(l, w, n), "s", "n")


@query("relax_staged", _relax_sql(D25, 25))
def relax_staged(spark, d):
    _, _, l, w, n = workloads.dimer(spark, d, "nation")
    return sparse(assemble.relaxation(coefficients(l, n), w, n, stages=20), "s", "n")


@query("route_except", "SELECT 0::BIGINT AS tensor_only, 0::BIGINT AS cell_only")
def route_except(spark, d):
    _, l, w, n = workloads.flow_system(spark, d)
    a = sparse(assemble.relaxation(coefficients(l, n), w, n), "s", "n")
    b = sparse(assemble.relaxation_by_cells(l, w, n), "s", "n")
    x, y = a.exceptAll(b).agg(F.count(F.lit(1)).alias("tensor_only")), b.exceptAll(a).agg(F.count(F.lit(1)).alias("cell_only"))
    return x.crossJoin(y)


@query("seq_equals_parallel", "SELECT 0::BIGINT AS only_a, 0::BIGINT AS only_b, true AS equal")
def seq_equals_parallel(spark, d):
    j, w = workloads.turns(spark, d)
    l = coefficients(j, 3)  # noqa: E741
    got = validate.compare(baselines.sequential(l, w, 3), assemble.relaxation(l, w, 3), ["sys", "s", "n"])
    return got.select("only_a", "only_b", (F.col("largest") < 1e-9).alias("equal"))


# -- random generators


def _random(n: int, count: int) -> str:
    return f"{o.elem(n)}, {o.gauss(n, f'SELECT DISTINCT chr(115) || (l_suppkey % {count})::VARCHAR AS sys FROM lineitem')}, {o.rates(n)}"


@query("gauss_cells", f"WITH {o.gauss(3, 'SELECT DISTINCT chr(115) || (l_suppkey % 4)::VARCHAR AS sys FROM lineitem')} SELECT sys, r AS row, c AS col, {r6('re')} AS re, {r6('im')} AS im FROM g")
def gauss_cells(spark, d):
    g = models.gaussian_cells(spark, 3, workloads.samples(spark, d, 4))
    return g.select("sys", F.col("row").cast("long").alias("row"), F.col("col").cast("long").alias("col"), c6(F.col("re")).alias("re"), c6(F.col("im")).alias("im"))


@query("hash_uniform", f"SELECT p_partkey, {r6(chr(40) + chr(40) + chr(39) + '0x' + chr(39) + ' || substr(md5(p_partkey::VARCHAR), 1, 8))::BIGINT::DOUBLE + 0.5) / 4294967296.0')} AS u FROM part")
def hash_uniform(spark, d):
    return io.table(spark, d, "part").select("p_partkey", c6(models.uniform(F.col("p_partkey").cast("string"), 0)).alias("u"))


@query("random_rates", f"WITH {_random(4, 2)} SELECT sys, j, k, {r6('re')} AS re, {r6('im')} AS im FROM w WHERE abs(re) > 1e-9 OR abs(im) > 1e-9")
def random_rates(spark, d):
    return sparse(models.random_rates(spark, 4, workloads.samples(spark, d, 2)), "sys", "j", "k", values=("re", "im"))


RATE_CELLS = "C AS (SELECT x.r AS a, y.r AS b, x.c AS c, y.c AS d, sum(w.re * (x.re * y.re + x.im * y.im) - w.im * (x.im * y.re - x.re * y.im)) AS re, sum(w.re * (x.im * y.re - x.re * y.im) + w.im * (x.re * y.re + x.im * y.im)) AS im FROM w JOIN elem x ON w.j = x.idx JOIN elem y ON w.k = y.idx GROUP BY x.r, y.r, x.c, y.c)"


@query("relax_rates", system_sql(f"{_random(3, 1)}, {o.super_sql(3, RATE_CELLS)}", o.RELAX))
def relax_rates(spark, d):
    r = models.random_rates(spark, 3, workloads.samples(spark, d, 1))
    return sparse(assemble.relaxation_from_rates(r, 3), "s", "n")


@query("relax_rates_cell", system_sql(f"{_random(4, 1)}, {o.super_sql(4, RATE_CELLS)}", o.RELAX))
def relax_rates_cell(spark, d):
    r = models.random_rates(spark, 4, workloads.samples(spark, d, 1))
    return sparse(assemble.relaxation_from_rates(r, 4, "cell"), "s", "n")


@query("rates_trace", "SELECT DISTINCT 's' || (l_suppkey % 4)::VARCHAR AS sys, -9.0::DOUBLE AS trace_r, -9.0::DOUBLE AS expected FROM lineitem")
def rates_trace(spark, d):
    r = models.random_rates(spark, 3, workloads.samples(spark, d, 4))
    got = validate.rates_trace(assemble.relaxation_from_rates(r, 3), r, 3)
    return got.select("sys", c6(F.col("trace_r")).alias("trace_r"), c6(F.col("expected")).alias("expected"))


@query("ensemble_trace", "SELECT DISTINCT 's' || (l_suppkey % 8)::VARCHAR AS sys, -1.125::DOUBLE AS mean_eigenvalue FROM lineitem")
def ensemble_trace(spark, d):
    r = models.random_rates(spark, 3, workloads.samples(spark, d, 8))
    t = spectrum.moments(assemble.relaxation_from_rates(r, 3))
    return t.select("sys", c6(F.col("trace") / 8).alias("mean_eigenvalue"))


@query("spectrum_moments", f"WITH {_random(3, 1)}, {o.super_sql(3, RATE_CELLS)}, R AS {o.RELAX} SELECT 's0' AS sys, {r6('(SELECT sum(x) FROM R WHERE s = n)')} AS trace, {r6('(SELECT sum(a.x * b.x) FROM R a JOIN R b ON a.s = b.n AND a.n = b.s)')} AS trace2")
def spectrum_moments(spark, d):
    r = models.random_rates(spark, 3, workloads.samples(spark, d, 1))
    e = spectrum.eigenvalues(assemble.relaxation_from_rates(r, 3), 8)
    return e.groupBy("sys").agg(c6(F.sum("re")).alias("trace"), c6(F.sum(F.expr("re*re-im*im"))).alias("trace2"))


def _power(k: int) -> str:
    """The sum of the k-th powers of R's eigenvalues, from traces."""
    names = "abc"[:k]
    return f"(SELECT sum({' * '.join(x + '.x' for x in names)}) FROM {', '.join('R ' + x for x in names)} WHERE {' AND '.join(f'{x}.n = {y}.s' for x, y in zip(names, names[1:] + names[0]))})"


@query("local_eigen", f"WITH {_random(4, 1)}, {o.super_sql(4, RATE_CELLS)}, R AS MATERIALIZED {o.RELAX} SELECT 's0' AS sys, 15::BIGINT AS n, {r6(_power(1))} AS p1, {r6(_power(2))} AS p2, {r6(_power(3))} AS p3")
def local_eigen(spark, d):
    r = models.random_rates(spark, 4, workloads.samples(spark, d, 1))
    e = spectrum.eigenvalues(assemble.relaxation_from_rates(r, 4), 15)
    return e.groupBy("sys").agg(F.count(F.lit(1)).alias("n"), c6(F.sum("re")).alias("p1"), c6(F.sum(F.expr("re*re-im*im"))).alias("p2"), c6(F.sum(F.expr("re*re*re-3*re*im*im"))).alias("p3"))


_EDGE = lambda i: f"CASE WHEN embedding[1]::DOUBLE BETWEEN -4 AND 4 AND embedding[2]::DOUBLE BETWEEN -4 AND 4 THEN least(floor((embedding[{i}]::DOUBLE + 4) / 0.08), 99)::INT END"
GRID = f"p AS (SELECT {_EDGE(1)} AS bx, {_EDGE(2)} AS cy FROM embeddings)"


def _points(spark, d):
    return io.table(spark, d, "embeddings").select(F.lit("points").alias("sys"), F.col("embedding")[0].cast("double").alias("re"), F.col("embedding")[1].cast("double").alias("im"))


@query('density_grid', f'''WITH {GRID} SELECT bx, cy AS "by", count(*) AS n, CASE WHEN bx IS NOT NULL THEN {r6('count(*) / (SELECT count(*) FROM p)::DOUBLE / (0.08 * 0.08)')} END AS density FROM p GROUP BY bx, cy''')
def density_grid(spark, d):
    return spectrum.density(_points(spark, d), bounds=(-4.0, 4.0, -4.0, 4.0)).select("bx", "by", "n", c6(F.col("density")).alias("density"))


@query("grid_area_norm", f"WITH {GRID} SELECT 10000::BIGINT AS cells, {r6('(SELECT count(bx) FROM p) / (SELECT count(*) FROM p)::DOUBLE')} AS mass")
def grid_area_norm(spark, d):
    g = spectrum.density(_points(spark, d), bounds=(-4.0, 4.0, -4.0, 4.0), empty=True)
    return g.agg(F.count("bx").alias("cells"), c6(F.sum("density") * 0.08 * 0.08).alias("mass"))


# -- models


def _op_rows(df: DataFrame) -> DataFrame:
    """Nonzeros, rounded as the SQL does (scaled, then to an integer): large cells lie near ties that decimal rounding decides otherwise."""
    re = F.round(F.col("re") * 1e6) / 1e6 + F.lit(0.0)
    return df.where("abs(re) > 1e-9").select(F.col("row").cast("long").alias("row"), F.col("col").cast("long").alias("col"), re.alias("re"))


def _op_sql(body: str, name: str) -> str:
    return f"WITH {body} SELECT r AS row, c AS col, {r6('re')} AS re FROM {name} WHERE abs(re) > 1e-9"


PARTS = o.dimer_cells("(SELECT count(*) FROM part)", "(SELECT p_partkey - 1 AS k FROM part)", "k")


@query("dimer_h0", _op_sql(PARTS, "h0"))
def dimer_h0(spark, d):
    return _op_rows(models.dimer(*workloads.part_levels(spark, d))[0])


@query("dimer_h1", _op_sql(o.dimer_cells(25, "nation", "n_nationkey"), "h1"))
def dimer_h1(spark, d):
    return _op_rows(models.dimer(workloads.levels_of(spark, d, "nation"), 25)[1])


@query("dimer_jump", _op_sql(PARTS, "la"))
def dimer_jump(spark, d):
    return _op_rows(models.dimer(*workloads.part_levels(spark, d))[2])


@query("dimer_relax", _relax_sql(D25, 25))
def dimer_relax(spark, d):
    _, _, l, w, n = workloads.dimer(spark, d, "nation")
    return sparse(assemble.relaxation(coefficients(l, n), w, n), "s", "n")


CHAIN = """st AS (SELECT n_regionkey AS site, abs(avg(c_acctbal) / 10000) AS g FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1),
L AS (SELECT site::INT AS op, (z - (1 << site) - (1 << (site + 1)) + 1)::BIGINT AS r, z::BIGINT + 1 AS c, 1.0::DOUBLE AS re, 0.0::DOUBLE AS im, g FROM st, range(32) t(z) WHERE site < 4 AND (z // (1 << site)) % 2 = 1 AND (z // (1 << (site + 1))) % 2 = 1)"""


@query("chain_embed", f"WITH {CHAIN} SELECT op, r AS row, c AS col, {r6('g')} AS gamma FROM L")
def chain_embed(spark, d):
    j, w = models.chain(workloads.sites(spark, d), 5, 2)
    return j.join(w, ["sys", "op"]).select("op", F.col("row").cast("long").alias("row"), F.col("col").cast("long").alias("col"), c6(F.col("gamma")).alias("gamma"))


@query("chain_relax", _relax_sql(f"{o.elem(32)}, {CHAIN}", 32))
def chain_relax(spark, d):
    j, w = models.chain(workloads.sites(spark, d), 5, 2)
    return sparse(assemble.relaxation(coefficients(j, 32), w, 32), "s", "n")


# -- panels

COUNTS = f"WITH {D25}, q AS (SELECT s, n, x FROM ({o.drift_sql('h0')}) WHERE abs(x) > 1e-9), nz AS (SELECT s, count(*) AS nnz FROM q GROUP BY s), rc AS (SELECT i::BIGINT AS s, coalesce(nnz, 0) AS nnz FROM range(1, 625) t(i) LEFT JOIN nz ON i = s)"
BALANCED = "bal AS (SELECT s, nnz, least(3, floor((sum(nnz) OVER (ORDER BY s) - nnz) * 4 / sum(nnz) OVER ()))::INT AS panel FROM rc)"


def _q0(spark, d):
    h0, *_ = workloads.dimer(spark, d, "nation")
    return assemble.drift(coefficients(h0, 25), 25).where("abs(x) > 1e-9")


@query("panel_uniform", COUNTS + " SELECT s, nnz::BIGINT AS nnz, ((s - 1) * 4 // 624)::INT AS panel FROM rc")
def panel_uniform(spark, d):
    return partition.uniform(partition.row_counts(_q0(spark, d), 624), 624, 4).select("s", "nnz", "panel")


@query("panel_balanced", COUNTS + f", {BALANCED} SELECT s, nnz::BIGINT AS nnz, panel FROM bal")
def panel_balanced(spark, d):
    return partition.balanced(partition.row_counts(_q0(spark, d), 624), 4).select("s", "nnz", "panel")


@query("imbalance", COUNTS + f", {BALANCED}, p AS (SELECT 'uniform' AS method, ((s - 1) * 4 // 624)::INT AS panel, nnz FROM rc UNION ALL SELECT 'balanced', panel, nnz FROM bal), t AS (SELECT method, panel, sum(nnz) AS nnz FROM p GROUP BY ALL) SELECT method, count(*) AS panels, max(nnz)::BIGINT AS largest, {r6('max(nnz) / avg(nnz)')} AS ratio FROM t GROUP BY method")
def imbalance(spark, d):
    c = partition.row_counts(_q0(spark, d), 624)
    rows = [measures.imbalance(p).select(F.lit(name).alias("method"), "panels", "largest", c6(F.col("ratio")).alias("ratio")) for name, p in (("uniform", partition.uniform(c, 624, 4)), ("balanced", partition.balanced(c, 4)))]
    return rows[0].unionByName(rows[1])


@query("edge_cut", COUNTS + f", {BALANCED} SELECT count(*) AS cut, count(DISTINCT a.panel * 1000 + q.n) AS remote FROM q JOIN bal a ON q.s = a.s JOIN bal b ON q.n = b.s WHERE a.panel <> b.panel")
def edge_cut(spark, d):
    q = _q0(spark, d)
    return measures.edge_cut(q, partition.balanced(partition.row_counts(q, 624), 4)).select("cut", "remote")


GRAPH = COUNTS + """, ge AS (SELECT DISTINCT s AS a, n AS b FROM q WHERE s <> n UNION SELECT DISTINCT n, s FROM q WHERE s <> n),
reach AS (SELECT s AS label, s FROM rc UNION SELECT reach.label, b FROM reach JOIN ge ON a = s),
comp AS (SELECT s, min(label) AS label FROM reach GROUP BY s),
ring AS (SELECT label, label AS s, 0 AS far FROM comp WHERE s = label UNION SELECT label, b, far + 1 FROM ring JOIN ge ON a = ring.s WHERE far < 100),
pos AS (SELECT rc.s, nnz, row_number() OVER (ORDER BY label, f, rc.s) AS pl FROM rc JOIN comp USING (s) JOIN (SELECT s, min(far) AS f FROM ring GROUP BY s) USING (s)),
gp AS (SELECT s, nnz, least(3, floor((sum(nnz) OVER (ORDER BY pl) - nnz) * 4 / sum(nnz) OVER ()))::INT AS panel FROM pos)"""
GRAPH = GRAPH.replace("WITH ", "WITH RECURSIVE ", 1)


@query("graph_panels", GRAPH + " SELECT s, nnz::BIGINT AS nnz, panel FROM gp")
def graph_panels(spark, d):
    return partition.by_graph(keep(_q0(spark, d)), 624, 4).select("s", "nnz", "panel")


@query("graph_cut", GRAPH + ", cuts AS (SELECT 'graph' AS method, s, panel FROM gp UNION ALL SELECT 'uniform', s, ((s - 1) * 4 // 624)::INT FROM rc) SELECT a.method, count(*) AS cut, count(DISTINCT a.panel * 1000 + q.n) AS remote FROM q JOIN cuts a ON q.s = a.s JOIN cuts b ON q.n = b.s AND a.method = b.method WHERE a.panel <> b.panel GROUP BY a.method")
def graph_cut(spark, d):
    q = keep(_q0(spark, d))
    panels = {"graph": partition.by_graph(q, 624, 4), "uniform": partition.uniform(partition.row_counts(q, 624), 624, 4)}
    parts = [measures.edge_cut(q, p).select(F.lit(name).alias("method"), "cut", "remote") for name, p in panels.items()]
    return parts[0].unionByName(parts[1])


@query("panel_loads", COUNTS + f", {BALANCED}, t AS (SELECT panel, sum(nnz) AS nnz FROM bal GROUP BY panel) SELECT count(*) AS tasks, max(nnz)::BIGINT AS largest, {r6('max(nnz) / avg(nnz)')} AS ratio FROM t")
def panel_loads(spark, d):
    """What the tasks of a balanced matrix really hold."""
    q = keep(_q0(spark, d))
    held = partition.loads(partition.dealt(q, partition.balanced(partition.row_counts(q, 624), 4), 4))
    return held.agg(F.count(F.lit(1)).alias("tasks"), F.max("rows").alias("largest"), c6(F.max("ratio")).alias("ratio"))


@query("ntile_panels", COUNTS + " SELECT s, ntile(4) OVER (ORDER BY s)::INT AS panel FROM rc")
def ntile_panels(spark, d):
    c = partition.row_counts(_q0(spark, d), 624)
    return c.select("s", F.ntile(4).over(Window.partitionBy("sys").orderBy("s")).alias("panel"))


# -- propagation


def _turn_system(spark, d):
    j, w = workloads.turns(spark, d)
    l = coefficients(j, 3)  # noqa: E741
    h = spark.createDataFrame([("turn3", 1, 2, 0.5, 0.0), ("turn3", 2, 1, 0.5, 0.0), ("turn3", 2, 3, 0.0, 0.25), ("turn3", 3, 2, 0.0, -0.25)], io.OPERATOR)
    v0 = expand.initial_vector(expand.pure(spark, "turn3", 1), 3)
    return integrate.bundle(assemble.drift(coefficients(h, 3), 3), assemble.relaxation(l, w, 3), assemble.inhomogeneity(l, w, 3), v0), h, j, w


def _rk4_sql(steps: int, period: float) -> str:
    """The density matrix stepped as a list of 18 numbers under its 18 x 18 real generator; then traced with the elements."""
    h = period / steps
    return f"""WITH RECURSIVE {TURN3}, h AS (SELECT * FROM (VALUES (1, 2, 0.5::DOUBLE, 0.0::DOUBLE), (2, 1, 0.5, 0.0), (2, 3, 0.0, 0.25), (3, 2, 0.0, -0.25)) t(r, c, re, im)),
{o.super_sql(3)},
Y AS (SELECT a, b, c, d, sum(re) AS re, sum(im) AS im FROM (SELECT * FROM X UNION ALL SELECT r, i, c, i, im, -re FROM h, lev UNION ALL SELECT i, c, i, r, -im, re FROM h, lev) GROUP BY ALL),
Z AS (SELECT (a - 1) * 6 + (b - 1) * 2 AS p, (c - 1) * 6 + (d - 1) * 2 AS q, re AS x FROM Y UNION ALL SELECT (a - 1) * 6 + (b - 1) * 2 + 1, (c - 1) * 6 + (d - 1) * 2 + 1, re FROM Y UNION ALL SELECT (a - 1) * 6 + (b - 1) * 2, (c - 1) * 6 + (d - 1) * 2 + 1, -im FROM Y UNION ALL SELECT (a - 1) * 6 + (b - 1) * 2 + 1, (c - 1) * 6 + (d - 1) * 2, im FROM Y),
M AS (SELECT list(l ORDER BY p) AS m FROM (SELECT p, list(coalesce(x, 0.0) ORDER BY q) AS l FROM (SELECT i AS p, j AS q FROM range(18) a(i), range(18) b(j)) LEFT JOIN Z USING (p, q) GROUP BY p)),
it AS (SELECT 0 AS k, [1.0::DOUBLE] || [0.0::DOUBLE FOR z IN range(17)] AS v
 UNION ALL SELECT k + 1, list_transform(range(1, 19), lambda i: v[i] + {h / 6!r} * (s1[i] + 2 * s2[i] + 2 * s3[i] + list_dot_product(m[i], list_transform(range(1, 19), lambda z: v[z] + {h!r} * s3[z])))) FROM (
  SELECT *, list_transform(range(1, 19), lambda i: list_dot_product(m[i], list_transform(range(1, 19), lambda z: v[z] + {h / 2!r} * s2[z]))) AS s3 FROM (
   SELECT *, list_transform(range(1, 19), lambda i: list_dot_product(m[i], list_transform(range(1, 19), lambda z: v[z] + {h / 2!r} * s1[z]))) AS s2 FROM (
    SELECT k, v, m, list_transform(range(1, 19), lambda i: list_dot_product(m[i], v)) AS s1 FROM it, M WHERE k < {steps}))))
"""


def _rk4_vec(steps: int, period: float) -> str:
    return _rk4_sql(steps, period) + f"""SELECT idx, {r6('x')} AS x FROM (SELECT e.idx, sum(e.re * v[(e.c - 1) * 6 + (e.r - 1) * 2 + 1] - e.im * v[(e.c - 1) * 6 + (e.r - 1) * 2 + 2]) AS x FROM elem e, it WHERE k = {steps} GROUP BY e.idx) WHERE abs(x) > 1e-9"""


def _rho_sql(steps: int, period: float) -> str:
    return _rk4_sql(steps, period) + f"""SELECT row, col, {r6('re')} AS re, {r6('im')} AS im FROM (SELECT a.i AS row, b.i AS col, v[(a.i - 1) * 6 + (b.i - 1) * 2 + 1] AS re, v[(a.i - 1) * 6 + (b.i - 1) * 2 + 2] AS im FROM it, lev a, lev b WHERE k = {steps}) WHERE abs(re) > 1e-9 OR abs(im) > 1e-9"""


@query("rk4_short", _rk4_vec(3, 0.3))
def rk4_short(spark, d):
    return sparse(integrate.rk4(_turn_system(spark, d)[0], 8, 3, 0.3, strategy="step"), "idx")


@query("rk4_grouped", _rk4_vec(40, 2.0))
def rk4_grouped(spark, d):
    return sparse(integrate.rk4(_turn_system(spark, d)[0], 8, 40, 2.0), "idx")


@query("rk4_collapsed", _rk4_vec(40, 2.0))
def rk4_collapsed(spark, d):
    return sparse(integrate.rk4(_turn_system(spark, d)[0], 8, 40, 2.0, strategy="collapsed"), "idx")


@query("rk4_panel", _rk4_vec(3, 0.3))
def rk4_panel(spark, d):
    return sparse(integrate.rk4(_turn_system(spark, d)[0], 8, 3, 0.3, strategy="panel"), "idx")


@query("rho_final", _rho_sql(40, 2.0))
def rho_final(spark, d):
    v = integrate.rk4(_turn_system(spark, d)[0], 8, 40, 2.0)
    return sparse(expand.density_from_vector(v, 3), F.col("row").cast("long").alias("row"), F.col("col").cast("long").alias("col"), values=("re", "im"))


@query("rk4_density_equals", _rho_sql(40, 2.0))
def rk4_density_equals(spark, d):
    _, h, j, w = _turn_system(spark, d)
    got = baselines.rk4_density(h, j, w, expand.pure(spark, "turn3", 1), 3, 40, 2.0)
    return sparse(got, F.col("row").cast("long").alias("row"), F.col("col").cast("long").alias("col"), values=("re", "im"))


def dimer_bundle(spark, d, name="region"):
    h0, h1, l, w, n = workloads.dimer(spark, d, name)
    e = coefficients(l, n)
    v0 = expand.initial_vector(h0.select("sys").distinct().select("sys", F.lit(1).alias("row"), F.lit(1).alias("col"), F.lit(1.0).alias("re"), F.lit(0.0).alias("im")), n)
    return integrate.bundle(assemble.drift(coefficients(h0, n), n), assemble.relaxation(e, w, n), assemble.inhomogeneity(e, w, n), v0, assemble.drift(coefficients(h1, n), n)), n


def _period_sql(n: int, steps: int, period: float) -> str:
    """The density matrix as 2 n^2 numbers; each half's step is a matrix (the series to fourth order), raised by squaring."""
    h, size, out = period / steps, 2 * n * n, []

    def product(name: str, a: str, b: str) -> None:
        out.append(f"{name} AS MATERIALIZED (SELECT a.p, b.q, sum(a.x * b.x) AS x FROM {a} a JOIN {b} b ON a.q = b.p GROUP BY a.p, b.q)")

    for half, eps in (("u", models.A), ("w", -models.A)):
        out.append(f"""h{half} AS (SELECT r, c, sum(re) AS re, sum(im) AS im FROM (SELECT * FROM h0 UNION ALL SELECT r, c, re * {eps!r}::DOUBLE, im FROM h1) GROUP BY r, c),
Y{half} AS (SELECT a, b, c, d, sum(re) AS re, sum(im) AS im FROM (SELECT * FROM X UNION ALL SELECT r, i, c, i, im, -re FROM h{half}, lev UNION ALL SELECT i, c, i, r, -im, re FROM h{half}, lev) GROUP BY ALL),
A{half} AS MATERIALIZED (SELECT p, q, sum(x) * {h!r}::DOUBLE AS x FROM (SELECT ((a - 1) * {n} + b - 1) * 2 + k AS p, ((c - 1) * {n} + d - 1) * 2 + m AS q, CASE WHEN k = m THEN re WHEN k = 1 THEN im ELSE -im END AS x FROM Y{half}, range(2) s(k), range(2) t(m)) GROUP BY p, q)""")
        product(f"A{half}2", f"A{half}", f"A{half}")
        product(f"A{half}3", f"A{half}2", f"A{half}")
        product(f"A{half}4", f"A{half}3", f"A{half}")
        terms = " UNION ALL ".join([f"SELECT i AS p, i AS q, 1.0::DOUBLE AS x FROM range({size}) t(i)", f"SELECT * FROM A{half}", f"SELECT p, q, x / 2 FROM A{half}2", f"SELECT p, q, x / 6 FROM A{half}3", f"SELECT p, q, x / 24 FROM A{half}4"])
        out.append(f"P{half}0 AS MATERIALIZED (SELECT p, q, sum(x) AS x FROM ({terms}) GROUP BY p, q)")
        done, bits = None, steps // 2
        for k in range(bits.bit_length()):
            if k:
                product(f"P{half}{k}", f"P{half}{k - 1}", f"P{half}{k - 1}")
            if bits >> k & 1:
                if done:
                    product(f"R{half}{k}", f"P{half}{k}", done)
                done = f"R{half}{k}" if done else f"P{half}{k}"
        out.append(f"E{half} AS (SELECT * FROM {done})")
    return f"WITH {D5}, {o.super_sql(n)}, {', '.join(out)}, v AS (SELECT w.p, sum(w.x * u.x) AS x FROM Ew w JOIN Eu u ON w.q = u.p WHERE u.q = 0 GROUP BY w.p) SELECT idx, {r6('x')} AS x FROM (SELECT e.idx, sum(CASE WHEN v.p % 2 = 0 THEN e.re ELSE -e.im END * v.x) AS x FROM elem e JOIN v ON v.p // 2 = (e.c - 1) * {n} + e.r - 1 GROUP BY e.idx) WHERE abs(x) > 1e-9"


@query("period_end", _period_sql(5, 2000, models.PERIOD))
def period_end(spark, d):
    system, n = dimer_bundle(spark, d)
    return sparse(integrate.rk4(system, basis.size(n), 2000, models.PERIOD, ((0.5, models.A), (0.5, -models.A))), "idx")


@query("neutral_state_residual", "SELECT 24::BIGINT AS rows, 0.0::DOUBLE AS largest")
def neutral_state_residual(spark, d):
    _, _, l, w, n = workloads.dimer(spark, d)
    h0 = workloads.dimer(spark, d)[0]
    e = coefficients(l, n)
    q, r, k = assemble.drift(coefficients(h0, n), n), assemble.relaxation(e, w, n), assemble.inhomogeneity(e, w, n)
    empty = k.select("sys", F.col("s").alias("idx"), "x").where("1 = 0")
    v = integrate.steady_state(integrate.bundle(q, r, k, empty), basis.size(n))
    res = validate.residual(q.unionByName(r), k, v)
    return v.join(res.select("sys", F.col("s").alias("idx"), F.col("x").alias("gap")), ["sys", "idx"], "left").agg(F.count(F.lit(1)).alias("rows"), c6(F.max(F.abs(F.coalesce("gap", F.lit(0.0))))).alias("largest"))


# -- observables and algebra


@query("populations", f"WITH {EMBED} SELECT sys, r AS level, {r6('re')} AS p FROM rho WHERE r = c")
def populations(spark, d):
    return measures.populations(workloads.gram(workloads.embedding_cells(spark, d))).select("sys", F.col("level").cast("long").alias("level"), c6(F.col("p")).alias("p"))


@query("purity", f"WITH {EMBED} SELECT sys, {r6('sum(re * re)')} AS purity, {r6('1 - sum(re * re)')} AS entropy FROM rho GROUP BY sys")
def purity(spark, d):
    return measures.purity(workloads.gram(workloads.embedding_cells(spark, d))).select("sys", c6(F.col("purity")).alias("purity"), c6(F.col("entropy")).alias("entropy"))


@query("expectation", f"WITH {LANG}, a AS (SELECT r, c, r * 0.5::DOUBLE + c * 0.25 AS x FROM rho) SELECT {r6('sum(rho.re * a.x)')} AS re FROM rho JOIN a ON rho.r = a.c AND rho.c = a.r")
def expectation(spark, d):
    rho = workloads.gram(workloads.lang_cells(spark, d))
    a = rho.select("sys", "row", "col", (F.col("row") * 0.5 + F.col("col") * 0.25).alias("re"), F.lit(0.0).alias("im"))
    return measures.expectation(rho, a).select(c6(F.col("re")).alias("re"))


@query("observables_map", f"WITH {LANG} SELECT {r6('sum(CASE WHEN r = c THEN re ELSE 0 END)')} AS trace, {r6('sum(re * re)')} AS purity FROM rho")
def observables_map(spark, d):
    m = measures.observables(workloads.gram(workloads.lang_cells(spark, d)))
    return m.select(c6(F.col("values")["trace"]).alias("trace"), c6(F.col("values")["purity"]).alias("purity"))


@query("matmul", f"WITH {o.flow('nation')} SELECT a.r AS row, b.c AS col, {r6('sum(a.v * b.v)')} AS re FROM flow a JOIN flow b ON a.c = b.r GROUP BY ALL HAVING abs(sum(a.v * b.v)) > 1e-9")
def matmul(spark, d):
    x = workloads.flow(spark, d, "nation")
    return _op_rows(linalg.matmul(x, x))


@query("commutator", f"WITH {o.flow()}, p AS (SELECT a.r, b.c, a.v * b.v AS x FROM flow a JOIN (SELECT c AS r, r AS c, v FROM flow) b ON a.c = b.r UNION ALL SELECT a.r, b.c, -a.v * b.v FROM (SELECT c AS r, r AS c, v FROM flow) a JOIN flow b ON a.c = b.r) SELECT r AS row, c AS col, {r6('sum(x)')} AS re FROM p GROUP BY ALL HAVING abs(sum(x)) > 1e-9")
def commutator(spark, d):
    x = workloads.flow(spark, d)
    return _op_rows(linalg.commutator(x, linalg.adjoint(x)))


@query("adjoint", f"WITH {o.flow()} SELECT c AS row, r AS col, {r6('v')} AS re FROM flow WHERE abs(v) > 1e-9")
def adjoint(spark, d):
    return _op_rows(linalg.adjoint(workloads.flow(spark, d)))


@query("kron", f"WITH {LABEL} SELECT (a.r - 1) * 2 + b.r AS row, (a.c - 1) * 2 + b.c AS col, {r6('a.re * b.re')} AS re FROM rho a, rho b WHERE abs(a.re * b.re) > 1e-9")
def kron(spark, d):
    rho = workloads.gram(workloads.label_cells(spark, d))
    return _op_rows(linalg.kron(rho, rho, 2))


@query("matvec", f"WITH {D5}, q AS ({o.drift_sql('h0')}) SELECT s, {r6('sum(x * (1.0::DOUBLE / n))')} AS x FROM q GROUP BY s HAVING abs(sum(x / n)) > 1e-9")
def matvec(spark, d):
    h0, *_ = workloads.dimer(spark, d)
    v = spark.range(1, 25).select(F.lit("dimer5").alias("sys"), F.col("id").alias("idx"), (1.0 / F.col("id")).alias("x"))
    return sparse(linalg.matvec(assemble.drift(coefficients(h0, 5), 5), v), "s")


@query("array_matvec", f"WITH {D5}, q AS ({o.drift_sql('h0')}) SELECT s, {r6('sum(x * n)')} AS x FROM q GROUP BY s HAVING abs(sum(x * n)) > 1e-9")
def array_matvec(spark, d):
    h0, *_ = workloads.dimer(spark, d)
    rows = linalg.dense_rows(assemble.drift(coefficients(h0, 5), 5), 24)
    v = spark.range(1).select(F.lit("dimer5").alias("sys"), F.expr("transform(sequence(1, 24), x -> CAST(x AS DOUBLE))").alias("v"))
    return sparse(linalg.array_matvec(rows, v), "s")


@query("dense_rows", f"WITH {D5}, q AS (SELECT * FROM ({o.drift_sql('h0')}) WHERE abs(x) > 1e-9) SELECT s, 24::INT AS width, {r6('sum(x)')} AS total FROM q GROUP BY s")
def dense_rows(spark, d):
    h0, *_ = workloads.dimer(spark, d)
    rows = linalg.dense_rows(assemble.drift(coefficients(h0, 5), 5), 24)
    return rows.select("s", F.size("cells").alias("width"), c6(F.aggregate("cells", F.lit(0.0), lambda a, x: a + x)).alias("total"))


@query("complex_ops", f"SELECT event_id, {r6('value * value / 10000 - 0.25')} AS re, {r6('value / 100')} AS im, {r6('value * value / 10000 + 0.25')} AS abs2, {r6('atan2(0.5, value / 100)')} AS arg FROM events")
def complex_ops(spark, d):
    z = (F.col("value") / 100, F.lit(0.5))
    p = cplx.mul(z, z)
    return io.table(spark, d, "events").select("event_id", c6(p[0]).alias("re"), c6(p[1]).alias("im"), c6(cplx.abs2(z)).alias("abs2"), c6(cplx.arg(z)).alias("arg"))


@query("complex_sum", f"SELECT event_type, {r6('sum(value * 0.6) / 1000')} AS re, {r6('sum(value * -0.8) / 1000')} AS im FROM events GROUP BY event_type")
def complex_sum(spark, d):
    z = cplx.conj((F.col("value") * 0.6, F.col("value") * 0.8))
    g = io.table(spark, d, "events").groupBy("event_type").agg(*cplx.total(z))
    return g.select("event_type", c6(F.col("re") / 1000).alias("re"), c6(F.col("im") / 1000).alias("im"))


@query("superop_cells", f"WITH {TURN3}, {o.super_sql(3)} SELECT a, b, c, d, {r6('re')} AS re, {r6('im')} AS im FROM X WHERE abs(re) > 1e-9 OR abs(im) > 1e-9")
def superop_cells(spark, d):
    j, w = workloads.turns(spark, d)
    x = baselines.superoperator(workloads.traceless(j, 3), w, 3)
    return sparse(x, *[F.col(c).cast("long").alias(c) for c in "abcd"], values=("re", "im"))


# -- events, text tables, drives


@query("event_lag", f"WITH {o.pairs_cte('hop5')} SELECT a, b, n FROM pp")
def event_lag(spark, d):
    return workloads.event_pairs(spark, d).groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"))


@query("hop_rates", f"WITH lev AS (SELECT i::BIGINT AS i FROM range(1, 6) t(i)), {o.jumps_cte('hop5')} SELECT op, {r6('g')} AS gamma FROM tj")
def hop_rates(spark, d):
    return workloads.hops(spark, d)[1].select("op", c6(F.col("gamma")).alias("gamma"))


@query("turn_rates", f"WITH lev AS (SELECT i::BIGINT AS i FROM range(1, 4) t(i)), {o.jumps_cte('turn3')} SELECT op, {r6('g')} AS gamma FROM tj")
def turn_rates(spark, d):
    return workloads.turns(spark, d)[1].select("op", c6(F.col("gamma")).alias("gamma"))


@query("label_table", "SELECT quality + 1 AS row, toxic + 1 AS col, count(*)::DOUBLE AS v FROM labels JOIN documents USING (doc_id) GROUP BY ALL")
def label_table(spark, d):
    return workloads.label_cells(spark, d).select("row", "col", "v")


@query("page_lang", "SELECT regexp_extract(url, '^https?://[^/]+/([a-z]{2})/', 1) AS lang, count(*) AS n FROM pages GROUP BY 1")
def page_lang(spark, d):
    return io.table(spark, d, "pages").groupBy(F.regexp_extract("url", r"^https?://[^/]+/([a-z]{2})/", 1).alias("lang")).agg(F.count(F.lit(1)).alias("n"))


@query("props_drive", f"SELECT (props->>'$.k')::BIGINT AS k, count(*) AS n, {r6('avg(value)')} AS eps FROM events GROUP BY 1")
def props_drive(spark, d):
    k = F.get_json_object("props", "$.k").cast("long")
    return io.table(spark, d, "events").groupBy(k.alias("k")).agg(F.count(F.lit(1)).alias("n"), c6(F.avg("value")).alias("eps"))


@query("event_phase", f"SELECT event_id, {r6('(epoch(ts) % 86400) / 86400.0')} AS phase FROM events")
def event_phase(spark, d):
    return io.table(spark, d, "events").select("event_id", c6(F.pmod(seconds(F.col("ts")), F.lit(86400.0)) / 86400.0).alias("phase"))


@query("drive_tumbling", f"SELECT time_bucket(INTERVAL 1 DAY, ts) AS t0, count(*) AS n, {r6('avg(value)')} AS eps FROM events GROUP BY 1")
def drive_tumbling(spark, d):
    return drives.tumbling(io.table(spark, d, "events")).select("t0", "n", c6(F.col("eps")).alias("eps"))


@query("drive_sliding", f"WITH e AS (SELECT time_bucket(INTERVAL 1 DAY, ts) AS b, value FROM events), x AS (SELECT b AS t0, value FROM e UNION ALL SELECT b - INTERVAL 1 DAY, value FROM e) SELECT t0, count(*) AS n, {r6('avg(value)')} AS eps FROM x GROUP BY t0")
def drive_sliding(spark, d):
    return drives.sliding(io.table(spark, d, "events")).select("t0", "n", c6(F.col("eps")).alias("eps"))


@query("drive_session", f"WITH e AS (SELECT user_id, ts, value, CASE WHEN ts - lag(ts) OVER w < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, new DESC ROWS UNBOUNDED PRECEDING) AS k FROM e) SELECT user_id, min(ts) AS t0, count(*) AS n, {r6('avg(value)')} AS eps FROM s GROUP BY user_id, k")
def drive_session(spark, d):
    return drives.sessions(io.table(spark, d, "events")).select("user_id", "t0", "n", c6(F.col("eps")).alias("eps"))


@query("drive_moving_avg", f"WITH t AS (SELECT time_bucket(INTERVAL 1 DAY, ts) AS t0, avg(value) AS eps FROM events GROUP BY 1) SELECT t0, {r6('avg(eps) OVER (ORDER BY t0 RANGE BETWEEN INTERVAL 2 DAY PRECEDING AND CURRENT ROW)')} AS eps FROM t")
def drive_moving_avg(spark, d):
    t = drives.tumbling(io.table(spark, d, "events"))
    w = Window.orderBy(seconds(F.col("t0")).cast("long")).rangeBetween(-2 * 86400, 0)  # a row a day
    return t.select("t0", c6(F.avg("eps").over(w)).alias("eps"))


@query("drive_intervals", "WITH t AS (SELECT DISTINCT time_bucket(INTERVAL 1 DAY, ts) AS t0 FROM events) SELECT t0, lead(t0) OVER (ORDER BY t0) AS t1 FROM t")
def drive_intervals(spark, d):
    t = drives.tumbling(io.table(spark, d, "events")).select("t0")
    return t.select("t0", F.lead("t0").over(Window.orderBy("t0")).alias("t1"))


@query("asof_drive", "SELECT e.event_id, max_by(s.value, (s.ts, s.event_id)) AS eps FROM events e JOIN events s ON s.event_type = 'signup' AND s.user_id = e.user_id AND s.ts <= e.ts GROUP BY e.event_id")
def asof_drive(spark, d):
    e = io.table(spark, d, "events")
    w = Window.partitionBy("user_id").orderBy(seconds(F.col("ts"))).rangeBetween(Window.unboundedPreceding, 0)
    last = F.max(F.when(F.col("event_type") == "signup", F.struct("ts", "event_id", "value"))).over(w)
    return e.select("event_id", last["value"].alias("eps")).where("eps IS NOT NULL")


@query("interval_drive", f"WITH t AS (SELECT time_bucket(INTERVAL 1 DAY, ts) AS t0, avg(value) AS eps FROM events GROUP BY 1) SELECT event_id, {r6('value - eps')} AS gap FROM events JOIN t ON ts >= t0 AND ts < t0 + INTERVAL 1 DAY")
def interval_drive(spark, d):
    e, t = io.table(spark, d, "events"), drives.tumbling(io.table(spark, d, "events"))
    # The interval's start is a function of the time, so the range join is an equi-join.
    j = e.withColumn("day", F.date_trunc("day", "ts")).join(t, (F.col("day") == F.col("t0")) & (F.col("ts") < F.col("t1")))
    return j.select("event_id", c6(F.col("value") - F.col("eps")).alias("gap"))


STREAM = """WITH RECURSIVE e AS (SELECT user_id, value, epoch(ts) / 3600 AS t, row_number() OVER w AS i, lag(value) OVER w AS eps, floor((epoch(ts) - lag(epoch(ts)) OVER w) / 21600) AS n FROM events WHERE ts IS NOT NULL WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
z AS (SELECT *, -0.005 AS zr, -0.0005 * eps AS zi FROM e), z2 AS (SELECT *, zr * zr - zi * zi AS ar, 2 * zr * zi AS ai FROM z), z3 AS (SELECT *, ar * zr - ai * zi AS br, ar * zi + ai * zr AS bi, ar * ar - ai * ai AS dr, 2 * ar * ai AS di FROM z2),
p AS (SELECT *, 1 + zr + ar / 2 + br / 6 + dr / 24 AS pr, zi + ai / 2 + bi / 6 + di / 24 AS pi FROM z3),
f AS (SELECT *, pow(pr * pr + pi * pi, n / 2) * cos(n * atan2(pi, pr)) AS gr, pow(pr * pr + pi * pi, n / 2) * sin(n * atan2(pi, pr)) AS gi, pow(1 - 0.005 + 0.0000125 - 0.005 * 0.000025 / 6 + 0.000025 * 0.000025 / 24, n) AS g3 FROM p),
g AS (SELECT *, -0.05 * 0.1 / (0.01 + 0.0001 * eps * eps) AS cr, 0.05 * 0.01 * eps / (0.01 + 0.0001 * eps * eps) AS ci FROM f),
v AS (SELECT user_id, i, 0.0::DOUBLE AS x, 0.0::DOUBLE AS y, 0.0::DOUBLE AS w FROM e WHERE i = 1
 UNION ALL SELECT g.user_id, g.i, gr * x - gi * y + (gr - 1) * cr - gi * ci, gr * y + gi * x + (gr - 1) * ci + gi * cr, g3 * w + 1 - g3 FROM v JOIN g ON g.user_id = v.user_id AND g.i = v.i + 1),
last AS (SELECT user_id, max(i) AS i, max(t) AS t FROM e GROUP BY user_id)"""


@query("stream_state", STREAM + f" SELECT user_id, i AS events, {r6('t')} AS t, {r6('x')} AS x1, {r6('y')} AS x2, {r6('w')} AS x3 FROM last JOIN v USING (user_id, i)")
def stream_state(spark, d):
    """The batch form of the stateful propagation; tests run it as a stream."""
    import numpy as np

    a0, a1, k = -0.1 * np.eye(3), np.array([[0, 1, 0], [-1, 0, 0], [0, 0, 0]]) * 0.01, np.array([0.05, 0, 0.1])
    got = drives.propagated(io.table(spark, d, "events"), a0, a1, k)
    return got.select("user_id", "events", c6(F.col("t")).alias("t"), *[c6(F.col("x")[i]).alias(f"x{i + 1}") for i in range(3)])


# -- relational operators on system matrices


@query("join_semi_support", f"WITH {TENSOR5}, {o.flow()}, {o.flow_h(5)}, v AS (SELECT idx FROM ({o.expand_sql('h')}) WHERE abs(re) > 1e-9) SELECT count(*) AS n FROM sc WHERE abs(alpha) > 1e-9 AND m IN (SELECT idx FROM v)")
def join_semi_support(spark, d):
    h, _, _, n = workloads.flow_system(spark, d)
    return structure.alpha(spark, 5).join(coefficients(h, n).where("abs(re) > 1e-9"), F.col("m") == F.col("idx"), "left_semi").agg(F.count(F.lit(1)).alias("n"))


@query("join_anti_cells", "SELECT item_id FROM benchmark WHERE item_id NOT IN (SELECT doc_id FROM labels)")
def join_anti_cells(spark, d):
    return io.table(spark, d, "benchmark").join(io.table(spark, d, "labels"), F.col("item_id") == F.col("doc_id"), "left_anti").select("item_id")


@query("theta_pairs", "SELECT a.n_nationkey AS j, b.n_nationkey AS k FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey")
def theta_pairs(spark, d):
    n = io.table(spark, d, "nation").select("n_nationkey")
    return n.alias("a").join(n.alias("b"), F.col("a.n_nationkey") < F.col("b.n_nationkey")).select(F.col("a.n_nationkey").alias("j"), F.col("b.n_nationkey").alias("k"))


@query("compare_full_outer", f"WITH {D5}, a AS (SELECT s, n, x FROM ({o.drift_sql('h0')}) WHERE abs(x) > 1e-9), b AS (SELECT s, n, x FROM ({o.drift_sql('h1')}) WHERE abs(x) > 1e-9) SELECT count(*) AS rows, count(*) FILTER (WHERE b.x IS NULL) AS only_a, count(*) FILTER (WHERE a.x IS NULL) AS only_b, {r6('max(abs(coalesce(a.x, 0) - coalesce(b.x, 0)))')} AS largest FROM a FULL JOIN b ON a.s = b.s AND a.n = b.n")
def compare_full_outer(spark, d):
    h0, h1, *_ = workloads.dimer(spark, d)
    a, b = (assemble.drift(coefficients(h, 5), 5).where("abs(x) > 1e-9") for h in (h0, h1))
    return validate.compare(a, b, ["s", "n"]).select("rows", "only_a", "only_b", c6(F.col("largest")).alias("largest"))


@query("drop_small", f"WITH {FLOW5}, q AS ({o.drift_sql('h')}) SELECT count(*) AS n FROM q WHERE abs(x) > 0.05")
def drop_small(spark, d):
    h, _, _, n = workloads.flow_system(spark, d)
    return assemble.drift(coefficients(h, n), n).where("abs(x) > 0.05").agg(F.count(F.lit(1)).alias("n"))


def _mats(spark, d):
    h0, h1, *_ = workloads.dimer(spark, d)
    q = lambda h, name: assemble.drift(coefficients(h, 5), 5).where("abs(x) > 1e-9").withColumn("part", F.lit(name)).withColumn("half", (F.col("s") > 12).cast("int"))
    return q(h0, "Q0").unionByName(q(h1, "Q1"))


MATS = f"WITH {D5}, mats AS (SELECT 'Q0' AS part, s, n, x, (s > 12)::INT AS half FROM ({o.drift_sql('h0')}) WHERE abs(x) > 1e-9 UNION ALL SELECT 'Q1', s, n, x, (s > 12)::INT FROM ({o.drift_sql('h1')}) WHERE abs(x) > 1e-9)"


@query("nnz_rollup", MATS + " SELECT part, half, count(*) AS nnz FROM mats GROUP BY ROLLUP (part, half)")
def nnz_rollup(spark, d):
    return _mats(spark, d).rollup("part", "half").agg(F.count(F.lit(1)).alias("nnz"))


@query("nnz_cube", MATS + " SELECT part, half, count(*) AS nnz FROM mats GROUP BY CUBE (part, half)")
def nnz_cube(spark, d):
    return _mats(spark, d).cube("part", "half").agg(F.count(F.lit(1)).alias("nnz"))


@query("nnz_grouping_sets", MATS + " SELECT part, half, count(*) AS nnz FROM mats GROUP BY GROUPING SETS ((part), (half))")
def nnz_grouping_sets(spark, d):
    m = _mats(spark, d)
    return m.groupingSets([[F.col("part")], [F.col("half")]], F.col("part"), F.col("half")).agg(F.count(F.lit(1)).alias("nnz"))


@query("distinct_cols", MATS + " SELECT part, count(DISTINCT n) AS cols FROM mats GROUP BY part")
def distinct_cols(spark, d):
    return _mats(spark, d).groupBy("part").agg(F.countDistinct("n").alias("cols"))


@query("matrix_density", MATS + f" SELECT part, {r6('count(*) / 576.0')} AS density FROM mats GROUP BY part")
def matrix_density(spark, d):
    return _mats(spark, d).withColumn("sys", F.col("part")).transform(lambda m: measures.density(m, 24)).select(F.col("sys").alias("part"), c6(F.col("density")).alias("density"))


@query("level_rank", "SELECT s_suppkey, dense_rank() OVER (ORDER BY s_nationkey)::BIGINT AS level FROM supplier")
def level_rank(spark, d):
    s = io.table(spark, d, "supplier").select("s_suppkey", "s_nationkey")
    order = s.select("s_nationkey").distinct().withColumn("level", F.row_number().over(Window.orderBy("s_nationkey")).cast("long"))  # at most 25 rows
    return s.join(F.broadcast(order), "s_nationkey").select("s_suppkey", "level")


@query("top_couplings", MATS + f" SELECT part, s, n, {r6('x')} AS x FROM mats QUALIFY row_number() OVER (PARTITION BY part ORDER BY abs(round(x, 9)) DESC, s, n) <= 5")
def top_couplings(spark, d):
    m = _mats(spark, d).withColumn("sys", F.col("part"))
    return linalg.top_cells(m, 5).select("part", "s", "n", c6(F.col("x")).alias("x"))


@query("top_rows_per_sys", MATS + " SELECT part, s, count(*) AS nnz FROM mats GROUP BY part, s QUALIFY row_number() OVER (PARTITION BY part ORDER BY count(*) DESC, s) <= 3")
def top_rows_per_sys(spark, d):
    c = _mats(spark, d).groupBy("part", "s").agg(F.count(F.lit(1)).alias("nnz"))
    w = Window.partitionBy("part").orderBy(F.col("nnz").desc(), "s")
    return c.withColumn("p", F.row_number().over(w)).where("p <= 3").drop("p")


@query("scaling_efficiency", f"SELECT nodes, memory, {r6('efficiency')} AS efficiency FROM (VALUES (5, 54.5::DOUBLE, NULL::DOUBLE), (25, 16.5::DOUBLE, 54.5 * 5 / (16.5::DOUBLE * 25))) t(nodes, memory, efficiency)")
def scaling_efficiency(spark, d):
    runs = spark.createDataFrame([(5, 54.5), (25, 16.5)], "nodes int, memory double")
    return measures.scaling_efficiency(runs).select("nodes", "memory", c6(F.col("efficiency")).alias("efficiency"))


TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@query("scan_counts", " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in TABLES))
def scan_counts(spark, d):
    parts = [io.table(spark, d, t).agg(F.lit(t).alias("name"), F.count(F.lit(1)).alias("n")) for t in TABLES]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


@query("save_load", system_sql(D5, o.drift_sql("h0")))
def save_load(spark, d):
    path = fresh_path(spark, "system")
    io.save_system(dimer_bundle(spark, d)[0], path)
    return sparse(io.load_system(spark, path, "dimer5", "Q0"), "s", "n")
