"""Variants, baselines, invariants and workloads beyond the basic queries; each next to SQL of another route."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from coherent.operators import assemble, basis, expand, integrate, measures, models, partition, spectrum, structure, validate
from coherent.plans import oracles as o
from coherent.plans import workloads
from coherent.plans.queries import D5, D25, FLOW5, RATE_CELLS, TENSOR5, _points, _q0, _random, _relax_sql, _turn_system, c6, coefficients, query, r6, sparse
from coherent.sources import io
from coherent.sources.store import fresh_path, keep
from coherent.streaming import drives

# -- stored tensors, routes, stages


@query("stored_tensor", f"WITH {TENSOR5} SELECT m, n, s, {r6('alpha')} AS alpha, {r6('beta')} AS beta FROM sc WHERE abs(alpha) > 1e-9 OR abs(beta) > 1e-9")
def stored_tensor(spark, d):
    t = structure.materialise(spark, fresh_path(spark, "tensor"), 5)
    return t.select("m", "n", "s", c6(F.col("alpha")).alias("alpha"), c6(F.col("beta")).alias("beta"))


SAME = "SELECT 0::BIGINT AS only_a, 0::BIGINT AS only_b, true AS equal"


def _same(a, b, keys):
    return validate.compare(a, b, keys).select("only_a", "only_b", (F.col("largest") < 1e-9).alias("equal"))


@query("stored_equals_fly", SAME)
def stored_equals_fly(spark, d):
    """The drift from stored planes, which are read and joined, and from planes made on the fly."""
    h, _, _, n = workloads.flow_system(spark, d)
    c = coefficients(h, n)
    t = structure.materialise(spark, fresh_path(spark, "tensor"), n).where("abs(alpha) > 1e-12")
    stored = t.join(c.select("sys", F.col("idx").alias("m"), "re"), "m").groupBy("sys", "s", "n").agg(F.sum(F.col("re") * F.col("alpha")).alias("x")).where("abs(x) > 1e-12")
    return _same(stored, assemble.drift(c, n), ["sys", "s", "n"])


@query("staged_equals_single", SAME)
def staged_equals_single(spark, d):
    _, _, l, w, n = workloads.dimer(spark, d)
    c = coefficients(l, n)
    return _same(assemble.relaxation(c, w, n, stages=7), assemble.relaxation(c, w, n), ["sys", "s", "n"])


@query("relax_auto", _relax_sql(FLOW5, 5))
def relax_auto(spark, d):
    _, l, w, n = workloads.flow_system(spark, d)
    return sparse(assemble.relaxation(coefficients(l, n), w, n, route="auto"), "s", "n")


@query("relax_diagonalised", f"WITH {_random(3, 1)}, {o.super_sql(3, RATE_CELLS)} SELECT s, n, {r6('x')} AS x FROM {o.RELAX} WHERE abs(x) > 1e-9")
def relax_diagonalised(spark, d):
    """Jump operators from the eigenvectors of a rate matrix give the R of the rates."""
    l, w = models.diagonalise_rates(models.random_rates(spark, 3, workloads.samples(spark, d, 1)), 3)  # noqa: E741
    return sparse(assemble.relaxation(keep(l), keep(w), 3), "s", "n")


@query("inhom_rates", f"WITH {_random(3, 1)}, {RATE_CELLS}, k0 AS (SELECT a AS r, b AS c, sum(CASE WHEN c = d THEN re ELSE 0 END) AS re, sum(CASE WHEN c = d THEN im ELSE 0 END) AS im FROM C GROUP BY a, b UNION ALL SELECT d, c, -sum(CASE WHEN a = b THEN re ELSE 0 END), -sum(CASE WHEN a = b THEN im ELSE 0 END) FROM C GROUP BY d, c), kk AS (SELECT r, c, sum(re) AS re, sum(im) AS im FROM k0 GROUP BY r, c) SELECT s, {r6('x / 3')} AS x FROM (SELECT e.idx AS s, sum(e.re * o.re - e.im * o.im) AS x FROM elem e JOIN kk o ON e.c = o.r AND e.r = o.c GROUP BY e.idx) WHERE abs(x / 3) > 1e-9")
def inhom_rates(spark, d):
    r = models.random_rates(spark, 3, workloads.samples(spark, d, 1))
    return sparse(assemble.inhomogeneity_from_rates(r, 3), "s")


# -- drift of another system


@query("drift_regions", f"WITH {D5}, q AS ({o.drift_sql('h0')}) SELECT s, n, {r6('x')} AS x FROM q WHERE abs(x) > 1e-9")
def drift_regions(spark, d):
    h0, _, _, _, n = workloads.dimer(spark, d)
    return sparse(assemble.drift(coefficients(h0, n), n), "s", "n")


# -- invariants


@query("state_invariants", "SELECT 'turn3' AS sys, 1.0::DOUBLE AS trace, 0.0::DOUBLE AS hermitian_gap, true AS positive")
def state_invariants(spark, d):
    v = integrate.rk4(_turn_system(spark, d)[0], 8, 40, 2.0)
    facts = validate.state_facts(expand.density_from_vector(keep(v), 3), 3)
    return facts.select("sys", c6(F.col("trace")).alias("trace"), c6(F.col("hermitian_gap")).alias("hermitian_gap"), (F.col("smallest") > -1e-9).alias("positive"))


@query("conjugate_spectrum", "SELECT 's0' AS sys, 0::BIGINT AS unmatched, true AS decaying")
def conjugate_spectrum(spark, d):
    r = models.random_rates(spark, 4, workloads.samples(spark, d, 1))
    e = keep(spectrum.eigenvalues(assemble.relaxation_from_rates(r, 4), 15))
    return validate.conjugate_gap(e).join(e.groupBy("sys").agg((F.max("re") < 1e-9).alias("decaying")), "sys")


@query("drift_antisymmetric", "SELECT 'dimer25' AS sys, 0.0::DOUBLE AS gap")
def drift_antisymmetric(spark, d):
    return validate.antisymmetric_gap(_q0(spark, d)).select("sys", c6(F.col("gap")).alias("gap"))


# -- spectra


@query("power_traces", f"WITH {_random(3, 1)}, {o.super_sql(3, RATE_CELLS)}, R AS MATERIALIZED {o.RELAX} SELECT 's0' AS sys, {r6('(SELECT sum(a.x * b.x * c.x) FROM R a, R b, R c WHERE a.n = b.s AND b.n = c.s AND c.n = a.s)')} AS trace3")
def power_traces(spark, d):
    r = assemble.relaxation_from_rates(models.random_rates(spark, 3, workloads.samples(spark, d, 1)), 3)
    return r.groupBy("sys").agg(spectrum.power_trace(3, 8)("s", "n", "x").alias("trace3")).select("sys", c6(F.col("trace3")).alias("trace3"))


@query("spectrum_grid", "SELECT 's0' AS sys, 63::BIGINT AS points, 1.0::DOUBLE AS mass, -1.015873::DOUBLE AS mean FROM range(1)")
def spectrum_grid(spark, d):
    """Eigenvalues of a random generator of eight levels on the grid: all are on it, and their mean is -N^2 / (N^2 - 1)."""
    r = models.random_rates(spark, 8, workloads.samples(spark, d, 1), local=True)
    e = keep(spectrum.eigenvalues(assemble.relaxation_from_rates(r, 8, "cell"), 63))
    ends = e.agg(F.min("re"), F.max("re"), F.min("im"), F.max("im")).first()
    area = (ends[1] - ends[0]) * (ends[3] - ends[2]) / 10_000
    g = spectrum.density(e).groupBy("sys").agg(F.sum("n").alias("points"), c6(F.sum("density") * area).alias("mass"))
    return g.join(e.groupBy("sys").agg(c6(F.avg("re")).alias("mean")), "sys")


@query("boundary_points", f"SELECT {r6('embedding[1]::DOUBLE')} AS re, {r6('embedding[2]::DOUBLE')} AS im FROM embeddings")
def boundary_points(spark, d):
    path = fresh_path(spark, "boundary")
    _points(spark, d).select("re", "im").write.csv(path)
    return spectrum.load_boundary(spark, path).select(c6(F.col("re")).alias("re"), c6(F.col("im")).alias("im"))


@query("ensemble_pools", "SELECT DISTINCT 's' || (l_suppkey % 4)::VARCHAR AS sys, -9.0::DOUBLE AS trace FROM lineitem")
def ensemble_pools(spark, d):
    """Samples side by side, each assembled over all tasks."""
    names = sorted(r[0] for r in workloads.samples(spark, d, 4).collect())
    own = [spark.createDataFrame([(x,)], "sys string") for x in names]
    done = integrate.ensemble(own, lambda s: keep(spectrum.moments(assemble.relaxation_from_rates(models.random_rates(spark, 3, s), 3))))
    out = done[0]
    for x in done[1:]:
        out = out.unionByName(x)
    return out.select("sys", c6(F.col("trace")).alias("trace"))


# -- chains of random local dissipators


def _gaussian(key: str, part: str) -> str:
    u = lambda i: f"((('0x' || substr(md5({key}), {1 + 8 * i}, 8))::BIGINT::DOUBLE + 0.5) / 4294967296.0::DOUBLE)"
    return f"sqrt(-ln({u(0)})) * {part}({2 * math.pi!r}::DOUBLE * {u(1)})"


def _chain_sql(body: int, count: int = 5) -> str:
    """Cells of random operators on windows of `body` of the regions in a ring: other bits are equal in row and column."""
    size, levels = 1 << body, 1 << count
    bit = lambda x, b: f"(({x} // (1 << ((site + {b}) % {count}))) % 2)"
    local = lambda x: " + ".join(f"{bit(x, b)} * {1 << b}" for b in range(body)) + " + 1"
    others = " AND ".join(f"{bit('y', b)} = {bit('z', b)}" for b in range(body, count))
    key = "'chain:chain:' || site || ':' || p || ':' || q"
    return f"""st AS (SELECT n_regionkey AS site, abs(avg(c_acctbal) / 10000) AS g FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1),
lo AS (SELECT site, g, p, q, {_gaussian(key, 'cos')} AS re, {_gaussian(key, 'sin')} AS im FROM st, range(1, {size + 1}) a(p), range(1, {size + 1}) b(q)),
ze AS (SELECT lo.site, g, p, q, re - CASE WHEN p = q THEN t ELSE 0 END AS re, im - CASE WHEN p = q THEN u ELSE 0 END AS im FROM lo JOIN (SELECT site, sum(re) / {size} AS t, sum(im) / {size} AS u FROM lo WHERE p = q GROUP BY site) USING (site)),
L AS (SELECT site::INT AS op, y::BIGINT + 1 AS r, z::BIGINT + 1 AS c, re, im, g FROM (SELECT *, {local('y')} AS p, {local('z')} AS q FROM st, range({levels}) a(y), range({levels}) b(z) WHERE {others}) JOIN (SELECT site, p, q, re, im FROM ze) USING (site, p, q))"""


for _body in (1, 2, 3):

    @query(f"chain_random_{_body}", f"WITH {_chain_sql(_body)} SELECT op, r AS row, c AS col, {r6('re')} AS re, {r6('im')} AS im, {r6('g')} AS gamma FROM L WHERE abs(re) > 1e-9 OR abs(im) > 1e-9")
    def chain_random(spark, d, body=_body):
        j, w = models.random_chain(workloads.sites(spark, d), 5, body, boundary="ring")
        return sparse(j.join(w, ["sys", "op"]), "op", F.col("row").cast("long").alias("row"), F.col("col").cast("long").alias("col"), values=("re", "im", "gamma"))


@query("chain_random_relax", f"WITH {_chain_sql(1)} SELECT {r6('-sum(g * (re * re + im * im)) * 32')} AS trace FROM L")
def chain_random_relax(spark, d):
    """R of a random chain of one-site operators, 32 levels; its trace is -N times the operators' weighted norms."""
    j, w = models.random_chain(workloads.sites(spark, d), 5, 1, boundary="ring")
    r = assemble.relaxation(coefficients(j, 32), w, 32)
    return r.where("s = n").agg(c6(F.sum("x")).alias("trace"))


# -- qubits and drives from tables

QUBIT = f"{o.elem(2)}, xq AS (SELECT quality + 1 AS r, toxic + 1 AS c, count(*)::DOUBLE AS v FROM labels JOIN documents USING (doc_id) GROUP BY ALL), xt AS (SELECT sum(v) AS t FROM xq WHERE r <> c), L AS (SELECT (r - 1)::INT AS op, r::BIGINT AS r, c::BIGINT AS c, 1.0::DOUBLE AS re, 0.0::DOUBLE AS im, v / t AS g FROM xq, xt WHERE r <> c)"


@query("qubit_relax", _relax_sql(QUBIT, 2))
def qubit_relax(spark, d):
    """A qubit that jumps between the labels' levels, at the shares of the off-diagonal counts."""
    x = workloads.label_cells(spark, d).where("row <> col")
    total = x.agg(F.sum("v").alias("t"))
    x = keep(x.crossJoin(total))  # one row on the right
    jumps = x.select("sys", (F.col("row") - 1).cast("int").alias("op"), F.col("row").cast("int").alias("row"), F.col("col").cast("int").alias("col"), F.lit(1.0).alias("re"), F.lit(0.0).alias("im"))
    w = x.select("sys", (F.col("row") - 1).cast("int").alias("op"), (F.col("v") / F.col("t")).alias("gamma"))
    return sparse(assemble.relaxation(coefficients(jumps, 2), w, 2), "s", "n")


WINDOWS = "t AS (SELECT time_bucket(INTERVAL 1 DAY, ts) AS t0, avg(value) AS v FROM events GROUP BY 1), b AS (SELECT min(epoch(t0)) AS lo, max(epoch(t0)) + 86400 AS hi, min(v) AS least, max(v) AS most FROM t), dr AS (SELECT (epoch(t0) - lo) / (hi - lo) AS t0, (epoch(t0) + 86400 - lo) / (hi - lo) AS t1, 2 * (v - least) / (most - least) - 1 AS eps FROM t, b)"


def _event_drive(spark, d):
    return drives.rescaled(drives.tumbling(io.table(spark, d, "events")), "qubit")


@query("drive_rescaled", f"WITH {WINDOWS} SELECT {r6('t0')} AS t0, {r6('t1')} AS t1, {r6('eps')} AS eps FROM dr")
def drive_rescaled(spark, d):
    return _event_drive(spark, d).select(*[c6(F.col(c)).alias(c) for c in ("t0", "t1", "eps")])


_SERIES = "zr, zi, 1 + zr + (zr * zr - zi * zi) / 2 + (zr * zr * zr - 3 * zr * zi * zi) / 6 + (zr * zr * zr * zr - 6 * zr * zr * zi * zi + zi * zi * zi * zi) / 24 AS pr, zi + zr * zi + (3 * zr * zr * zi - zi * zi * zi) / 6 + (zr * zr * zr * zi - zr * zi * zi * zi) / 6 AS pi"


@query("drive_propagated", f"WITH {WINDOWS}, z AS (SELECT h, 20.0::DOUBLE / count(*) OVER () / 10 * -0.05 AS zr, -20.0::DOUBLE / count(*) OVER () / 10 * 0.7 * eps AS zi, count(*) OVER () AS k FROM (SELECT *, 1 AS h FROM dr)), p AS (SELECT {_SERIES}, k FROM z), c AS (SELECT 0.5 * exp(sum(10 * ln(sqrt(pr * pr + pi * pi)))) AS size, sum(10 * atan2(pi, pr)) AS angle FROM p), g AS (SELECT pow(1 + y + y * y / 2 + y * y * y / 6 + y * y * y * y / 24, 10 * k) AS a FROM (SELECT -0.1 * 20.0::DOUBLE / count(*) / 10 AS y, count(*) AS k FROM dr)) SELECT {r6('sqrt(2.0::DOUBLE) * size * cos(angle)')} AS x1, {r6('-sqrt(2.0::DOUBLE) * size * sin(angle)')} AS x2, {r6('(1 - a) / sqrt(2.0::DOUBLE)')} AS x3 FROM c, g")
def drive_propagated(spark, d):
    """A decaying qubit whose level distance follows the events' daily means, ten steps a day."""
    drive = [(r.t1 - r.t0, r.eps) for r in _event_drive(spark, d).orderBy("t0").collect()]  # a row a day
    h, l, w = models.decaying_qubit(spark, 0.7, 0.1)  # noqa: E741
    l = coefficients(l, 2)  # noqa: E741
    plus = spark.createDataFrame([("qubit", i, j, 0.5, 0.0) for i in (1, 2) for j in (1, 2)], "sys string, row int, col int, re double, im double")
    q = assemble.drift(coefficients(h, 2), 2)
    system = integrate.bundle(q.where("1 = 0"), assemble.relaxation(l, w, 2), assemble.inhomogeneity(l, w, 2), expand.initial_vector(plus, 2), q)
    days = len(drive)
    end = keep(integrate.rk4(system, 3, 10 * days, 20.0, tuple((1 / days, eps) for _, eps in drive)))
    at = lambda i: c6(F.max(F.when(F.col("idx") == i, F.col("x")))).alias(f"x{i}")
    return end.agg(at(1), at(2), at(3))


@query("stream_sink", "SELECT c_nationkey AS nation, count(*) AS n FROM events LEFT JOIN customer ON user_id = c_custkey GROUP BY 1")
def stream_sink(spark, d):
    """The events as a stream, each joined to its customer, every batch written once; then counted."""
    events = io.table(spark, d, "events")
    customers = io.table(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_nationkey")
    path = fresh_path(spark, "sink")
    events.write.parquet(f"{path}/in")  # a folder, as a file source needs
    stream = spark.readStream.schema(events.schema).parquet(f"{path}/in")
    joined = drives.with_static(stream, customers, "user_id")
    q = joined.writeStream.foreachBatch(drives.upsert(f"{path}/out", "batch")).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(f"{path}/out").groupBy(F.col("c_nationkey").alias("nation")).agg(F.count(F.lit(1)).alias("n"))


# -- aggregates and measures


@query("event_spread", f"SELECT event_type, {r6('quantile_cont(value, 0.5)')} AS median, {r6('quantile_cont(value, 0.9)')} AS p90, {r6('sum(value::DECIMAL(28, 10))::DOUBLE')} AS total FROM events GROUP BY event_type")
def event_spread(spark, d):
    """Percentiles, and a sum without rounding errors."""
    e = io.table(spark, d, "events").groupBy("event_type")
    return e.agg(c6(F.percentile("value", 0.5)).alias("median"), c6(F.percentile("value", 0.9)).alias("p90"), c6(F.sum(F.col("value").cast("decimal(28,10)")).cast("double")).alias("total"))


@query("event_pivot", "SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'view') AS view FROM events GROUP BY user_id")
def event_pivot(spark, d):
    return io.table(spark, d, "events").groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1))).na.fill(0)


@query("approx_users", "SELECT true AS near")
def approx_users(spark, d):
    e = io.table(spark, d, "events").agg(F.approx_count_distinct("user_id", 0.02).alias("a"), F.countDistinct("user_id").alias("b"))
    return e.select((F.abs(F.col("a") - F.col("b")) <= 0.1 * F.col("b")).alias("near"))


@query("memory_rows", f"WITH {D25}, q AS (SELECT * FROM ({o.drift_sql('h0')}) WHERE abs(x) > 1e-9) SELECT count(*) AS rows, true AS measured FROM q")
def memory_rows(spark, d):
    """Bytes that each task's worker receives; their rows add up to the matrix."""
    m = measures.partition_bytes(_q0(spark, d))
    return m.agg(F.sum("rows").alias("rows"), (F.sum("bytes") >= 8 * F.sum("rows")).alias("measured"))


@query("flow_density", f"WITH {o.flow('nation')} SELECT count(*) AS cells, {r6('count(*) / 625.0')} AS density FROM flow WHERE abs(v) > 1e-12")
def flow_density(spark, d):
    """How dense the flow between nations is: about two fifths at the smallest scale, full beyond."""
    x = workloads.flow(spark, d, "nation").where("abs(re) > 1e-12")
    return x.agg(F.count(F.lit(1)).alias("cells"), c6(F.count(F.lit(1)) / 625.0).alias("density"))


@query("rk4_dense", "SELECT 's0' AS sys, 63::BIGINT AS rows, true AS contracts")
def rk4_dense(spark, d):
    """A dense random generator of eight levels propagated by panels of rows; the state stays in the ball of density operators."""
    r = models.random_rates(spark, 8, workloads.samples(spark, d, 1), local=True)
    k = assemble.inhomogeneity_from_rates(r, 8)
    r = assemble.relaxation_from_rates(r, 8, "cell")
    v0 = expand.initial_vector(expand.pure(spark, "s0", 1), 8)
    system = integrate.bundle(r.where("1 = 0"), r, k, v0)
    v = integrate.rk4(system, basis.size(8), 4, 0.4, strategy="panel")
    return v.groupBy("sys").agg(F.count(F.lit(1)).alias("rows"), (F.sum(F.col("x") * F.col("x")) <= 1 - 1 / 8 + 1e-9).alias("contracts"))


@query("neutral_iterative", "SELECT 24::BIGINT AS rows, true AS equal")
def neutral_iterative(spark, d):
    h0, _, l, w, n = workloads.dimer(spark, d)
    c = coefficients(l, n)
    k = assemble.inhomogeneity(c, w, n)
    system = keep(integrate.bundle(assemble.drift(coefficients(h0, n), n), assemble.relaxation(c, w, n), k, k.select("sys", F.col("s").alias("idx"), "x").where("1 = 0")))
    a, b = (integrate.steady_state(system, basis.size(n), m) for m in ("direct", "iterative"))
    return a.join(b.withColumnRenamed("x", "y"), ["sys", "idx"]).agg(F.count(F.lit(1)).alias("rows"), (F.max(F.abs(F.col("x") - F.col("y"))) < 1e-8).alias("equal"))


@query("panels_dealt", "SELECT 'largest_first' AS method, 4::BIGINT AS panels, true AS even")
def panels_dealt(spark, d):
    c = partition.row_counts(_q0(spark, d), 624)
    got = measures.imbalance(partition.largest_first(c, 4))
    return got.select(F.lit("largest_first").alias("method"), "panels", (F.col("ratio") < 1.05).alias("even"))
