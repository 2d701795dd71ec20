"""Hand values, invariants, equal routes and strategies, hostile input."""

import math
import uuid

import numpy as np
import pytest
from pyspark.sql import functions as F

from coherent.functions import checks
from coherent.operators import assemble, baselines, basis, expand, integrate, linalg, measures, models, partition, spectrum, structure, validate
from coherent.sources import io, structure_source
from coherent.sources.store import keep
from coherent.streaming import drives

D = "/root/testdata/sf0.001"


def as_dict(df, *keys, value="x"):
    return {tuple(r[k] for k in keys) if len(keys) > 1 else r[keys[0]]: r[value] for r in df.collect()}


def test_index_is_a_bijection(spark):
    rows = basis.catalogue(spark, 7).collect()
    assert sorted(r.idx for r in rows) == list(range(1, 49))
    assert len({(r.fam, r.j, r.k) for r in rows}) == 48
    assert basis.catalogue(spark, 2000).agg(F.max("idx"), F.max(F.when(F.col("fam") == "S", F.col("k")))).first()[:] == (3_999_999, 2000)


@pytest.mark.parametrize("n", [2, 3, 4])
def test_closed_forms_equal_traces_and_counts(spark, n):
    a = structure.tensor(spark, n)
    b = structure.by_trace(basis.elements(spark, n))
    for c in ("alpha", "beta"):
        assert validate.compare(a, b, ["m", "n", "s"], c).first().largest < 1e-12
    got = a.agg(F.count(F.when(F.abs("alpha") > 1e-12, 1)), F.count(F.when(F.abs("beta") > 1e-12, 1))).first()
    assert tuple(got) == structure.counts(n)


def test_decaying_qubit(spark):
    omega, gamma = 0.7, 0.3
    h, l, w = models.decaying_qubit(spark, omega, gamma)  # noqa: E741
    hv, lv = expand.expand(h, 2), expand.expand(l, 2)
    assert as_dict(hv, "idx", value="re") == pytest.approx({3: omega / math.sqrt(2)})
    q = as_dict(assemble.drift(hv, 2), "s", "n")
    assert q == pytest.approx({(2, 1): omega, (1, 2): -omega})
    r = as_dict(assemble.relaxation(lv, w, 2), "s", "n")
    assert r == pytest.approx({(1, 1): -gamma / 2, (2, 2): -gamma / 2, (3, 3): -gamma})
    k = as_dict(assemble.inhomogeneity(lv, w, 2), "s")
    assert k == pytest.approx({3: gamma / math.sqrt(2)})
    system = integrate.bundle(assemble.drift(hv, 2), assemble.relaxation(lv, w, 2), assemble.inhomogeneity(lv, w, 2), expand.initial_vector(expand.pure(spark, "qubit", 2), 2)).persist()
    assert as_dict(integrate.steady_state(system, 3), "idx")[3] == pytest.approx(1 / math.sqrt(2))
    got = {s: as_dict(integrate.rk4(system, 3, 4, 0.4, strategy=s), "idx") for s in integrate.STRATEGIES}
    for s in integrate.STRATEGIES[1:]:
        assert all(got[s].get(i, 0.0) == pytest.approx(got["grouped"][i], abs=1e-12) for i in (1, 2, 3)), s
    exact = (1 - 2 * math.exp(-gamma * 0.4)) / math.sqrt(2)
    assert got["grouped"][3] == pytest.approx(exact, abs=1e-6)


def test_step_halving_has_order_four():
    a, k, v = np.array([[-0.2, 1.0], [-1.0, -0.1]]), np.array([0.3, 0.0]), np.array([1.0, 0.0])

    def end(steps):
        u = v
        for _ in range(steps):
            u = integrate.step(a, k, u, 2.0 / steps)
        return u

    exact = end(4000)
    assert 3.5 < math.log2(np.abs(end(20) - exact).max() / np.abs(end(40) - exact).max()) < 4.5


def dense_basis(n):
    """Basis elements as matrices, from their definition."""
    out, pairs = [], [(j, k) for k in range(1, n) for j in range(k)]
    for x in (1, -1j):
        for j, k in pairs:
            f = np.zeros((n, n), complex)
            f[j, k], f[k, j] = x / math.sqrt(2), np.conj(x) / math.sqrt(2)
            out.append(f)
    for d in range(1, n):
        out.append(np.diag([1.0] * d + [-d] + [0.0] * (n - d - 1)).astype(complex) / math.sqrt(d * (d + 1)))
    return out


def dense_parts(h, jumps, n):
    """Q, R and k from traces of matrices; jumps are (weight, matrix)."""
    f = dense_basis(n)
    dissipate = lambda x: sum(g * (a @ x @ a.conj().T - (a.conj().T @ a @ x + x @ a.conj().T @ a) / 2) for g, a in jumps)
    q = np.array([[np.trace(-1j * x @ (h @ y - y @ h)).real for y in f] for x in f])
    r = np.array([[np.trace(x @ dissipate(y)).real for y in f] for x in f])
    return q, r, np.array([np.trace(x @ dissipate(np.eye(n))).real / n for x in f])


def bosons(n):
    """Hopping, number and offset operators of n - 1 bosons on two sites, by ladder operators on a larger space cut to the shell."""
    size = n
    b = np.diag(np.sqrt(np.arange(1, size)), 1)
    one, two = np.kron(b, np.eye(size)), np.kron(np.eye(size), b)
    shell = [i * size + k for i in range(size) for k in range(size) if i + k == n - 1]
    shell.sort(key=lambda z: z % size)
    return one, two, np.ix_(shell, shell)


@pytest.mark.parametrize("n", [3, 4, 6])
def test_dimer_equals_dense_matrices(spark, n):
    one, two, shell = bosons(n)
    hop = (one.T @ two + two.T @ one)[shell]
    n1, n2 = (one.T @ one)[shell], (two.T @ two)[shell]
    unit = np.eye(n)
    h = -models.J * hop + 2 * models.U / (n - 1) * (n1 @ (n1 - unit) + n2 @ (n2 - unit)) + models.E * (n2 - n1)
    lost = ((one + two).T @ (one - two))[shell]
    lv = spark.range(1, n + 1).select(F.lit("d").alias("sys"), F.col("id").cast("int").alias("level"))
    h0, _, jump = models.dimer(lv, n)
    w = spark.createDataFrame([("d", 0, models.dimer_weight(n))], "sys string, op int, gamma double")
    hv, lv_ = keep(expand.expand(h0, n)), keep(expand.expand(jump.withColumn("op", F.lit(0)), n))
    want = dense_parts(h, [(models.GAMMA / (n - 1), lost - np.trace(lost) / n * unit)], n)
    q = assemble.drift(hv, n)
    for got, exact in ((q, want[0]), (assemble.relaxation(lv_, w, n), want[1])):
        cells = as_dict(got, "s", "n")
        assert sum(abs(v) > 1e-9 for v in cells.values()) == (np.abs(exact) > 1e-9).sum()
        assert all(cells.get((s + 1, m + 1), 0.0) == pytest.approx(exact[s, m], abs=1e-9) for s in range(n * n - 1) for m in range(n * n - 1))
    k = as_dict(assemble.inhomogeneity(lv_, w, n), "s")
    assert all(k.get(s + 1, 0.0) == pytest.approx(want[2][s], abs=1e-9) for s in range(n * n - 1))
    assert validate.antisymmetric_gap(q).first().gap < 1e-12
    printed = models.dimer(lv, n, pump="printed")[2].withColumn("op", F.lit(0))
    assert assemble.inhomogeneity(expand.expand(printed, n), w, n).count() == 0


def test_random_generator_invariants_and_routes(spark):
    systems = spark.createDataFrame([("a",), ("b",)], "sys string")
    rates = models.random_rates(spark, 3, systems)
    assert validate.compare(rates, models.random_rates(spark, 3, systems, local=True), ["sys", "j", "k"], "re").first().largest < 1e-12
    r = assemble.relaxation_from_rates(rates, 3)
    assert validate.compare(r, assemble.relaxation_from_rates(rates, 3, "cell"), ["sys", "s", "n"]).first().largest < 1e-12
    l, w = models.diagonalise_rates(rates, 3)  # noqa: E741
    assert validate.compare(r, assemble.relaxation(l, w, 3), ["sys", "s", "n"]).first().largest < 1e-9
    assert validate.compare(r, baselines.sequential(l, w, 3), ["sys", "s", "n"]).first().largest < 1e-9
    e = spectrum.eigenvalues(r, 8).toPandas()
    assert (e["re"] < 1e-9).all() and e.groupby("sys")["re"].mean().to_numpy() == pytest.approx([-9 / 8] * 2)
    # The printed prefactor, twice ours, would miss the trace.
    t = validate.rates_trace(r, rates, 3).first()
    assert t.trace_r == pytest.approx(t.expected) and 2 * t.trace_r != pytest.approx(t.expected)


def test_staged_assembly_restarts(spark, tmp_path):
    import glob
    import os
    import shutil

    lv = spark.range(1, 7).select(F.lit("d").alias("sys"), F.col("id").cast("int").alias("level"))
    w = spark.createDataFrame([("d", 0, models.dimer_weight(6))], "sys string, op int, gamma double")
    v = keep(expand.expand(models.dimer(lv, 6)[2].withColumn("op", F.lit(0)), 6))
    path = str(tmp_path / "r")
    one = keep(assemble.relaxation(v, w, 6))
    got = validate.compare(assemble.relaxation(v, w, 6, stages=5, path=path), one, ["sys", "s", "n"]).first()
    assert (got.only_a, got.only_b) == (0, 0) and got.largest < 1e-12
    held = [spark.read.parquet(f"{path}/blocks/stage={i}").count() for i in range(5)]
    assert sum(held) == one.count() and max(held) < 0.5 * sum(held)
    # One block is lost: only that one is computed again.
    times = {f: os.stat(f).st_mtime_ns for f in glob.glob(f"{path}/blocks/*/_SUCCESS")}
    shutil.rmtree(f"{path}/blocks/stage=2")
    assert assemble.relaxation(v, w, 6, stages=5, path=path).count() == one.count()
    assert {f for f, t in times.items() if os.stat(f).st_mtime_ns == t} == set(times) - {f"{path}/blocks/stage=2/_SUCCESS"}


def test_routes_by_size(spark):
    h, l, w = models.decaying_qubit(spark, 1.0, 0.5)  # noqa: E741
    v = expand.expand(l, 2)
    same = lambda a, b: validate.compare(a, b, ["sys", "s", "n"]).first().largest < 1e-12
    assert same(assemble.relaxation(v, w, 2), assemble.relaxation(v, w, 2, route="cell")) and same(assemble.relaxation(v, w, 2), assemble.relaxation(v, w, 2, route="auto"))
    assert assemble.choose_route(40, 10) == "tensor" and assemble.choose_route(9999, 100) == "cell"
    assert [integrate.choose_strategy(*x) for x in ((24, 300, 20_000, 1), (4000, 40_000, 20_000, 1), (10**6, 10**9, 100, 1))] == ["collapsed", "grouped", "panel"]


def test_graph_panels_reach_the_whole_component(spark):
    n = 61  # a path in shuffled order: its ends are sixty steps apart
    place = lambda i: i * 17 % n + 1
    cells = [("g", "R", place(i), place(i + 1), 1.0) for i in range(n - 1)] + [("g", "R", 70, 71, 1.0)]
    mat = spark.createDataFrame(cells, "sys string, part string, s long, n long, x double")
    got = partition.by_graph(mat, 71, 4)
    p = as_dict(got, "s", value="panel")
    assert sorted(p) == list(range(1, 72))
    edge = measures.edge_cut(mat, got).first()
    assert edge.cut <= 8 < measures.edge_cut(mat, partition.uniform(partition.row_counts(mat, 71), 71, 4)).first().cut
    held = partition.loads(partition.dealt(mat, got, 4)).collect()
    assert sum(r.rows for r in held) == n and max(r.rows for r in held) <= n / 4 + 2


def test_random_chains(spark):
    sites = spark.createDataFrame([("c", i, 0.5 + i) for i in range(3)], "sys string, site int, gamma double")
    for body, boundary, mode in ((1, "open", "jump"), (2, "ring", "jump"), (3, "open", "jump"), (2, "open", "rates"), (1, "ring", "rates")):
        j, w = models.random_chain(sites, 3, body, boundary=boundary, mode=mode)
        j, w = keep(j), keep(w)
        windows = 3 if boundary == "ring" else 4 - body
        assert w.count() == windows * (1 if mode == "jump" else 4**body - 1)
        assert j.where("row = col").groupBy("op").agg(F.sum("re").alias("x"), F.sum("im").alias("y")).where("abs(x) + abs(y) > 1e-9").count() == 0
        # Outside its window an operator is the identity: every local cell occurs on each setting of the other bits.
        assert j.groupBy("op", F.round("re", 9), F.round("im", 9)).count().where(F.col("count") % (1 << (3 - body)) != 0).count() == 0
        cells = {}
        for r in j.join(w, ["sys", "op"]).collect():
            cells.setdefault((r.op, r.gamma), np.zeros((8, 8), complex))[r.row - 1, r.col - 1] = complex(r.re, r.im)
        if mode == "rates":  # each window's rate matrix has trace 2^body; an operator is repeated on 2^(3 - body) settings
            for site in range(windows):
                norm = sum((np.abs(a) ** 2).sum() for (op, _), a in cells.items() if op // (4**body - 1) == site)
                assert norm == pytest.approx(2**body * 2 ** (3 - body))
        else:
            q, r, k = dense_parts(np.zeros((8, 8)), [(g, a) for (_, g), a in cells.items()], 8)
            got = as_dict(assemble.relaxation(keep(expand.expand(j, 8)), w, 8), "s", "n")
            assert all(got.get((s + 1, m + 1), 0.0) == pytest.approx(r[s, m], abs=1e-8) for s in range(63) for m in range(63))
        again, _ = models.random_chain(sites, 3, body, boundary=boundary, mode=mode)
        assert j.exceptAll(again).count() == 0 and j.exceptAll(models.random_chain(sites, 3, body, seed="other", boundary=boundary, mode=mode)[0]).count() > 0


def test_recentring_keeps_the_dynamics(spark):
    cells = [("z", 1, 1, 0.5, 0.2), ("z", 1, 2, 1.0, 0.0), ("z", 2, 2, 0.3, -0.4)]
    jump = spark.createDataFrame(cells, io.OPERATOR)
    w = spark.createDataFrame([("z", 0, 1.0)], "sys string, op int, gamma double")
    whole = baselines.superoperator(jump.withColumn("op", F.lit(0)), w, 2)
    l0, h = expand.recentre_jump(jump, None, 1.0, 2)
    moved = baselines.superoperator(l0.withColumn("op", F.lit(0)), w, 2, h)
    for c in ("re", "im"):
        assert validate.compare(whole, moved, ["a", "b", "c", "d"], c).first().largest < 1e-12


def test_panels_cover_rows_once_and_balance(spark):
    c = spark.range(1, 101).select(F.lit("x").alias("sys"), F.col("id").alias("s"), (F.col("id") % 7 * 5).alias("nnz"))
    p = partition.balanced(c, 6, blocks=16).orderBy("s").collect()
    assert [r.s for r in p] == list(range(1, 101)) and all(a.panel <= b.panel for a, b in zip(p, p[1:]))
    loads = [sum(r.nnz for r in p if r.panel == i) for i in range(6)]
    assert max(loads) <= sum(loads) / 6 + 30
    assert measures.imbalance(partition.largest_first(c, 6)).first().ratio < 1.1


def test_hostile_operators(spark):
    op = spark.createDataFrame([("a", 1, 2, 1.0, 0.0), ("a", 1, 2, 1.0, 0.0), ("a", 1, 1, -0.0, 0.0)], io.OPERATOR)
    with pytest.raises(ValueError):
        checks.assert_hermitian(op)
    with pytest.raises(ValueError):
        checks.require_schema(op.drop("im"), checks.OP)
    with pytest.raises(ValueError):
        expand.expand(op, 1)
    bad = spark.createDataFrame([("a", 1, 1, float("nan"), 0.0)], io.OPERATOR)
    with pytest.raises(Exception, match="NaN"):
        checks.assert_finite(bad, "re").collect()
    assert as_dict(expand.expand(op, 2), "idx", value="re")[1] == pytest.approx(2 / math.sqrt(2))  # duplicate cells add up
    zero = op.where("1 = 0")
    assert expand.expand(zero, 3).count() == 0 and assemble.drift(expand.expand(zero, 3), 3).count() == 0


def test_sources_round_trip(spark, tmp_path):
    structure_source.register(spark)
    a = spark.read.format("structure_constants").option("levels", 3).load()
    assert validate.compare(a, structure.tensor(spark, 3), ["m", "n", "s"], "alpha").first().largest < 1e-12
    op = spark.createDataFrame([("a", 1, 2, 1.0, 0.5)], io.OPERATOR)
    for kind in ("parquet", "orc", "json", "csv"):
        op.write.format(kind).save(str(tmp_path / kind))
        assert io.read_operator(spark, str(tmp_path / kind), kind).collect() == op.collect()


def test_matrix_algebra(spark):
    rng = np.random.default_rng(0)
    x, y = (rng.standard_normal((3, 3)) + 1j * rng.standard_normal((3, 3)) for _ in range(2))
    frame = lambda a: spark.createDataFrame([("m", i + 1, j + 1, float(a[i, j].real), float(a[i, j].imag)) for i in range(3) for j in range(3)], io.OPERATOR)

    def dense(df, n=3):
        out = np.zeros((n, n), complex)
        for r in df.collect():
            out[r.row - 1, r.col - 1] += r.re + 1j * r.im
        return out

    assert np.allclose(dense(linalg.commutator(frame(x), frame(y))), x @ y - y @ x)
    assert np.allclose(dense(linalg.adjoint(frame(x))), x.conj().T)
    assert np.allclose(dense(linalg.kron(frame(x), frame(y), 3), 9), np.kron(x, y))


def test_streams_equal_batches(spark, tmp_path):
    events = io.table(spark, D, "events").withColumn("ts", F.col("ts").cast("timestamp")).where("user_id < 4")
    src = str(tmp_path / "in")
    for i in range(3):  # chunks that interleave in time
        events.where(F.col("event_id") % 3 == i).coalesce(1).write.mode("append").parquet(src)
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(src)

    def run(df, mode):
        name = f"t{uuid.uuid4().hex}"
        q = df.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True).start()
        q.awaitTermination(120)
        return spark.table(name)

    got = run(drives.tumbling(stream, watermark="60 days"), "complete")
    want = drives.tumbling(events)
    assert sorted((r.t0, r.n) for r in got.collect()) == sorted((r.t0, r.n) for r in want.collect())
    a0, a1, k = -0.1 * np.eye(2), np.array([[0.0, 0.01], [-0.01, 0.0]]), np.array([0.1, 0.0])
    streamed = run(drives.propagated(stream, a0, a1, k), "update")
    batch = drives.propagated(events, a0, a1, k)
    events.coalesce(1).write.parquet(f"{src}-ordered")  # one trigger: no event is late
    ordered = as_dict(run(drives.propagated(spark.readStream.schema(events.schema).parquet(f"{src}-ordered"), a0, a1, k), "update"), "user_id", value="x")
    want = as_dict(batch, "user_id", value="x")
    assert ordered.keys() == want.keys() and all(ordered[u] == pytest.approx(want[u]) for u in want)
    odd = events.select("event_id", F.when(F.col("user_id") % 2 == 0, F.col("user_id")).alias("user_id"), F.when(F.col("event_id") % 3 > 0, F.col("ts")).alias("ts"), "value")
    counts = odd.where("ts is not null").groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))
    assert as_dict(drives.propagated(odd, a0, a1, k), "user_id", value="events") == as_dict(counts, "user_id", value="n")
    assert drives.propagated(events.where("1 = 0"), a0, a1, k).count() == 0
    last = streamed.groupBy("user_id").agg(F.max("events").alias("n"))
    assert as_dict(last, "user_id", value="n") == as_dict(events.groupBy("user_id").agg(F.count(F.lit(1)).alias("n")), "user_id", value="n")


def test_density_grid_keeps_mass(spark):
    pts = spark.range(100).select(F.lit("g").alias("sys"), (-F.col("id") / 100.0).alias("re"), F.lit(0.0).alias("im"))
    box = (-2.0, 0.0, -1.0, 1.0)
    g = spectrum.density(pts, 10, 10, box, empty=True)
    assert g.count() == 100 and g.agg(F.sum("density") * 0.2 * 0.2).first()[0] == pytest.approx(1.0)
    # The upper edges belong to the last cells; points outside are a row of their own.
    more = pts.unionByName(spark.createDataFrame([("g", 0.0, 1.0), ("g", 0.5, 0.0), ("g", -2.0, -1.0)], "sys string, re double, im double"))
    rows = {(r.bx, r.by): r for r in spectrum.density(more, 10, 10, box).collect()}
    assert rows[(9, 9)].n == 1 and rows[(0, 0)].n == 1 and rows[(None, None)].n == 1 and rows[(None, None)].density is None
    assert sum(r.n for r in rows.values()) == 103
    own = spectrum.density(more, 10, 10)
    assert own.agg(F.sum("n"), F.sum("density") * (2.5 / 10) * (2.0 / 10)).first()[:] == (103, pytest.approx(1.0))
    assert spectrum.density(pts.where("1 = 0"), 10, 10).count() == 0 and spectrum.density(pts.limit(1), 10, 10).first().n == 1


def test_states_spectra_and_memory(spark):
    good = expand.mixed(spark, "a", 3).unionByName(spark.createDataFrame([("b", 1, 1, 1.5, 0.0), ("b", 2, 2, -0.5, 0.0), ("b", 1, 3, 0.0, 0.25)], io.OPERATOR))
    facts = {r.sys: r for r in validate.state_facts(good, 3).collect()}
    assert facts["a"].trace == pytest.approx(1.0) and facts["a"].hermitian_gap == 0 and facts["a"].smallest == pytest.approx(1 / 3)
    assert facts["b"].hermitian_gap == pytest.approx(0.25) and facts["b"].smallest < -0.4
    eig = spark.createDataFrame([("x", 0, -1.0, 2.0), ("x", 1, -1.0, -2.0), ("y", 0, -1.0, 2.0), ("y", 1, -1.0, 0.0)], "sys string, i int, re double, im double")
    assert as_dict(validate.conjugate_gap(eig), "sys", value="unmatched") == {"x": 0, "y": 1}
    m = measures.partition_bytes(spark.range(0, 1000, 1, 4)).collect()
    assert len(m) == 4 and sum(r.rows for r in m) == 1000 and all(8 * r.rows <= r.bytes <= 10 * r.rows for r in m)
    spark.range(10_000).groupBy(F.col("id") % 7).count().collect()
    assert measures.peak_memory(spark).agg(F.max("execution")).first()[0] > 0


def test_steady_states_and_strategies_agree(spark):
    rates = models.random_rates(spark, 3, spark.createDataFrame([("a",), ("b",)], "sys string"))
    r, k = assemble.relaxation_from_rates(rates, 3), assemble.inhomogeneity_from_rates(rates, 3)
    v0 = expand.initial_vector(expand.pure(spark, "a", 1).unionByName(expand.pure(spark, "b", 2)), 3)
    system = keep(integrate.bundle(r.where("1 = 0"), r, k, v0, r.where("s < n")))
    ends = {s: as_dict(integrate.rk4(system, 8, 4, 0.8, ((0.5, 0.3), (0.5, -0.2)), strategy=s), "sys", "idx") for s in ("grouped", "collapsed", "panel", "auto")}
    for s, e in ends.items():
        assert all(e[i] == pytest.approx(ends["grouped"][i], abs=1e-12) for i in ends["grouped"]), s
    plain = system.where("part <> 'Q1'")
    a, b = (as_dict(integrate.steady_state(plain, 8, m), "sys", "idx") for m in ("direct", "iterative"))
    assert all(a[i] == pytest.approx(b[i], abs=1e-9) for i in a)
    done = integrate.ensemble([plain.where(f"sys = '{x}'") for x in "ab"], lambda d: d.count(), pools=2)
    assert sum(done) == plain.count()
    import pandas as pd
    sparse = integrate.Csr(np.array([0, 0, 2]), np.array([1, 2, 0]), np.array([1.0, 2.0, 3.0]), 3)
    assert (sparse @ np.array([1.0, 10.0, 100.0])).tolist() == [210.0, 0.0, 3.0]
    with pytest.raises(ValueError):
        integrate.matrices(pd.DataFrame({"s": [], "n": [], "x": [], "part": []}), integrate.DENSE + 1)


def test_stream_sinks_and_joins(spark, tmp_path):
    events = io.table(spark, D, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    events.unionByName(events.where("event_id < 100")).repartition(3).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    users = spark.createDataFrame([(1, "a"), (2, "b")], "user_id long, name string")
    joined = drives.with_static(drives.once(stream, "400 days"), users, "user_id")

    def run():
        q = joined.writeStream.foreachBatch(drives.upsert(str(tmp_path / "out"), "batch")).option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start()
        q.awaitTermination(120)

    run()
    got = spark.read.parquet(str(tmp_path / "out"))
    assert got.count() == events.count() == got.select("event_id").distinct().count()
    assert got.where("name = 'a'").count() == events.where("user_id = 1").count() and got.where("name is null").count() == events.where("user_id not in (1, 2)").count()
    drives.upsert(str(tmp_path / "out"), "batch")(got.limit(0), 99)
    run()  # nothing new: nothing is written twice
    assert spark.read.parquet(str(tmp_path / "out")).count() == events.count()


def test_rescaled_drive(spark):
    w = spark.createDataFrame([(10.0, 20.0, 3.0), (20.0, 30.0, 5.0), (30.0, 50.0, 4.0)], "a double, b double, eps double").select(F.col("a").cast("timestamp").alias("t0"), F.col("b").cast("timestamp").alias("t1"), "eps")
    assert [tuple(r)[1:] for r in drives.rescaled(w, "x").orderBy("t0").collect()] == [(0.0, 0.25, -1.0), (0.25, 0.5, 1.0), (0.5, 1.0, 0.0)]


def test_diagonal_planes_are_dealt_out(spark):
    """No task makes more than a fair share of the planes' rows, though the last elements have most of them."""
    n = 24
    counts = structure.tensor(spark, n).groupBy(F.spark_partition_id().alias("p")).agg(F.sum((F.col("m") > n * (n - 1)).cast("int")).alias("rows")).where("rows > 0").collect()
    assert max(r.rows for r in counts) < 0.5 * sum(r.rows for r in counts)


def test_dimer_of_more_levels_than_int_products_hold(spark):
    from coherent.plans import queries

    n = 1_200_000
    lv = spark.createDataFrame([("x", k) for k in (1, 317_333, n)], "sys string, level int")
    h0, _, jump = models.dimer(lv, n)
    got = as_dict(h0.where("row = col"), "row", value="re")
    b, inter = n - 1, lambda t, o: 2 * models.U / (n - 1) * (o * (o - 1) + t * (t - 1)) + models.E * (t - o)
    assert got == {1: inter(0, b), 317_333: inter(317_332, b - 317_332), n: inter(b, 0)}
    # Cells are rounded as the SQL rounds: scaled first. Decimal rounding takes this one, 529244.1469785 as printed, up.
    hop = math.sqrt(317_333.0 * (b - 317_332))
    assert as_dict(queries._op_rows(jump), "row", "col", value="re")[317_334, 317_333] == math.floor(hop * 1e6 + 0.5) / 1e6 == 529244.146978


def _on_tables(spark, name, folder=D):
    """The query's result, which comes from files that Spark reads."""
    from coherent.plans import queries

    df = queries.QUERIES[name](spark, folder)
    assert df.inputFiles()
    return df


def test_alpha_plane_of_the_flow(spark):
    from coherent.plans import queries

    terms = _on_tables(spark, "alpha_plane").groupBy("s", "n").agg(F.sum(F.expr("re*alpha")).alias("x"))
    assert validate.compare(terms, queries.QUERIES["drift_tensor"](spark, D), ["s", "n"]).first().largest < 1e-5


def test_basis_gram_of_the_flow(spark):
    """Its sum is the squared norm of the traceless part of the Hamiltonian."""
    from coherent.plans import queries

    g, h = _on_tables(spark, "basis_gram").collect(), queries.QUERIES["flow_h"](spark, D).collect()
    trace = sum(r.re for r in h if r.row == r.col)
    assert all(r.i == r.j for r in g) and sum(r.re for r in g) == pytest.approx(sum(r.re**2 + r.im**2 for r in h) - trace**2 / 5, abs=1e-4)


def test_beta_plane_of_the_flow(spark):
    from coherent.plans import queries

    got = _on_tables(spark, "beta_plane").collect()
    own = {r.idx: (r.re, r.im) for r in queries.QUERIES["expand_jump"](spark, D).collect()}
    assert {r.m: (r.re, r.im) for r in got} == own
    assert len(got) == structure.beta(spark, 5).where(F.col("m").isin(*own)).count()


def test_contraction_tuples_of_jumps(spark):
    full = spark.range(1, 9).select(F.lit("x").alias("sys"), F.lit(0).alias("op"), F.col("id").alias("idx"))
    assert measures.contraction_tuples(spark, 3, full).first().tuples == measures.contraction_tuples(spark, 3).first().tuples
    assert _on_tables(spark, "contraction_tuples").columns == ["op", "tuples"]


def test_dense_tensor_count_of_turns(spark):
    from coherent.plans import queries

    own = {}
    for r in queries.QUERIES["qutrit_expand"](spark, D).collect():
        own[r.op] = own.get(r.op, 0) + 64
    assert as_dict(_on_tables(spark, "dense_tensor_count"), "op", value="entries") == own
