"""SQL by other routes than the queries take: traces over basis elements, commutators, matrix cells."""

from __future__ import annotations

import math

from coherent.operators import models
from coherent.plans.workloads import EVENT_TYPES, LANGS, ROLES

ORDER = {"hop5": EVENT_TYPES, "turn3": ROLES}


def r6(x: str) -> str:
    return f"round({x}, 6) + 0.0"


def elem(n: int) -> str:
    h = n * (n - 1) // 2
    return f"""lev AS (SELECT i::BIGINT AS i FROM range(1, {n + 1}) t(i)),
pr AS (SELECT a.i AS j, b.i AS k, (b.i - 1) * (b.i - 2) // 2 + a.i AS p FROM lev a JOIN lev b ON a.i < b.i),
elem AS (SELECT p AS idx, j AS r, k AS c, sqrt(0.5::DOUBLE) AS re, 0.0::DOUBLE AS im FROM pr UNION ALL SELECT p, k, j, sqrt(0.5::DOUBLE), 0.0 FROM pr
 UNION ALL SELECT p + {h}, j, k, 0.0, -sqrt(0.5::DOUBLE) FROM pr UNION ALL SELECT p + {h}, k, j, 0.0, sqrt(0.5::DOUBLE) FROM pr
 UNION ALL SELECT l.i + {2 * h}, a.i, a.i, CASE WHEN a.i <= l.i THEN 1.0::DOUBLE ELSE -l.i::DOUBLE END / sqrt((l.i * (l.i + 1))::DOUBLE), 0.0 FROM lev l JOIN lev a ON a.i <= l.i + 1 WHERE l.i < {n})"""


FLOW_CELLS = """SELECT c_nationkey AS a, s_nationkey AS b, sum(l_extendedprice * (1 - l_discount)) AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey
 JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY ALL"""


def flow(level: str = "region") -> str:
    """CTE flow(r, c, v)."""
    if level == "nation":
        return f"f0 AS (SELECT a AS r, b AS c, v FROM ({FLOW_CELLS})), flow AS (SELECT r::BIGINT + 1 AS r, c::BIGINT + 1 AS c, v / (SELECT max(v) FROM f0) AS v FROM f0)"
    return f"""f0 AS (SELECT x.n_regionkey AS r, y.n_regionkey AS c, sum(v) AS v FROM ({FLOW_CELLS}) JOIN nation x ON a = x.n_nationkey JOIN nation y ON b = y.n_nationkey GROUP BY ALL),
flow AS (SELECT r::BIGINT + 1 AS r, c::BIGINT + 1 AS c, v / (SELECT max(v) FROM f0) AS v FROM f0)"""


def flow_h(n: int) -> str:
    """CTE h(r, c, re, im): symmetric part plus the term that compensates the jump operator's trace."""
    return f"""tr AS (SELECT sum(v) / {n} AS t FROM flow WHERE r = c),
l0 AS (SELECT r, c, v - CASE WHEN r = c THEN t ELSE 0 END AS v FROM flow, tr),
h AS (SELECT r, c, sum(re) AS re, sum(im) AS im FROM (SELECT r, c, v / 2 AS re, 0.0::DOUBLE AS im FROM flow UNION ALL SELECT c, r, v / 2, 0.0 FROM flow
  UNION ALL SELECT r, c, 0.0, t * v / 2 FROM l0, tr UNION ALL SELECT c, r, 0.0, -t * v / 2 FROM l0, tr) GROUP BY ALL)"""


def flow_jump() -> str:
    return "L AS (SELECT 0 AS op, r, c, v AS re, 0.0::DOUBLE AS im, 1.0::DOUBLE AS g FROM l0)"


def dimer_cells(n: int | str, tab: str, key: str) -> str:
    """CTEs lv, h0, h1, la (antisymmetric pump), lp (printed pump)."""
    b, j, e = n - 1 if isinstance(n, int) else f"({n} - 1)", models.J, models.E
    u = f"{2 * models.U!r}::DOUBLE / {b}"
    return f"""lv AS (SELECT {key}::BIGINT + 1 AS k, {key}::DOUBLE AS t, {b} - {key}::DOUBLE AS o FROM {tab}),
hp AS (SELECT k, sqrt((t + 1) * o) AS x, t, o FROM lv WHERE t < {b}),
h0 AS (SELECT * FROM (SELECT k AS r, k + 1 AS c, {-j}::DOUBLE * x AS re, 0.0::DOUBLE AS im FROM hp UNION ALL SELECT k + 1, k, {-j}::DOUBLE * x, 0.0 FROM hp
  UNION ALL SELECT k, k, {u} * (o * (o - 1) + t * (t - 1)) + {e}::DOUBLE * (t - o), 0.0 FROM lv) WHERE abs(re) > 1e-12),
h1 AS (SELECT k AS r, k AS c, t - o AS re, 0.0::DOUBLE AS im FROM lv WHERE t <> o),
la AS (SELECT * FROM (SELECT k AS r, k AS c, o - t AS re, 0.0::DOUBLE AS im FROM lv UNION ALL SELECT k + 1, k, x, 0.0 FROM hp UNION ALL SELECT k, k + 1, -x, 0.0 FROM hp) WHERE abs(re) > 1e-12),
lp AS (SELECT k AS r, k AS c, 0.0::DOUBLE AS re, 0.0::DOUBLE AS im FROM lv UNION ALL SELECT k + 1, k, x, 0.0 FROM hp UNION ALL SELECT k, k + 1, x, 0.0 FROM hp)"""


def dimer_jump(n: int, source: str = "la") -> str:
    return f"L AS (SELECT 0 AS op, r, c, re, im, {models.dimer_weight(n)!r}::DOUBLE AS g FROM {source})"


def pairs_cte(which: str) -> str:
    if which == "hop5":
        return "pq AS (SELECT lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS a, event_type AS b FROM events), pp AS (SELECT a, b, count(*) AS n FROM pq WHERE a IS NOT NULL GROUP BY ALL)"
    return "pq AS (SELECT role AS a, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS b FROM conversations), pp AS (SELECT a, b, count(*) AS n FROM pq WHERE b IS NOT NULL GROUP BY ALL)"


def jumps_cte(which: str) -> str:
    """CTEs tj(op, f, t, g) and L, the traceless jump operators."""
    names = ORDER[which]
    n = len(names)
    lst = "[" + ", ".join(f"'{x}'" for x in names) + "]"
    return f"""{pairs_cte(which)},
tj AS (SELECT ((list_position({lst}, a) - 1) * {n} + list_position({lst}, b) - 1)::INT AS op, list_position({lst}, a)::BIGINT AS f, list_position({lst}, b)::BIGINT AS t, n::DOUBLE / (SELECT sum(n) FROM pp) AS g FROM pp),
L AS (SELECT op, r, c, sum(re) AS re, sum(im) AS im, any_value(g) AS g FROM (SELECT op, t AS r, f AS c, 1.0::DOUBLE AS re, 0.0::DOUBLE AS im, g FROM tj
  UNION ALL SELECT op, i, i, -1.0 / {n}, 0.0, g FROM tj, lev WHERE f = t) GROUP BY op, r, c)"""


def expand_sql(op: str) -> str:
    """idx, re, im of Tr(F A), by the definition."""
    return f"SELECT e.idx, sum(e.re * o.re - e.im * o.im) AS re, sum(e.re * o.im + e.im * o.re) AS im FROM elem e JOIN {op} o ON e.c = o.r AND e.r = o.c GROUP BY e.idx"


def drift_sql(h: str) -> str:
    """s, n, x of Tr(F_s (-i)[H, F_n])."""
    return f"""SELECT s, n, sum(x) AS x FROM (
 SELECT f.idx AS s, e.idx AS n, f.re * (h.re * e.im + h.im * e.re) + f.im * (h.re * e.re - h.im * e.im) AS x FROM {h} h JOIN elem e ON h.c = e.r JOIN elem f ON f.c = h.r AND f.r = e.c
 UNION ALL SELECT f.idx, e.idx, -(f.re * (h.re * e.im + h.im * e.re) + f.im * (h.re * e.re - h.im * e.im)) FROM {h} h JOIN elem e ON e.c = h.r JOIN elem f ON f.c = e.r AND f.r = h.c) GROUP BY ALL"""


def super_sql(n: int, c: str | None = None) -> str:
    """CTEs C, G, X: the generator on cells from L(op, r, c, re, im, g), or from given cells C."""
    c = c or "C AS (SELECT x.r AS a, y.r AS b, x.c AS c, y.c AS d, sum(x.g * (x.re * y.re + x.im * y.im)) AS re, sum(x.g * (x.im * y.re - x.re * y.im)) AS im FROM L x JOIN L y ON x.op = y.op GROUP BY ALL)"
    return f"""{c}, sink AS (SELECT d AS p, c AS q, sum(re) AS re, sum(im) AS im FROM C WHERE a = b GROUP BY ALL),
X AS (SELECT a, b, c, d, sum(re) AS re, sum(im) AS im FROM (SELECT a, b, c, d, re, im FROM C UNION ALL SELECT p, i, q, i, -re / 2, -im / 2 FROM sink, lev UNION ALL SELECT i, q, i, p, -re / 2, -im / 2 FROM sink, lev) GROUP BY ALL)"""


RELAX = """(SELECT s, n, sum(re * x - im * y) AS x FROM (SELECT n, a, b, sum(X.re * e.re - X.im * e.im) AS re, sum(X.re * e.im + X.im * e.re) AS im FROM X JOIN (SELECT idx AS n, r AS c, c AS d, re, im FROM elem) e USING (c, d) GROUP BY n, a, b)
 JOIN (SELECT idx AS s, r AS b, c AS a, re AS x, im AS y FROM elem) USING (a, b) GROUP BY s, n)"""

INHOM = """(SELECT e.idx AS s, sum(e.re * o.re - e.im * o.im) AS x FROM elem e JOIN (
 SELECT r, c, sum(re) AS re, sum(im) AS im FROM (
  SELECT x.r AS r, y.r AS c, x.g * (x.re * y.re + x.im * y.im) AS re, x.g * (x.im * y.re - x.re * y.im) AS im FROM L x JOIN L y ON x.op = y.op AND x.c = y.c
  UNION ALL SELECT x.c, y.c, -x.g * (x.re * y.re + x.im * y.im), -x.g * (x.re * y.im - x.im * y.re) FROM L x JOIN L y ON x.op = y.op AND x.r = y.r) GROUP BY ALL) o ON e.c = o.r AND e.r = o.c GROUP BY e.idx)"""


def trace_tensor() -> str:
    """CTE sc(m, n, s, alpha, beta) by traces of triple products."""
    return """t3 AS (SELECT m, n, f.idx AS s, sum(p.re * f.re - p.im * f.im) AS x, sum(p.re * f.im + p.im * f.re) AS y FROM (
 SELECT a.idx AS m, b.idx AS n, a.r AS r, b.c AS c, a.re * b.re - a.im * b.im AS re, a.re * b.im + a.im * b.re AS im FROM elem a JOIN elem b ON a.c = b.r) p JOIN elem f ON p.c = f.r AND p.r = f.c GROUP BY ALL),
sc AS (SELECT m, n, s, sum(y) AS alpha, sum(x) AS beta FROM (SELECT m, n, s, x, y FROM t3 UNION ALL SELECT n, m, s, x, -y FROM t3) GROUP BY ALL)"""


def gauss(n: int, systems: str, seed: str = "rates") -> str:
    """CTE g(sys, r, c, re, im)."""
    m = n * n - 1
    u = lambda part: f"(('0x' || substr(md5(k), {1 + 8 * part}, 8))::BIGINT::DOUBLE + 0.5) / 4294967296.0::DOUBLE"
    return f"""gk AS (SELECT sys, a.i AS r, b.i AS c, '{seed}:' || sys || ':' || a.i || ':' || b.i AS k FROM ({systems}), range(1, {m + 1}) a(i), range(1, {m + 1}) b(i)),
g AS (SELECT sys, r, c, sqrt(-ln({u(0)})) * cos({2 * math.pi!r}::DOUBLE * {u(1)}) AS re, sqrt(-ln({u(0)})) * sin({2 * math.pi!r}::DOUBLE * {u(1)}) AS im FROM gk)"""


def rates(n: int) -> str:
    return f"""gt AS (SELECT sys, sum(re * re + im * im) AS t FROM g GROUP BY sys),
w AS (SELECT sys, x.r AS j, y.r AS k, {n} * sum(x.re * y.re + x.im * y.im) / any_value(t) AS re, {n} * sum(x.im * y.re - x.re * y.im) / any_value(t) AS im FROM g x JOIN g y USING (sys, c) JOIN gt USING (sys) GROUP BY sys, x.r, y.r)"""


LANG_LIST = "[" + ", ".join(f"'{x}'" for x in LANGS) + "]"
