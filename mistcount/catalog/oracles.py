"""SQL of queries whose formulas or draws take some room: theory, fits of other kinds, and simulations cell by cell."""

from __future__ import annotations

import math

from ..functions import budget as bd
from ..operators import baselines as bl
from . import comparisons, methods
from . import sql as S
from .comparisons import _W11_BETAS, _W11_FLIP
from .methods import EXPONENTIAL, KEY, LINES, ORDERS, SMALL, WIDE, bitmap_sql, party_sql, released_sql
from .registry import oracle

_F = methods._SYM
_P, _Q = repr(_F.p), repr(_F.q)

# --- observed and sandwich errors, plans

_LEVELS = f"SELECT f.g, f.n_hat, j, c.k[j] AS k, {S.log_miss(WIDE)}[j] AS lg FROM ({methods._LINE_FIT}) f JOIN ({methods._LINE_COUNTS}) c USING (g), range(1, 25) r(j)"
_TERMS = f"SELECT *, exp(n_hat * lg) AS miss, {_Q} + ({_P} - {_Q}) * (1 - exp(n_hat * lg)) AS one, 1 - {_P} + ({_P} - {_Q}) * exp(n_hat * lg) AS zero FROM ({_LEVELS})"
oracle(
    "m15a_observed_and_sandwich",
    f"""
WITH t AS (SELECT *, -({_P} - {_Q}) * miss * lg * (1 / one + 1 / zero) AS w FROM ({_TERMS})),
h AS (SELECT g, any_value(n_hat) AS n_hat, -sum(lg * lg * ((4096 - k) * (1 - {_P}) * ({_P} - {_Q}) * miss / (zero * zero) - k * {_P} * ({_P} - {_Q}) * miss / (one * one))) AS curve, sum(w * w * one * (1 - one) * 4096) AS own FROM t GROUP BY g),
x AS (SELECT a.g, sum(a.w * b.w * {(_F.p - _F.q) ** 2!r} * (exp(a.n_hat * ln(1 - (1 - exp(a.lg)) - (1 - exp(b.lg)))) - a.miss * b.miss) * (4096.0 * 4096.0 - CASE WHEN a.j = b.j THEN 4096.0 ELSE 0.0 END)) AS cross_ FROM t a JOIN t b ON a.g = b.g GROUP BY a.g),
s AS (SELECT *, {S.stderr(WIDE, 'n_hat', _P, _Q)} AS se FROM h JOIN x USING (g))
SELECT g, round(se, 2) AS stderr, round(1 / sqrt(curve), 2) AS observed, round(se * se * sqrt(greatest(own + cross_, 0)), 2) AS sandwich FROM s""",
)


def _relative(b: str, q: str) -> str:
    """Relative standard error at a million items of 24 levels of b buckets, by a column q of flips."""
    lg = f"ln(1 - pow(2.0::DOUBLE, -least(j, 23)) / {b})"
    g = f"exp(1e6 * {lg})"
    return f"1 / sqrt({b} * (1 - 2 * {q}) * list_sum(list_transform(range(1, 25), lambda j: {lg} * {lg} * {g} * ((1 - {q}) / (1 - {q} - (1 - 2 * {q}) * {g}) - {q} / ({q} + (1 - 2 * {q}) * {g}))))) / 1e6"


oracle(
    "m15d_plans",
    f"""
WITH RECURSIVE b AS (SELECT 'buckets' AS what, t AS target, e AS given, min(b)::DOUBLE AS answer FROM (SELECT t, e, pow(2.0::DOUBLE, i) AS b, 1 / (exp(e) + 1) AS q FROM (VALUES (0.02::DOUBLE), (0.05::DOUBLE)) x(t), (VALUES (1.0::DOUBLE), (2.0::DOUBLE)) y(e), range(4, 23) z(i)) WHERE {_relative('b', 'q')} <= t GROUP BY t, e),
it AS (
  SELECT t, k, 0 AS i, 0.0::DOUBLE AS low, 20.0::DOUBLE AS high FROM (VALUES (0.02::DOUBLE), (0.05::DOUBLE)) x(t), (VALUES (1), (4), (16)) y(k)
  UNION ALL
  SELECT t, k, i + 1, CASE WHEN fits THEN low ELSE mid END, CASE WHEN fits THEN mid ELSE high END
  FROM (SELECT *, {_relative('4096.0::DOUBLE', 'q')} <= t AS fits FROM (SELECT *, 1 / (1 / (1 - pow(1 - exp(-mid), k)) + 1) AS q FROM (SELECT *, (low + high) / 2 AS mid FROM it WHERE i < 25)))
)
SELECT * FROM b UNION ALL SELECT 'epsilon', t, k::DOUBLE, round(high, 5) FROM it WHERE i = 25""",
)

# --- claims by enumeration

oracle(
    "m16_deterministic_merges",
    """
WITH v AS (SELECT range / 32.0::DOUBLE AS v FROM range(1, 32)),
r AS (
  SELECT a || '' || b || c AS op, target, p.v AS p, q.v AS q, a, b, c,
    (1 - q.v) * (1 - q.v) * a + 2 * q.v * (1 - q.v) * b + q.v * q.v * c AS f00,
    (1 - q.v) * (1 - p.v) * a + (q.v * (1 - p.v) + (1 - q.v) * p.v) * b + q.v * p.v * c AS f01,
    (1 - p.v) * (1 - p.v) * a + 2 * p.v * (1 - p.v) * b + p.v * p.v * c AS f11
  FROM v p, v q, (VALUES (0), (1)) x(a), (VALUES (0), (1)) y(b), (VALUES (0), (1)) z(c), (VALUES ('or'), ('and')) t(target) WHERE p.v >= 0.5 AND q.v <= 0.5 AND q.v < p.v
)
SELECT op, target, count(*) AS n_flips, min(p) AS least_p, max(p) AS most_p FROM (SELECT *, CASE WHEN target = 'or' THEN f01 ELSE f11 END AS one, CASE WHEN target = 'or' THEN abs(f01 - f11) ELSE abs(f00 - f01) END < 1e-12 AS same FROM r)
WHERE same AND abs(one - f00) >= 1e-12 AND f00 <= 0.5 + 1e-12 AND one >= 0.5 - 1e-12 GROUP BY op, target""",
)


def _largest(epsilons: list[float]) -> str:
    w = "[" + ", ".join(f"{math.exp(-e)!r}::DOUBLE" for e in epsilons) + "]"
    product = f"list_reduce(list_transform(range(1, {len(epsilons)} + 1), lambda i: CASE WHEN (bits >> (i - 1)) & 1 = 0 THEN 1.0::DOUBLE ELSE -{w}[i] END / (1 - {w}[i])), lambda a, x: a * x)"
    t = f"SELECT eps, (1 - q) - (1 - 2 * q) * {product} AS t FROM (SELECT i * 0.001::DOUBLE AS eps, 1 / (exp(i * 0.001::DOUBLE) + 1) AS q FROM range(1, {int(max(epsilons) / 1e-3) + 1}) r(i)), range({1 << len(epsilons)}) b(bits)"
    return f"SELECT '{epsilons}' AS epsilons, round(max(eps), 6) AS max_eps, round({bd.combine_or(epsilons)!r}::DOUBLE, 6) AS law_eps FROM (SELECT eps FROM ({t}) GROUP BY eps HAVING min(t) >= -1e-12 AND max(t) <= 1 + 1e-12)"


oracle("m17_largest_budget", " UNION ALL ".join(map(_largest, ([1.0, 1.0], [0.5, 2.0], [0.7, 1.3, 2.2]))))

# --- simulated sketches

_TINY = methods._TINY
_BITS = S.draw("sim", "multinomial", "'level'", "CAST(t AS VARCHAR)", "CAST(i AS VARCHAR)")
_THROWN = f"SELECT DISTINCT t AS trial, CAST({S.draw('sim', 'multinomial', repr('bucket'), 'CAST(t AS VARCHAR)', 'CAST(i AS VARCHAR)')} % {_TINY.buckets} * {_TINY.levels} + least({_TINY.levels}, bit_count(xor(u, u - 1))) - 1 AS INTEGER) AS cell FROM (SELECT CAST(t AS INTEGER) AS t, i, {_BITS} AS u FROM range(20) x(t), range(5000) y(i))"
_DENSE = f"SELECT CAST(t AS INTEGER) AS trial, r.cell, CASE WHEN c.cell IS NULL THEN 0 ELSE 1 END AS bit FROM range(20) x(t) CROSS JOIN (SELECT CAST(range AS INTEGER) AS cell FROM range({_TINY.cells})) r LEFT JOIN ({_THROWN}) c ON c.trial = t AND c.cell = r.cell"
oracle("m18_multinomial", f"SELECT trial, round(n_hat, 3) AS n_hat FROM ({S.fit(S.arrays(S.levels(_DENSE, _TINY, 'trial'), 'trial'), _TINY, 1.0, 0.0, 'trial')})")


def _coupled(n: int) -> str:
    one = 1 << 52
    u = lambda i: f"greatest({S.draw('sim', 'coupling', repr(f'len{i}'), 'CAST(t AS VARCHAR)')} / {float(one)!r}::DOUBLE, 1e-15)"
    place = lambda what: S.draw("sim", "coupling", repr(what), "CAST(t AS VARCHAR)", "CAST(i AS VARCHAR)")
    rho = "[" + ", ".join(f"{r!r}::DOUBLE" for r in methods.COUPLED.rho()) + "]"
    longest = int(n + 8 * n**0.5) + 1
    b, p = methods.COUPLED.buckets, methods.COUPLED.levels
    return f"""SELECT count(*) AS trials, avg(CASE WHEN differ = 0 THEN 1 ELSE 0 END)::DOUBLE AS share_equal, avg(CASE WHEN two = 0 THEN 1 ELSE 0 END)::DOUBLE AS share_poisson, avg(differ)::DOUBLE AS mean_differ, {n} AS n FROM (
  SELECT t, sum(CASE WHEN f <> p OR p <> alone THEN 1 ELSE 0 END) AS differ, sum(CASE WHEN f <> p THEN 1 ELSE 0 END) AS two FROM (
    SELECT *, CASE WHEN (CASE WHEN p = 1 THEN v * one ELSE one + v * (1 - one) END) < 1 - exp({float(n)!r} * ln(1 - rho)) THEN 1 ELSE 0 END AS alone FROM (
      SELECT g.t, g.cell, coalesce(c.f, 0) AS f, coalesce(c.p, 0) AS p, {rho}[g.cell % {p} + 1] AS rho, 1 - exp(-{float(n)!r} * {rho}[g.cell % {p} + 1]) AS one, {S.draw('sim', 'coupling', repr('couple'), 'CAST(g.t AS VARCHAR)', 'CAST(g.cell AS VARCHAR)')} / {float(one)!r}::DOUBLE AS v
      FROM (SELECT t, CAST(c AS INTEGER) AS cell FROM range(20) x(t), range({b * p}) y(c)) g LEFT JOIN (
        SELECT t, cell, max(CASE WHEN i < {n} THEN 1 ELSE 0 END) AS f, max(CASE WHEN i < len THEN 1 ELSE 0 END) AS p FROM (
          SELECT t, i, len, CAST({place('bucket')} % {b} * {p} + least({p}, bit_count(xor(w, w - 1))) - 1 AS INTEGER) AS cell FROM (
            SELECT t, i, greatest(0, round({n} + sqrt(-2 * ln({u(1)})) * cos(6.283185307179586 * {u(2)}) * {n**0.5!r}::DOUBLE)) AS len, {place('level')} AS w FROM range(20) x(t), range({longest}) y(i)
          )) GROUP BY t, cell
      ) c ON c.t = g.t AND c.cell = g.cell)) GROUP BY t)"""


oracle("m18c_coupling_agreement", " UNION ALL ".join(map(_coupled, (1000, 10000))))
_POISSON = "[" + ", ".join(f"{-r!r}::DOUBLE" for r in WIDE.rho()) + "]"
oracle("m18p_poisson_fit", f"SELECT a.g, round(a.n_hat, 1) AS likelihood, round(b.n_hat, 1) AS poisson FROM ({methods._LINE_FIT}) a JOIN ({S.fit(methods._LINE_COUNTS, WIDE, _F.p, _F.q, log=_POISSON)}) b USING (g)")
oracle("m19_exponential_bitmap", bitmap_sql(EXPONENTIAL, 2.0, "exponential"))
oracle("t13_bounded_contribution", f"SELECT n, count(*) AS n_items FROM (SELECT item, count(*) AS n FROM (SELECT *, row_number() OVER (PARTITION BY item ORDER BY {S.h60(chr(39).join(['concat_ws(', '|', ', item, g)']))}, g) AS r FROM (SELECT DISTINCT g, item FROM ({ORDERS}))) WHERE r <= 2 GROUP BY item) GROUP BY n")

# --- baselines


def _ends(shares: str, beta: str, relative: bool, p: str, q: str) -> tuple[str, str]:
    """The largest lower end and the least upper one over levels, of counts k."""
    lg = f"{S.log_miss(WIDE)}[j]"
    s = f"(({p} - {shares}[j] / 4096.0::DOUBLE) / ({p} - {q}))"
    slack = f"({beta} * abs({s}))" if relative else f"{beta}"
    low = f"CASE WHEN {s} + {slack} <= 0 THEN 'inf'::DOUBLE ELSE ln(least(1.0::DOUBLE, greatest({s} + {slack}, 1e-300::DOUBLE))) / {lg} END"
    high = f"CASE WHEN {s} - {slack} >= 1 THEN 0.0 WHEN {s} - {slack} <= 0 THEN 'inf'::DOUBLE ELSE ln(greatest({s} - {slack}, 1e-300::DOUBLE)) / {lg} END"
    return f"list_max(list_transform(range(1, 25), lambda j: {low}))", f"list_min(list_transform(range(1, 25), lambda j: {high}))"


_HALF = bd.half_flip(2.0)
_B03 = S.arrays(S.levels(S.flip(S.dense(LINES, WIDE), _HALF.p, _HALF.q, KEY, "b03"), WIDE))


def _interval(relative: bool) -> str:
    a, b = _ends("k", "beta", relative, repr(_HALF.p), repr(_HALF.q))
    step = math.log(1 / bl.BETA_LEAST) / bl.BETA_GRID
    tried = f"SELECT g, i, {a} AS a, {b} AS b FROM (SELECT g, k, i, {bl.BETA_LEAST} * exp(i * {step!r}::DOUBLE) AS beta FROM ({_B03}), range(0, {bl.BETA_GRID + 1}) r(i))"
    return f"SELECT g, round(arg_min((a + b) / 2, i), 2) AS n_hat FROM ({tried}) WHERE a <= b AND b < 'inf'::DOUBLE AND a < 'inf'::DOUBLE GROUP BY g"


oracle("b03_interval_estimate", f"SELECT a.g, a.n_hat AS additive, b.n_hat AS relative FROM ({_interval(False)}) a JOIN ({_interval(True)}) b USING (g)")


def _fixed(beta: float, f: bd.Flip = _HALF) -> str:
    a, b = _ends("k", f"{beta!r}::DOUBLE", False, repr(f.p), repr(f.q))
    return f"CASE WHEN {a} <= {b} AND {b} < 'inf'::DOUBLE THEN ({a} + {b}) / 2 END"


oracle("b03o_fixed_tolerance", "SELECT g, " + ", ".join(f"round({_fixed(b)}, 2) AS beta_{str(b).replace('.', '_')}" for b in (0.01, 0.02, 0.05, 0.1, 0.2)) + f" FROM ({_B03})")

_RISES = """(-(4096 - used) / 4096.0::DOUBLE + list_sum(list_transform(range(1, 25), lambda j: c[j] * (-(CASE WHEN j = 24 THEN 0.0 ELSE pow(2.0::DOUBLE, -j) END) / 4096.0 + (pow(2.0::DOUBLE, -(j - 1)) - (CASE WHEN j = 24 THEN 0.0 ELSE pow(2.0::DOUBLE, -j) END)) / 4096.0 *
  coalesce(exp(-exp(mid) / 4096.0 * (pow(2.0::DOUBLE, -(j - 1)) - (CASE WHEN j = 24 THEN 0.0 ELSE pow(2.0::DOUBLE, -j) END))) / nullif(1 - exp(-exp(mid) / 4096.0 * (pow(2.0::DOUBLE, -(j - 1)) - (CASE WHEN j = 24 THEN 0.0 ELSE pow(2.0::DOUBLE, -j) END))), 0), 0))))) > 0"""
oracle(
    "b07m_hll_likelihood",
    f"""
WITH RECURSIVE r AS (SELECT g, r, count(*) AS c FROM ({comparisons._REGISTERS}) GROUP BY g, r),
a AS (SELECT x.g, list(coalesce(r.c, 0) ORDER BY j) AS c, sum(coalesce(r.c, 0)) AS used FROM (SELECT DISTINCT g, j FROM r, range(1, 25) t(j)) x LEFT JOIN r ON r.g = x.g AND r.r = j GROUP BY x.g),
it AS (
  SELECT g, c, used, 0 AS i, 0.0::DOUBLE AS low, 25.0::DOUBLE AS high FROM a
  UNION ALL
  SELECT g, c, used, i + 1, CASE WHEN up THEN mid ELSE low END, CASE WHEN up THEN high ELSE mid END FROM (SELECT *, {_RISES} AS up FROM (SELECT *, (low + high) / 2 AS mid FROM it WHERE i < 60))
)
SELECT g, round(exp((low + high) / 2), 2) AS n_hat FROM it WHERE i = 60""",
)

_ORDER_REGISTERS = f"SELECT g, cell // 16 AS bucket, max(cell % 16 + 1) AS r FROM ({S.set_cells(ORDERS, SMALL)}) GROUP BY 1, 2"
_V = f"({S.draw('laplace', KEY, repr('b10'), 'g')} / {float(1 << 52)!r}::DOUBLE - 0.5)"
oracle(
    "b10_noisy_estimate",
    f"SELECT g, round(CASE WHEN raw <= 2.5 * 256 AND used < 256 THEN 256 * ln(256.0 / greatest(256 - used, 1)) ELSE raw END - 10.0 * sign({_V}) * ln(1 - least(2 * abs({_V}), 1 - 1e-12::DOUBLE)), 3) AS n_hat FROM (SELECT *, {0.7213 / (1 + 1.079 / 256)!r}::DOUBLE * 256 * 256 / (z + (256 - used)) AS raw FROM (SELECT g, count(*) AS used, sum(pow(2.0, -r)) AS z FROM ({_ORDER_REGISTERS}) GROUP BY g))",
)
_KEPT = f"SELECT 'x' AS g, item FROM ({LINES}) WHERE {S.h60(chr(39).join(['concat_ws(', '|', ', ', 'sample', ', item)']))} % {1 << 20} < {1 << 19}"
_S2 = bd.symmetric(2.0)
oracle("b12_subsampled", f"SELECT round(n_hat / 0.5, 2) AS n_hat, 'ok' AS status FROM ({S.fit(S.arrays(S.levels(S.flip(S.dense(_KEPT, WIDE), _S2.p, _S2.q, KEY, 'b12').replace('CAST(g AS VARCHAR), ', ''), WIDE)), WIDE, _S2.p, _S2.q)})")

_S3 = bd.symmetric(3.0)
_PRODUCT = f"pow({(_S3.p - 1) / (_S3.p - _S3.q)!r}::DOUBLE, m) * pow({_S3.p / (_S3.p - _S3.q)!r}::DOUBLE, n - m)"
_RHO = "[" + ", ".join(f"{r!r}::DOUBLE" for r in WIDE.rho()) + "]"
oracle(
    "b13_union_without_merging",
    f"""
WITH RECURSIVE e AS (SELECT g, list(e ORDER BY level) AS e FROM (SELECT g, cell % 24 AS level, avg({_PRODUCT}) AS e FROM (SELECT g, cell, sum(bit) AS m, count(*) AS n FROM ({released_sql('3.0::DOUBLE')}) GROUP BY g, cell) GROUP BY 1, 2) GROUP BY g),
it AS (
  SELECT g, e, 0 AS i, 0.0::DOUBLE AS low, 25.0::DOUBLE AS high FROM e
  UNION ALL
  SELECT g, e, i + 1, CASE WHEN s > 0 THEN mid ELSE low END, CASE WHEN s > 0 THEN high ELSE mid END
  FROM (SELECT *, list_sum(list_transform(range(1, 25), lambda j: (e[j] - exp(exp(mid) * {S.log_miss(WIDE)}[j])) * exp(exp(mid) * {S.log_miss(WIDE)}[j]) * {S.log_miss(WIDE)}[j])) AS s FROM (SELECT *, (low + high) / 2 AS mid FROM it WHERE i < 60))
)
SELECT g, round(exp((low + high) / 2), 2) AS n_hat FROM it WHERE i = 60""",
)

# --- unions and intersections of two parties

_S4 = bd.symmetric(4.0)
_PARTIES = released_sql("4.0::DOUBLE", k=2)
_EACH = S.fit(S.arrays(S.levels(f"SELECT party, cell, bit FROM ({_PARTIES})", WIDE, "party"), "party"), WIDE, _S4.p, _S4.q, "party")
_MERGED = S.union_randomized(_PARTIES, "x01")
_COUNTS = f"SELECT g, max(star) AS star, list(k ORDER BY level) AS k FROM (SELECT g, star, cell % 24 AS level, sum(bit)::BIGINT AS k FROM ({_MERGED}) GROUP BY ALL) GROUP BY g"
_SP, _SQ = "(1 - 1 / (exp(star) + 1))", "(1 / (exp(star) + 1))"
oracle(
    "x01_intersection_size",
    f"""
SELECT round(s, 2) AS sum_n, round(n_hat, 2) AS union_n, round(s - n_hat, 2) AS intersection_n, round(sqrt(v) + {S.stderr(WIDE, 'n_hat', _SP, _SQ)}, 2) AS stderr_bound
FROM (SELECT sum(n_hat) AS s, sum(pow({S.stderr(WIDE, 'n_hat', repr(_S4.p), repr(_S4.q))}, 2)) AS v FROM ({_EACH})), ({S.fit(_COUNTS, WIDE, _SP, _SQ, keep='star')})""",
)
_NOISY = S.flip(f"SELECT 'all|' || party AS w, cell, bit FROM ({S.dense(party_sql(), WIDE, 'party')})", _S3.p, _S3.q, KEY, "packed-noisy", "w")
_STAR = bd.symmetric(bd.combine_or([3.0] * 4))
oracle("op_udaf_packed_noisy", f"SELECT g, round(n_hat, 2) AS n_hat, 'ok' AS status FROM ({S.fit(S.arrays(S.levels(S.union_randomized(f'SELECT {chr(39)}all{chr(39)} AS g, cell, bit, 3.0::DOUBLE AS eps FROM ({_NOISY})', 'packed'), WIDE)), WIDE, _STAR.p, _STAR.q)})")

# --- private counts of slices of line items, and simulations with every cell drawn


def _counted() -> str:
    """method, eps, trial, n, n_hat, stderr of the measures' runs."""
    values = ", ".join(f"('{m}', {e!r}::DOUBLE, {p!r}::DOUBLE, {q!r}::DOUBLE)" for m, e, p, q in comparisons.RUNS)
    u = S.draw("flip", KEY, "'trials'", "method", "CAST(eps AS VARCHAR)", "CAST(trial AS VARCHAR)", "CAST(cell AS VARCHAR)")
    bits = f"SELECT method, eps, trial, p, q, cell, CAST(CASE WHEN bit = 1 THEN u < {S.chance('p')} ELSE u < {S.chance('q')} END AS INTEGER) AS bit FROM (SELECT *, {u} AS u FROM ({S.dense(comparisons.TRIAL_ITEMS, SMALL, 'trial')}), (VALUES {values}) x(method, eps, p, q))"
    by = "method, eps, trial, p, q"
    counts = f"SELECT method, eps, trial, p AS pp, q AS qq, list(k ORDER BY level) AS k FROM ({S.levels(bits, SMALL, by)}) GROUP BY {by}"
    fitted = S.fit(counts, SMALL, "pp", "qq", "method, eps, trial", keep="pp, qq")
    truth = f"SELECT trial, CAST(count(DISTINCT item) AS DOUBLE) AS n FROM ({comparisons.TRIAL_ITEMS}) GROUP BY trial"
    return f"SELECT method, eps, trial, n, n_hat, {S.stderr(SMALL, 'n', 'pp', 'qq')} AS stderr FROM ({fitted}) JOIN ({truth}) USING (trial)"


_RUNS = _counted()
_MSE = f"SELECT method, eps, count(*) AS trials, 0.0::DOUBLE AS failure_rate, avg(n_hat - n) AS bias, var_pop(n_hat) AS variance, avg(pow(n_hat - n, 2)) AS mse, sqrt(avg(pow(n_hat - n, 2))) / avg(n) AS rrmse FROM ({_RUNS}) GROUP BY method, eps"
oracle("a01_accuracy", f"SELECT method, eps, trials, failure_rate, round(bias, 2) AS bias, round(variance, 0) AS variance, round(mse, 0) AS mse, round(rrmse, 5) AS rrmse FROM ({_MSE})")
oracle("a02_relative_efficiency", f"SELECT method, eps, round(mse / max(CASE WHEN method = 'randomized' THEN mse END) OVER (PARTITION BY eps), 3) AS relative_efficiency FROM ({_MSE})")
oracle("a04_calibration", f"SELECT method, eps, round(sqrt(avg(pow(stderr, 2))) / sqrt(avg(pow(n_hat - n, 2))), 3) AS calibration FROM ({_RUNS}) GROUP BY method, eps")
oracle("a05_failure_rate", f"SELECT method, eps, failure_rate FROM ({_MSE})")
oracle("a10_coverage", f"SELECT method, eps, round(avg(CASE WHEN abs(n_hat - n) <= 1.96 * stderr THEN 1.0 ELSE 0.0 END), 3)::DOUBLE AS coverage FROM ({_RUNS}) GROUP BY method, eps")


def _w11() -> str:
    f = _W11_FLIP
    u = S.draw("sim", "w11", "CAST(trial AS VARCHAR)", "CAST(cell AS VARCHAR)")
    full = f"(1 - exp(100000.0 * {S.log_miss(WIDE)}[cell % 24 + 1]))"
    bits = f"SELECT trial, cell, CAST({u} < {S.chance(f'({f.q!r}::DOUBLE + {f.p - f.q!r}::DOUBLE * {full})')} AS INTEGER) AS bit FROM (SELECT CAST(range AS INTEGER) AS trial FROM range(20)), (SELECT CAST(range AS INTEGER) AS cell FROM range({WIDE.cells}))"
    each = " UNION ALL ".join(f"SELECT {b!r}::DOUBLE AS beta, {_fixed(b, f)} AS n_hat FROM c" for b in _W11_BETAS)
    return f"WITH c AS ({S.arrays(S.levels(bits, WIDE, 'trial'), 'trial')}) SELECT beta, round(avg(CASE WHEN n_hat IS NULL THEN 1.0 ELSE 0.0 END), 4)::DOUBLE AS failure_rate, round(sqrt(avg(pow(n_hat - 1e5, 2))) / 1e5, 4) AS rrmse FROM ({each}) GROUP BY beta"


oracle("w11_failures_by_cells", _w11())
