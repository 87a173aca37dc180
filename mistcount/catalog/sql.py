"""The methods' steps as DuckDB SQL, to check the queries against another engine."""

from __future__ import annotations

import math

from ..functions.noise import ONE
from ..layout import Exponential, Layout


def num(x: float | str) -> str:
    return x if isinstance(x, str) else f"{float(x)!r}::DOUBLE"


def h60(text: str) -> str:
    return f"('0x' || substr(md5({text}), 1, 15))::BIGINT"


def draw(purpose: str, key: str, *parts: str) -> str:
    """parts are SQL expressions."""
    return f"('0x' || substr(sha256(concat_ws('|', '{purpose}', '{key}', {', '.join(parts)})), 1, 13))::BIGINT"


def chance(p: float | str) -> str:
    return f"CAST(floor({p} * {float(ONE)!r}::DOUBLE) AS BIGINT)" if isinstance(p, str) else str(int(p * ONE))


def cell(item: str, layout: Layout, which: int = 0) -> str:
    h = h60(f"concat_ws('|', '{layout.seed}:{which}', CAST({item} AS VARCHAR))")
    if layout.levels == 1:
        return f"CAST({h} % {layout.buckets} AS INTEGER)"
    rest = f"({h} // {layout.buckets})"
    if isinstance(layout, Exponential):
        sums, total = [], 0.0
        for r in layout.rho()[:-1]:
            total += r * layout.buckets
            sums.append(f"{total!r}::DOUBLE")
        u = f"(({rest} % {1 << 40}) / {float(1 << 40)!r}::DOUBLE)"
        return f"CAST({h} % {layout.buckets} * {layout.levels} + len(list_filter([{', '.join(sums)}], lambda x: {u} >= x)) AS INTEGER)"
    return f"CAST({h} % {layout.buckets} * {layout.levels} + least({layout.levels}, bit_count(xor({rest}, {rest} - 1))) - 1 AS INTEGER)"


def set_cells(items: str, layout: Layout, by: str = "g") -> str:
    """items: SQL with columns by and item."""
    each = " UNION ".join(f"SELECT {by}, {cell('item', layout, i)} AS cell FROM ({items}) WHERE item IS NOT NULL" for i in range(layout.hashes))
    return f"SELECT DISTINCT {by}, cell FROM ({each})"


def dense(items: str, layout: Layout, by: str = "g") -> str:
    return (
        f"SELECT gg.{by}, r.cell, CASE WHEN c.cell IS NULL THEN 0 ELSE 1 END AS bit FROM (SELECT DISTINCT {by} FROM ({items})) gg "
        f"CROSS JOIN (SELECT CAST(range AS INTEGER) AS cell FROM range({layout.cells})) r LEFT JOIN ({set_cells(items, layout, by)}) c ON c.{by} = gg.{by} AND c.cell = r.cell"
    )


def flip(bits: str, p: float | str, q: float | str, key: str, release: str, by: str = "g", extra: str = "") -> str:
    u = draw("flip", key, f"'{release}'", f"CAST({by} AS VARCHAR)", "CAST(cell AS VARCHAR)")
    return f"SELECT {by}, cell, {extra} CAST(CASE WHEN bit = 1 THEN u < {chance(p)} ELSE u < {chance(q)} END AS INTEGER) AS bit FROM (SELECT *, {u} AS u FROM ({bits}))"


def levels(bits: str, layout: Layout, by: str = "g") -> str:
    return f"SELECT {by}, cell % {layout.levels} AS level, sum(bit)::BIGINT AS k FROM ({bits}) GROUP BY ALL"


def ones_csv(level_counts: str, by: str = "g") -> str:
    return f"SELECT {by}, string_agg(CAST(k AS VARCHAR), ',' ORDER BY level) AS ones FROM ({level_counts}) GROUP BY {by}"


def arrays(level_counts: str, by: str = "g") -> str:
    return f"SELECT {by}, list(k ORDER BY level) AS k FROM ({level_counts}) GROUP BY {by}"


def log_miss(layout: Layout) -> str:
    return "[" + ", ".join(f"{math.log1p(-r)!r}::DOUBLE" for r in layout.rho()) + "]"


def score(layout: Layout, k: str, n: str, p: str, q: str, log: str = "") -> str:
    lg = f"{log or log_miss(layout)}[j]"
    g = f"exp({n} * {lg})"
    zero = f"CASE WHEN {p} = 1 THEN 1 ELSE coalesce(({p} - {q}) * {g} / nullif(1 - {p} + ({p} - {q}) * {g}, 0), 0) END"
    one = f"coalesce(({p} - {q}) * {g} / nullif({p} - ({p} - {q}) * {g}, 0), 0)"
    return f"list_sum(list_transform(range(1, {layout.levels} + 1), lambda j: ({layout.buckets} - {k}[j]) * {zero} * {lg} - {k}[j] * {one} * {lg}))"


def fit(counts: str, layout: Layout, p: float | str, q: float | str, by: str = "g", keep: str = "", steps: int = 60, high: float = 25.0, log: str = "") -> str:
    """by, keep and n_hat by halving log n; counts: by, keep, k (a list), and the columns that p and q name."""
    extra = f"{keep}, " if keep else ""
    return f"""
SELECT {by}, {extra} CASE WHEN s1 <= 0 THEN 0 ELSE exp((a + b) / 2) END AS n_hat FROM (
  WITH RECURSIVE start AS (SELECT {by}, {extra} k, {num(p)} AS p, {num(q)} AS q FROM ({counts})),
  it AS (
    SELECT {by}, {extra} k, p, q, 0 AS i, 0.0::DOUBLE AS a, {high}::DOUBLE AS b, {score(layout, 'k', '1.0', 'p', 'q', log)} AS s1 FROM start
    UNION ALL
    SELECT {by}, {extra} k, p, q, i + 1, CASE WHEN s > 0 THEN mid ELSE a END, CASE WHEN s > 0 THEN b ELSE mid END, s1
    FROM (SELECT *, (a + b) / 2 AS mid, {score(layout, 'k', 'exp((a + b) / 2)', 'p', 'q', log)} AS s FROM it WHERE i < {steps})
  ) SELECT * FROM it WHERE i = {steps}
)"""


def stderr(layout: Layout, n: str, p: str, q: str) -> str:
    lg = f"{log_miss(layout)}[j]"
    g = f"exp({n} * {lg})"
    zero = f"CASE WHEN {p} = 1 THEN 0 ELSE (1 - {p}) / (1 - {p} + ({p} - {q}) * {g}) END"
    return f"1 / sqrt({layout.buckets} * ({p} - {q}) * list_sum(list_transform(range(1, {layout.levels} + 1), lambda j: {lg} * {lg} * {g} * (coalesce({p} / nullif({p} - ({p} - {q}) * {g}, 0), 0) - {zero}))))"


def union_randomized(noisy: str, salt: str, by: str = "g") -> str:
    """noisy: by, cell, bit, eps -> by, cell, bit, star."""
    u = draw("merge", salt, f"CAST({by} AS VARCHAR)", "CAST(cell AS VARCHAR)")
    return f"""
SELECT {by}, cell, star, CAST(CASE WHEN m = 0 THEN false ELSE {u} < CAST(floor((1 / (1 + exp(-star))) * (1 - (CASE WHEN m % 2 = 0 THEN 1 ELSE -1 END) * exp(-s)) * {float(ONE)!r}::DOUBLE) AS BIGINT) END AS INTEGER) AS bit
FROM (SELECT {by}, cell, sum(bit) AS m, sum(CASE WHEN bit = 1 THEN eps ELSE 0 END) AS s, -ln(1 - exp(sum(ln(1 - exp(-eps))))) AS star FROM ({noisy}) GROUP BY {by}, cell)"""
