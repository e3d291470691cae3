"""The codec's phases as common table expressions for DuckDB, operation for operation like the Column formulas."""

from __future__ import annotations

from ratiobin.sources.series import SERIES_SQL

E = 0.001


def double(x: float) -> str:
    return f"CAST({x!r} AS DOUBLE)"


def ctes(series: str, elem_bytes: int = 8, bits: int | None = None, error_bound: float = E, where: str = "true", group: str | None = None, steps: str = "true", anchor: str = "min") -> str:
    """s series, r ratios, g ranges, b bins, h histogram, k ranks, z sizes, p chosen lengths, c centres, i index.

    series is a name or a select.  where filters ratios, steps filters the series; group is an expression over r whose values choose their own lengths.
    """
    w, keys = double(2 * error_bound), "var, step" + (", grp" if group else "")
    grp = f", {group} AS grp" if group else ""
    bin_ = f"CAST(floor((ratio + {double(error_bound)}) / {w}) AS BIGINT)" if anchor == "zero" else f"CAST(floor((ratio - lo) / {w}) AS BIGINT)"
    centre = f"bin * {w}" if anchor == "zero" else f"lo + (bin + {double(0.5)}) * {w}"
    pick = f"bits = {bits}" if bits else "true"
    return f"""
WITH s AS (SELECT * FROM ({SERIES_SQL.get(series, series)}) WHERE {steps}),
r0 AS (SELECT var, step, pos, prev, cur, CASE WHEN prev IS NOT NULL AND cur IS NOT NULL AND prev <> 0 THEN (cur - prev) / prev END AS ratio FROM (
  SELECT var, step, pos, value AS cur, CASE WHEN lag(step) OVER w = step - 1 THEN lag(value) OVER w END AS prev, min(step) OVER (PARTITION BY var) AS f
  FROM s WINDOW w AS (PARTITION BY var, pos ORDER BY step)) WHERE step > f),
r AS (SELECT *{grp} FROM r0 WHERE {where}),
g AS (SELECT {keys}, min(ratio) AS lo, max(ratio) AS hi, count(*) AS n, count(ratio) AS n_defined FROM r GROUP BY ALL),
b AS (SELECT r.*, lo, {bin_} AS bin FROM r JOIN g USING ({keys})),
h AS (SELECT {keys}, bin, lo, count(*) AS cnt FROM b WHERE bin IS NOT NULL GROUP BY ALL),
k AS (SELECT *, row_number() OVER (PARTITION BY {keys} ORDER BY cnt DESC, bin) AS rank FROM h),
zc AS (SELECT {keys}, n, bits, CAST(coalesce(sum(cnt) FILTER (rank <= (1 << bits) - 1), 0) AS BIGINT) AS covered, count(rank) FILTER (rank <= (1 << bits) - 1) AS used,
  coalesce(sum(cnt * log2(cnt)) FILTER (rank <= (1 << bits) - 1), 0) AS logs
  FROM (SELECT {keys}, n, CAST(unnest(range(1, 17)) AS INTEGER) AS bits FROM g) LEFT JOIN k USING ({keys}) GROUP BY ALL),
z AS (SELECT *, n - covered AS n_exact, pow(2.0, bits) * {elem_bytes} + n * bits / 8.0 + (n - covered) * {elem_bytes} AS est_bytes,
  used * {elem_bytes} + n * (log2(n) - (logs + CASE WHEN n > covered THEN (n - covered) * log2(n - covered) ELSE 0 END) / n) / 8.0 + (n - covered) * {elem_bytes} AS entropy_bytes FROM zc),
p AS (SELECT * FROM z WHERE {pick} QUALIFY row_number() OVER (PARTITION BY {keys} ORDER BY est_bytes, bits) = 1),
c AS (SELECT {keys}, CAST(rank - 1 AS INTEGER) AS idx, bin, {centre} AS centre, cnt FROM k JOIN p USING ({keys}) WHERE rank <= (1 << bits) - 1),
i AS (SELECT b.*, p.bits, c.centre, CAST(coalesce(c.idx, (1 << p.bits) - 1) AS INTEGER) AS idx FROM b JOIN p USING ({keys}) LEFT JOIN c USING ({keys}, bin))
"""


def decoded(series: str, **kw) -> str:
    """The chain of all steps, decoded one step on the other: table d (var, step, pos, value_hat)."""
    return ctes(series, **kw).replace("WITH s AS", "WITH RECURSIVE s AS", 1) + """,
f AS (SELECT var, step, pos, centre, cur FROM i UNION ALL SELECT var, step, pos, NULL, value FROM s WHERE step = (SELECT min(step) FROM s)),
d AS (SELECT var, step, pos, cur AS value_hat FROM f WHERE step = (SELECT min(step) FROM f)
  UNION ALL SELECT f.var, f.step, f.pos, CASE WHEN f.centre IS NULL THEN f.cur ELSE d.value_hat * (1 + f.centre) END FROM d JOIN f ON f.var = d.var AND f.pos = d.pos AND f.step = d.step + 1)
"""
