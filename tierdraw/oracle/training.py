"""Training runs in DuckDB's SQL, one set of common table expressions a step."""

from __future__ import annotations

from .sql import u

ROWS = (
    "samples AS MATERIALIZED (SELECT l_orderkey * 8 + l_linenumber AS key, ((l_orderkey * 8 + l_linenumber) % {m})::INT AS worker, "
    "[1.0::DOUBLE, l_quantity / 50, l_discount * 10, l_tax * 12.5] AS a, l_extendedprice / 50000 AS y FROM lineitem)"
)


def grad(name: str, batch: str, model: str) -> str:
    return f"{name} AS MATERIALIZED (SELECT worker, i AS pos, avg((list_dot_product(a, x) - y) * a[i + 1]) AS val FROM {batch}, (SELECT list(val ORDER BY pos) AS x FROM {model}), (SELECT unnest(range(4)) AS i) GROUP BY worker, i)"


def compress(kind: str, src: str, out: str, step: int, seed: int, k: int) -> list[str]:
    """CTEs from src(worker, pos, val) to out(worker, pos, val)."""
    if kind == "plain":
        return [f"{out} AS (SELECT * FROM {src})"]
    if kind == "topk":
        return [f"{out} AS (SELECT worker, pos, val FROM {src} QUALIFY row_number() OVER (PARTITION BY worker ORDER BY abs(val) DESC, pos) <= {k})"]
    if kind == "randk":
        return [f"{out} AS (SELECT worker, pos, val * 4 / {k}.0 AS val FROM {src} QUALIFY row_number() OVER (PARTITION BY worker ORDER BY {u(seed, step, 'worker', 'pos')}, pos) <= {k})"]
    if kind == "fixed":
        bit = "CASE WHEN top = 0 THEN 0 WHEN abs(val) / top >= 1 THEN 1 ELSE floor(abs(val) / top * pow(2, level)) % 2 END"
        hi = "1 - pow(2, -level)"
        return [
            f"{out}d AS (SELECT worker, min(level) AS level FROM (SELECT DISTINCT worker, {u(seed, step, 'worker')} AS u FROM {src}), (SELECT unnest(range(1, 64))::INT AS level) WHERE u < CASE WHEN level = 63 THEN 1 ELSE ({hi}) / (1 - pow(2, -63)) END GROUP BY worker)",
            f"{out} AS MATERIALIZED (SELECT worker, pos, sign(val) * top * ({bit}) / pow(2, level) / (pow(2, -level) / (1 - pow(2, -63))) AS val FROM (SELECT *, max(abs(val)) OVER (PARTITION BY worker) AS top FROM {src}) JOIN {out}d USING (worker))",
        ]
    if kind == "segment":
        return [
            f"{out}r AS MATERIALIZED (SELECT worker, pos, val, ceil(row_number() OVER (PARTITION BY worker ORDER BY abs(val) DESC, pos) / {k}.0)::INT AS level FROM {src})",
            f"{out}q AS (SELECT worker, level, delta / sum(delta) OVER (PARTITION BY worker) AS q FROM (SELECT worker, level, sqrt(sum(val * val)) AS delta FROM {out}r GROUP BY worker, level))",
            f"{out}b AS (SELECT *, sum(q) OVER (PARTITION BY worker ORDER BY level ROWS UNBOUNDED PRECEDING) AS hi, max(CASE WHEN q > 0 THEN level END) OVER (PARTITION BY worker) AS last, {u(seed, step, 'worker')} AS u FROM {out}q)",
            f"{out} AS MATERIALIZED (SELECT worker, pos, val / q AS val FROM {out}r JOIN (SELECT worker, level, q FROM {out}b WHERE q > 0 AND hi - q <= u AND u < CASE WHEN level >= last THEN 1 ELSE hi END) USING (worker, level))",
        ]
    raise ValueError(kind)


def run(kind: str, steps: int, eta: float, m: int, fraction: float, seed: int, k: int = 1, beta: float = 0.1, p: float = 0.5, a: float = 0.2) -> str:
    """step, pos, val of the models of a run; kind: plain, topk, randk, fixed, segment, ef21m (top-k inside), marina and dasha (segment inside)."""
    out = [ROWS.format(m=m), "x1 AS MATERIALIZED (SELECT unnest(range(4)) AS pos, 0.0::DOUBLE AS val)"]
    for t in range(1, steps + 1):
        where = "" if fraction >= 1 else f" WHERE {u(seed, chr(39) + 'b' + chr(39), t, 'key')} < {fraction}"
        out += [f"b{t} AS MATERIALIZED (SELECT * FROM samples{where})", grad(f"g{t}", f"b{t}", f"x{t}")]
        if kind == "ef21m":
            if t == 1:
                out.append("s1 AS MATERIALIZED (SELECT worker, pos, val AS mo, val AS tr FROM g1)")
            else:
                out.append(f"v{t} AS MATERIALIZED (SELECT worker, pos, {1 - beta} * mo + {beta} * val AS mo, tr, {1 - beta} * mo + {beta} * val - tr AS val FROM s{t - 1} JOIN g{t} USING (worker, pos))")
                out += compress("topk", f"(SELECT worker, pos, val FROM v{t})", f"c{t}", t, seed, k)
                out.append(f"s{t} AS MATERIALIZED (SELECT worker, pos, mo, tr + coalesce(c.val, 0) AS tr FROM v{t} LEFT JOIN c{t} c USING (worker, pos))")
            out.append(f"m{t} AS (SELECT worker, pos, tr AS val FROM s{t})")
        elif kind == "marina":
            if t == 1:
                out.append("m1 AS MATERIALIZED (SELECT * FROM g1)")
            else:
                out += [grad(f"h{t}", f"b{t}", f"x{t - 1}"), f"d{t} AS MATERIALIZED (SELECT worker, pos, g.val - h.val AS val FROM g{t} g JOIN h{t} h USING (worker, pos))", *compress("segment", f"d{t}", f"c{t}", t, seed, k)]
                coin = u(seed, "'coin'", t)
                out.append(f"m{t} AS MATERIALIZED (SELECT worker, pos, CASE WHEN {coin} < {p} THEN g.val ELSE m.val + coalesce(c.val, 0) END AS val FROM m{t - 1} m JOIN g{t} g USING (worker, pos) LEFT JOIN c{t} c USING (worker, pos))")
        elif kind == "dasha":
            if t == 1:
                out += ["m1 AS MATERIALIZED (SELECT * FROM g1)"]
            else:
                out += [f"d{t} AS MATERIALIZED (SELECT worker, pos, g.val - h.val - {a} * (m.val - h.val) AS val FROM g{t} g JOIN g{t - 1} h USING (worker, pos) JOIN m{t - 1} m USING (worker, pos))", *compress("segment", f"d{t}", f"c{t}", t, seed, k)]
                out.append(f"m{t} AS MATERIALIZED (SELECT worker, pos, m.val + coalesce(c.val, 0) AS val FROM m{t - 1} m LEFT JOIN c{t} c USING (worker, pos))")
        else:
            out += compress(kind, f"g{t}", f"m{t}", t, seed, k)
        out.append(f"x{t + 1} AS MATERIALIZED (SELECT pos, x.val - {eta} * coalesce(s.val, 0) AS val FROM x{t} x LEFT JOIN (SELECT pos, sum(val) / {m} AS val FROM m{t} GROUP BY pos) s USING (pos))")
    return "WITH " + ", ".join(out) + " " + " UNION ALL ".join(f"SELECT {t - 1} AS step, pos, round(val, 6) AS val FROM x{t}" for t in range(1, steps + 2))
