"""DuckDB SQL that the queries are checked against, put together from common table expressions."""

from __future__ import annotations

C = "c AS MATERIALIZED (SELECT vec_id, unnest(range(len(embedding))) AS pos, unnest(embedding)::DOUBLE AS val FROM embeddings)"
RANKED = "r AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY abs(val) DESC, pos) AS rk FROM c)"
TOP = "t AS MATERIALIZED (SELECT vec_id, max(abs(val)) AS top, sum(abs(val)) AS l1, sum(val*val) AS l2sq, count(*) AS d FROM c GROUP BY vec_id)"


def u(*parts: object) -> str:
    """The hashed uniform of parts (SQL expressions, or numbers)."""
    return "(('0x' || substr(md5(concat_ws('|', " + ", ".join(str(p) for p in parts) + ")), 1, 13))::BIGINT / 4503599627370496.0)"


def with_(*ctes: str, select: str) -> str:
    return "WITH " + ", ".join(ctes) + " " + select


def coords_out(expr: str, source: str, where: str = "") -> str:
    return f"SELECT vec_id, pos, round({expr}, 6) + 0.0 AS val FROM {source} {where}"


def top_k(k: int) -> str:
    return with_(C, RANKED, select=coords_out("val", "r", f"WHERE rk <= {k}"))


def rand_k(k: int, seed: int) -> str:
    return with_(C, f"w AS (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY {u(seed, 'vec_id', 'pos')}, pos) AS rn, count(*) OVER (PARTITION BY vec_id) AS d FROM c)", select=coords_out(f"val * d / {k}.0", "w", f"WHERE rn <= {k}"))


def fixed_point(bits: int) -> str:
    return with_(C, TOP, select=coords_out(f"sign(val) * top * CASE WHEN abs(val) / top >= 1 THEN ({2**bits} - 1) / {2**bits}.0 ELSE floor(abs(val) / top * {2**bits}) / {2**bits}.0 END", "c JOIN t USING (vec_id)"))


LEAD = "pow(2, floor(log2(abs(val))))"


def float_point(bits: int) -> str:
    return with_(C, select=coords_out(f"CASE WHEN val = 0 THEN 0 ELSE sign(val) * {LEAD} * (1 + floor((abs(val) / {LEAD} - 1) * {2**bits}) / {2**bits}.0) END", "c"))


def quantize(steps: int, seed: int) -> str:
    z = f"({steps} * abs(val) / sqrt(l2sq))"
    return with_(C, TOP, select=coords_out(f"sqrt(l2sq) * sign(val) * (floor({z}) + CASE WHEN {u(seed, 'vec_id', 'pos')} < {z} - floor({z}) THEN 1 ELSE 0 END) / {steps}.0", "c JOIN t USING (vec_id)"))


def grid(level: int, clip: str = "grid") -> str:
    delta = f"(2 * top / {2**level - 1}.0)"
    idx = f"round_even(val / {delta}, 0)"
    edge = f"{2 ** (level - 1) - 1}.0" if clip == "grid" else "top"
    return f"greatest(-top, least(top, {delta} * {idx}))" if clip == "value" else f"{delta} * greatest(-{edge}, least({edge}, {idx}))"


def rounded(level: int, clip: str = "grid") -> str:
    return with_(C, TOP, select=coords_out(grid(level, clip), "c JOIN t USING (vec_id)"))


def residuals(family: str, n: int = 0) -> list[str]:
    """CTEs that end in res(vec_id, pos, val, bv, level, r)."""
    if family == "segment":
        return [C, TOP, RANKED, f"res AS MATERIALIZED (SELECT vec_id, pos, val, 0.0 AS bv, ceil(rk / {n}.0)::INT AS level, val AS r FROM r)"]
    if family == "fixed":
        bit = "CASE WHEN abs(val) / top >= 1 THEN 1 ELSE floor(abs(val) / top * pow(2, level)) % 2 END"
        return [C, TOP, f"res AS MATERIALIZED (SELECT vec_id, pos, val, 0.0 AS bv, level, sign(val) * top * ({bit}) / pow(2, level) AS r FROM c JOIN t USING (vec_id), (SELECT unnest(range(1, 64))::INT AS level))"]
    if family in ("float", "float_zero"):
        bit = f"(floor((abs(val) / {LEAD} - 1) * pow(2, level)) % 2)"
        more = f" + CASE WHEN level = 1 THEN sign(val) * {LEAD} ELSE 0 END" if family == "float_zero" else ""
        base = "0.0" if family == "float_zero" else f"sign(val) * {LEAD}"
        return [C, TOP, f"res AS MATERIALIZED (SELECT vec_id, pos, val, {base} AS bv, level, sign(val) * {LEAD} * {bit} / pow(2, level){more} AS r FROM c, (SELECT unnest(range(1, 53))::INT AS level))"]
    if family == "custom":
        few, grid4 = "CASE WHEN rk <= 4 THEN val ELSE 0 END", grid(4)
        steps = (few, f"{grid4} - {few}", f"val - {grid4}")
        ladder = " UNION ALL ".join(f"SELECT vec_id, pos, val, 0.0 AS bv, {l} AS level, {r} AS r FROM r JOIN t USING (vec_id)" for l, r in enumerate(steps, 1))
        return [C, TOP, RANKED, f"res AS MATERIALIZED ({ladder})"]
    parts = " UNION ALL ".join(f"SELECT vec_id, pos, val, 0.0 AS bv, {l} AS level, {'val' if l == n else grid(l)} - {'0' if l == 1 else grid(l - 1)} AS r FROM c JOIN t USING (vec_id)" for l in range(1, n + 1))
    return [C, TOP, f"res AS MATERIALIZED ({parts})"]


def deltas(family: str, n: int = 0) -> list[str]:
    return [*residuals(family, n), "dl AS MATERIALIZED (SELECT vec_id, level, sqrt(sum(r*r)) AS delta FROM res GROUP BY vec_id, level)"]


def probs(family: str, n: int = 0, how: str = "adaptive") -> list[str]:
    """CTEs that end in pr(vec_id, level, q)."""
    if how == "adaptive":
        return [*deltas(family, n), "pr AS MATERIALIZED (SELECT vec_id, level, delta / sum(delta) OVER (PARTITION BY vec_id) AS q FROM dl)"]
    if how == "uniform":
        return [*residuals(family, n), f"pr AS MATERIALIZED (SELECT vec_id, level, 1 / {n}::DOUBLE AS q FROM (SELECT DISTINCT vec_id FROM c), (SELECT unnest(range(1, {n + 1}))::INT AS level))"]
    depth = int(how)
    return [*residuals(family, n), f"pr AS MATERIALIZED (SELECT vec_id, level, pow(2, -level) / (1 - pow(2, -{depth})) AS q FROM (SELECT DISTINCT vec_id FROM c), (SELECT unnest(range(1, {depth + 1}))::INT AS level))"]


def estimate(family: str, n: int = 0, how: str = "adaptive", seed: int = 0) -> str:
    return with_(
        *probs(family, n, how),
        f"b AS (SELECT vec_id, level, q, sum(q) OVER w AS hi, max(CASE WHEN q > 0 THEN level END) OVER (PARTITION BY vec_id) AS last, {u(seed, 'vec_id')} AS u FROM pr WINDOW w AS (PARTITION BY vec_id ORDER BY level ROWS UNBOUNDED PRECEDING))",
        "drawn AS MATERIALIZED (SELECT vec_id, level, q FROM b WHERE q > 0 AND hi - q <= u AND u < CASE WHEN level >= last THEN 1.0 ELSE hi END)",
        select="SELECT vec_id, level, round(q, 9) AS q, pos, round(bv + r / q, 6) AS val FROM res JOIN drawn USING (vec_id, level)",
    )


def variance(family: str, n: int = 0, how: str = "adaptive") -> str:
    return with_(
        *probs(family, n, how),
        "d2 AS (SELECT vec_id, level, sum(r*r) AS d2 FROM res GROUP BY vec_id, level)",
        "s AS (SELECT vec_id, sum(d2 / q) AS second_moment FROM d2 JOIN pr USING (vec_id, level) WHERE q > 0 GROUP BY vec_id)",
        "rest AS (SELECT vec_id, sum((val - bv) * (val - bv)) AS r2 FROM (SELECT DISTINCT vec_id, pos, val, bv FROM res) GROUP BY vec_id)",
        select="SELECT vec_id, round(second_moment, 6) AS second_moment, round(second_moment - r2, 6) AS variance, round(l2sq, 6) AS norm2 FROM s JOIN rest USING (vec_id) JOIN t USING (vec_id)",
    )


def drawn_by_events(probs: str, seed: int = 13) -> str:
    """level, q, n of a query ``probs`` of level and q."""
    return with_(
        f"p AS ({probs})",
        "b AS (SELECT level, q, sum(q) OVER (ORDER BY level ROWS UNBOUNDED PRECEDING) AS hi, max(CASE WHEN q > 0 THEN level END) OVER () AS last FROM p)",
        f"e AS (SELECT {u(seed, 'event_id')} AS u FROM events)",
        "n AS (SELECT level, count(*) AS n FROM e JOIN b ON hi - q <= u AND u < CASE WHEN level >= last THEN 1.0 ELSE hi END WHERE q > 0 GROUP BY level)",
        select="SELECT level, round(q, 12) AS q, coalesce(n, 0) AS n FROM p LEFT JOIN n USING (level)",
    )


VECTOR = with_(C, select=coords_out("val", "c"))
