"""URL filters: rules first, then a logistic regression on hashed character n-grams of host and path, in DataFrame functions only.

The model is fitted by full-batch descent on a small labelled table of bounded size. Errors, gradients and weights are whole numbers of millionths, so
sums do not depend on the order of rows, and a rerun or another engine gives the same verdicts. Weights come to the driver once a round: BUCKETS numbers.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut

#: Buckets of the hash (three hexadecimal digits of MD5), characters of an n-gram, most labelled URLs of each class, rounds, step of a round.
BUCKETS, GRAM, MAX_PER_CLASS, ROUNDS, RATE = 4096, 3, 1000, 20, 12
MICRO = 1_000_000
#: Fixed values of the contract: rules as (host and path, verdict).
RULES = (("net/", "block"), ("example.net/en/", "allow"), ("example.com/de/", "block"), ("org/fr/", "allow"))
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def split_url(url: Column) -> tuple[Column, Column]:
    """Host and path of a URL; both empty for null or without ``://``."""
    mark = F.instr(url, "://")
    rest = F.when(mark > 0, F.substring(url, mark + 3, F.length(url))).otherwise(F.lit(""))
    rest = F.coalesce(rest, F.lit(""))
    host = F.translate(F.regexp_extract(rest, r"^([^/?#]*)", 1), UPPER, LOWER)
    return host, F.regexp_extract(rest, r"^[^/?#]*(/[^?#]*)", 1)


def rule_of(host: Column, path: Column, rules: Sequence[tuple[str, str]] = RULES) -> tuple[Column, Column]:
    """The longest rule that fits host or a domain above it and begins the path, and its verdict; nulls where none fits. For short lists of rules."""
    name = said = None
    for rule, verdict in sorted(rules, key=lambda r: (-len(r[0]), r[0])):
        at, _, rest = rule.partition("/")
        fits = ((host == at) | host.endswith("." + at)) & path.startswith("/" + rest)
        name = F.when(fits, F.lit(rule)) if name is None else name.when(fits, F.lit(rule))
        said = F.when(fits, F.lit(verdict)) if said is None else said.when(fits, F.lit(verdict))
    return (F.lit(None).cast("string"), F.lit(None).cast("string")) if name is None else (name, said)


def grams(host: Column, path: Column) -> Column:
    """Distinct buckets of the character n-grams of ``h:`` and host and of ``p:`` and path; texts shorter than an n-gram have none."""

    def of(s: Column) -> Column:
        cuts = F.transform(F.sequence(F.lit(1), F.greatest(F.length(s) - (GRAM - 1), F.lit(1))), lambda i: F.substring(s, i, F.lit(GRAM)))
        hashed = F.transform(cuts, lambda g: F.conv(F.substring(F.md5(g.cast("binary")), 1, 3), 16, 10).cast("int"))
        return F.when(F.length(s) >= GRAM, hashed).otherwise(F.array().cast("array<int>"))

    once = lambda value, body: F.transform(F.array(value), body)[0]
    return F.array_distinct(F.concat(once(F.concat(F.lit("h:"), host), of), once(F.concat(F.lit("p:"), path), of)))


def logit(features: Column, weights: Sequence[int]) -> Column:
    """Sum of weights in millionths; the first of ``weights`` is the bias. The list is one constant of the plan, BUCKETS + 1 numbers long."""
    table = F.split(F.lit(",".join(map(str, weights))), ",").cast("array<bigint>")
    return F.aggregate(F.transform(features, lambda f: F.element_at(table, f + 2)), F.element_at(table, 1), lambda a, x: a + x)


def labelled_urls(rows: DataFrame) -> DataFrame:
    """host, path, y: at most MAX_PER_CLASS distinct labelled URLs of each class, the first by MD5. ``rows``: host, path, label (block or allow)."""
    rows = rows.filter("label in ('block', 'allow')").select("host", "path", (F.col("label") == "block").cast("bigint").alias("y")).distinct()
    rows = rows.withColumn("h", F.md5(F.concat_ws("/", "host", "path").cast("binary")))
    pick = lambda y: rows.filter(F.col("y") == y).orderBy("h", "host", "path").limit(MAX_PER_CLASS)
    return pick(1).union(pick(0)).drop("h")


def train(labelled: DataFrame, rounds: int = ROUNDS) -> list[int]:
    """Bias and weights in millionths. ``labelled``: host, path, y, of bounded size. Without both classes: zero weights and a bias that allows."""
    rows = cut(labelled.select("y", grams(F.col("host"), F.col("path")).alias("f")))
    n, blocked = rows.agg(F.count(F.lit(1)), F.coalesce(F.sum("y"), F.lit(0))).first()
    if not 0 < blocked < n:
        return [-MICRO] + [0] * BUCKETS
    weights = [0] * (BUCKETS + 1)
    for _ in range(rounds):
        chance = 1 / (1 + F.exp(-logit(F.col("f"), weights) / MICRO))
        err = F.round((chance - F.col("y")) * MICRO).cast("bigint")
        # the bias is one more bucket, before the others
        parts = rows.select(err.alias("e"), F.explode(F.concat(F.array(F.lit(-1)), "f")).alias("f"))
        for f, g in parts.groupBy("f").agg(F.sum("e").alias("g")).collect():  # at most BUCKETS + 1 rows
            step = g * RATE
            weights[f + 1] -= step // n if step >= 0 else -(-step // n)
    return weights


def judge(pages: DataFrame, labelled: DataFrame | None = None, rules: Sequence[tuple[str, str]] = RULES, url_col: str = "url") -> DataFrame:
    """All rows and columns of ``pages`` plus host, path, rule and verdict (replaced if there).

    A rule's verdict stands; the others are the classifier's: block from a chance of one half on. Without ``labelled`` (host, path, label), URLs that rules
    decide are the labelled ones. Null URLs have empty host and path and get the verdict of a URL without n-grams. Empty table: no rows.
    """
    host, path = split_url(F.col(f"`{url_col}`"))
    keep = [c for c in pages.columns if c not in ("host", "path", "rule", "verdict")]
    rows = pages.select(*[f"`{c}`" for c in keep], host.alias("host"), path.alias("path"))
    rule, said = rule_of(F.col("host"), F.col("path"), rules)
    rows = rows.select("*", rule.alias("rule"), said.alias("said"))
    if labelled is None:
        labelled = rows.select("host", "path", F.col("said").alias("label"))
    weights = train(labelled_urls(labelled))
    blocks = logit(grams(F.col("host"), F.col("path")), weights) >= 0
    guess = F.when(blocks, F.lit("block")).otherwise(F.lit("allow"))
    return rows.select(*[f"`{c}`" for c in keep], "host", "path", "rule", F.coalesce("said", guess).alias("verdict"))


def oracle_sql(rounds: int = ROUNDS) -> str:
    """The query over ``pages`` in DuckDB's SQL: one table of weights a round."""
    fits, order = [], sorted(RULES, key=lambda r: (-len(r[0]), r[0]))
    for rule, verdict in order:
        at, _, rest = rule.partition("/")
        fits.append((f"((host = '{at}' OR suffix(host, '.{at}')) AND prefix(path, '/{rest}'))", rule, verdict))
    case = lambda k: "CASE " + " ".join(f"WHEN {f[0]} THEN '{f[k]}'" for f in fits) + " END"
    feats = "list_distinct(list_concat(" + ", ".join(f"list_transform(range(1, greatest(length({p}) - {GRAM - 2}, 1)), lambda i: ('0x' || substr(md5(substr({p}, i, {GRAM})), 1, 3))::INT)" for p in ("'h:' || host", "'p:' || path")) + "))"
    out = [
        f"WITH cut AS MATERIALIZED (SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages), "
        f"parts AS MATERIALIZED (SELECT page_id, translate(regexp_extract(rest, '^([^/?#]*)', 1), '{UPPER}', '{LOWER}') AS host, regexp_extract(rest, '^[^/?#]*(/[^?#]*)', 1) AS path FROM cut), "
        f"ruled AS MATERIALIZED (SELECT *, {case(1)} AS rule, {case(2)} AS said FROM parts), "
        "seen AS (SELECT DISTINCT host, path, (said = 'block')::BIGINT AS y FROM ruled WHERE said IS NOT NULL), "
        f"ranked AS (SELECT *, row_number() OVER (PARTITION BY y ORDER BY md5(host || '/' || path), host, path) AS rk FROM seen), "
        f"small AS MATERIALIZED (SELECT row_number() OVER (ORDER BY y, rk) AS id, y, {feats} AS f FROM ranked WHERE rk <= {MAX_PER_CLASS}), "
        "long AS MATERIALIZED (SELECT id, y, unnest(list_concat([-1], f)) AS f FROM small), size AS (SELECT count(*) AS n, count(DISTINCT y) AS classes FROM small), "
        "w0 AS MATERIALIZED (SELECT DISTINCT f, 0::BIGINT AS w FROM long)"
    ]
    for k in range(rounds):
        out.append(
            f"e{k} AS (SELECT id, round((1 / (1 + exp(-sum(w) / {MICRO}.0)) - any_value(y)) * {MICRO})::BIGINT AS e FROM long JOIN w{k} USING (f) GROUP BY id), "
            f"w{k + 1} AS MATERIALIZED (SELECT f, any_value(w)::BIGINT - trunc(sum(e)::BIGINT * {RATE} / (SELECT n FROM size))::BIGINT AS w FROM long JOIN e{k} USING (id) JOIN w{k} USING (f) GROUP BY f)"
        )
    out.append(
        f"scored AS (SELECT page_id, coalesce(sum(w), 0) AS s FROM (SELECT page_id, unnest(list_concat([-1], {feats})) AS f FROM ruled) JOIN w{rounds} USING (f) GROUP BY page_id) "
        "SELECT page_id, host, path, rule, coalesce(said, CASE WHEN (SELECT classes FROM size) = 2 AND coalesce(s, 0) >= 0 THEN 'block' ELSE 'allow' END) AS verdict FROM ruled LEFT JOIN scored USING (page_id)"
    )
    return ", ".join(out)
