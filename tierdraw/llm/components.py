"""Connected components of a graph of links, as rounds of DataFrame joins with a checkpoint after each."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut


def components(links: DataFrame) -> DataFrame:
    """node, root for every node of ``links`` (a, b): root is the least node of its component.

    Large-star and small-star rounds: every round hangs all neighbours of a node on the least of them, first the larger, then the smaller
    ones, until no link changes. A node with very many links is combined on the map side (a minimum), never gathered; rounds grow with the logarithm of
    the size of a component. Null ends and loops are left out. No links: no rows.
    """
    edges = links.select(F.col("a").cast("long"), F.col("b").cast("long")).filter("a <> b")
    edges = cut(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    state = _digest(edges)
    while state[0]:
        both = edges.union(edges.select("b", "a"))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("k"), F.least("a", "m").alias("m"))
        large = both.filter("b > a").join(least, F.col("a") == F.col("k")).select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        least = large.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("k"), "m")
        small = large.join(least, F.col("a") == F.col("k"))
        small = small.select(F.col("b").alias("a"), F.col("m").alias("b")).union(small.select("a", F.col("m").alias("b"))).filter("a <> b").distinct()
        edges = cut(small)
        before, state = state, _digest(edges)
        if before == state:
            break
    nodes = edges.select(F.col("a").alias("node"), F.col("b").alias("root"))
    return nodes.union(nodes.select("root", "root").distinct())


def _digest(edges: DataFrame) -> tuple:
    """Number of links and two order-free hashes of them."""
    row = edges.agg(F.count(F.lit(1)), F.expr("bit_xor(xxhash64(a, b))"), F.expr("bit_xor(xxhash64(b, a, 1))")).first()
    return tuple(row)
