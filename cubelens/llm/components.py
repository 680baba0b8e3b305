"""Connected components of an edge table by alternating star contraction, with DataFrame joins only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubelens.storage import keep, materialize, release


def _large_star(edges: DataFrame) -> DataFrame:
    """Every neighbour above a node moves to the node's smallest neighbour."""
    both = edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    moved = both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.filter("u <> v").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """A node and its lower neighbours move to the lowest of them. ``edges`` have u > v."""
    least = edges.groupBy("u").agg(F.min("v").alias("m"))
    moved = edges.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.unionByName(least.select("u", F.col("m").alias("v"))).filter("u <> v").distinct()


def _digest(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, root): every node with an edge and the smallest node reachable from it, roots left out.

    edges: two BIGINT columns u, v; repeated edges, both directions and loops are allowed.
    Each round is two joins and two aggregations over the edges; the number of rounds
    grows with the logarithm of a component's size, and each is cut by a written table.
    """
    now = materialize(edges.filter("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
    seen = _digest(now)
    for _ in range(max_rounds if seen[0] else 0):
        nxt = materialize(_small_star(_large_star(now)), "edges")
        release(now)
        now, last, seen = nxt, seen, _digest(nxt)
        if seen == last:
            break
    else:
        if seen[0]:
            raise RuntimeError("components did not settle")
    return keep(now.select(F.col("u").alias("node"), F.col("v").alias("root")), now)
