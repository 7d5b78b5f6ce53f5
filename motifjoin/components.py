"""Distributed union-find: connected components of an edge list by star contraction.

Every round is a few aggregations with map-side combining and equi-joins, so a
node with very many neighbours costs one partial minimum per task and a join
that adaptive execution can split; no task ever holds a whole component.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifjoin.workspace import materialize


def _to_larger(edges: DataFrame) -> DataFrame:
    """Hang every larger neighbour of a node on the smallest node around it."""
    both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v")


def _to_smaller(edges: DataFrame) -> DataFrame:
    """Hang the smaller neighbours of a node, and the node itself, on the smallest of them."""
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = down.groupBy("u").agg(F.min("v").alias("m"))
    rest = down.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v")
    return rest.union(least.select("u", F.col("m").alias("v"))).distinct()


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """``edges(u, v)`` of one orderable type to ``(node, root)``; root = smallest node reached.

    Self-loops and null endpoints are ignored; nodes without an edge are absent
    from the result (each is its own component). The loop ends when a round
    changes nothing, which star contraction reaches in a number of rounds
    logarithmic in practice; not converging in ``max_rounds`` is an error.
    """
    current = materialize(edges.select("u", "v").filter("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
    mark = None
    for _ in range(max_rounds):
        following = materialize(_to_smaller(_to_larger(current)), "edges")
        found = following.agg(F.count(F.lit(1)), F.expr("bit_xor(xxhash64(u, v))")).first()
        if mark is not None and tuple(found) == mark:
            leaves = following.select(F.col("u").alias("node"), F.col("v").alias("root"))
            return leaves.union(leaves.select(F.col("root").alias("node"), "root").distinct())
        mark, current = tuple(found), following
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
