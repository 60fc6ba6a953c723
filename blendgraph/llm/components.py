"""Connected components of an edge table, by alternating stars."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written


def _mark(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.expr("bit_xor(xxhash64(u, v))")).first())


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """edges(a, b) of longs -> (node, root): the smallest node of each component, for every node in an edge.

    Each round hangs the larger neighbours of a node below its smallest one, then the smaller ones too; it keeps no
    more edges than it got, and takes O(log^2 n) rounds. Rounds are written to the shared folder. A hub's edges are
    only joined with one row for the hub, so a split of the join's large side is enough. Nulls in an edge are left out.
    """
    e = edges.selectExpr("greatest(a, b) AS u", "least(a, b) AS v", "a", "b").filter("a IS NOT NULL AND b IS NOT NULL AND u <> v").select("u", "v").distinct()
    e = written(e, "edges")
    mark = _mark(e)
    for _ in range(max_rounds):
        both = e.unionByName(e.selectExpr("v AS u", "u AS v"))
        # the least are written before each join, so that both sides come by an exchange and a hub's side can be split
        least = written(both.groupBy("u").agg(F.min("v").alias("m")).selectExpr("u", "least(u, m) AS m"), "least")
        large = written(both.join(least, "u").filter("v > u").selectExpr("v AS u", "m AS v").distinct(), "large-stars")
        least = written(large.groupBy("u").agg(F.min("v").alias("m")), "least")
        small = large.join(least, "u").selectExpr("v AS u", "m AS v").filter("u <> v").unionByName(least.selectExpr("u", "m AS v"))
        e = written(small.distinct(), "edges")
        if (now := _mark(e)) == mark:
            break
        mark = now
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return e.selectExpr("u AS node", "v AS root").unionByName(e.selectExpr("v AS node", "v AS root").distinct())
