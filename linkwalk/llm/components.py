"""Connected components by alternating star contraction, as joins and aggregates only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import cut, discard


def _state(edges: DataFrame) -> tuple:
    row = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    return tuple(row)


def _stars(both: DataFrame) -> DataFrame:
    """For every u the least of u and its neighbours; aggregation combines before the shuffle, and the join back is one
    that adaptive execution can split when a hub has very many neighbours."""
    least = both.groupBy("u").agg(F.least(F.col("u"), F.min("v")).alias("m"))
    return both.join(least, "u")


def connected_components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """``edges(u, v)`` of longs → ``(node, component)``: the least node reachable, for each node on an edge.

    Null ends and loops are ignored; repeated edges count once; no edges give no rows. The number of rounds grows with the
    logarithm of the longest path; where ``rounds`` do not do, this raises.
    """
    pairs = edges.where("u is not null and v is not null and u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    now = cut(pairs.distinct())
    state = _state(now)
    for _ in range(rounds if state[0] else 0):
        both = now.select("u", "v").unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = _stars(both).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        # Every edge of the large star points down, so the small star joins each node's smaller neighbours to the least.
        large = cut(large.where("u <> v").distinct())
        small = _stars(large)
        small = small.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(small.select("u", F.col("m").alias("v")))
        after = cut(small.where("u <> v").distinct())
        discard(large)
        then = _state(after)
        discard(now)
        now = after
        if then == state:
            break
        state = then
    else:
        if state[0]:
            raise RuntimeError(f"components did not settle in {rounds} rounds")
    return now.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("component")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
