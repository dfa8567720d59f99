"""Expressions as binary relations: every operator evaluated by itself, bottom-up.

This is the declarative meaning, kept as a baseline and as a check on the product evaluation. A star is a closure and can
have a row for each pair of nodes; ``within`` restricts all relations to a set of nodes first.
"""

from __future__ import annotations

from functools import reduce as fold

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.tables import keep
from ..plans.expr import Alt, Empty, Inverse, Label, Nothing, Opt, Other, PathExpr, Plus, Seq, Star, as_expr
from ..sources.graph import TripleGraph


def _terms(graph: TripleGraph, within: DataFrame | None) -> DataFrame:
    nodes = graph.adjacency().select("node").distinct()
    if within is not None:
        nodes = nodes.join(within.select(F.col(within.columns[0]).alias("node")).distinct(), "node", "left_semi")
    return nodes.select(F.col("node").alias("s"), F.col("node").alias("o"))


def closure_of(pairs: DataFrame) -> DataFrame:
    """Pairs joined by one step or more, semi-naive: each round extends only the pairs that the last one found."""
    base = keep(pairs)
    parts, front = [base], base
    while not front.isEmpty():
        longer = front.select("s", F.col("o").alias("m")).join(base.select(F.col("s").alias("m"), "o"), "m").select("s", "o").distinct()
        front = keep(longer.join(fold(DataFrame.unionByName, parts), ["s", "o"], "left_anti"))
        parts.append(front)
    return fold(DataFrame.unionByName, parts)


def eval_pairs(graph: TripleGraph, expr: str | PathExpr, within: DataFrame | None = None) -> DataFrame:
    """``(s, o)``: the relation of ``expr``. Zero-length pairs exist for the terms of the graph only."""
    e = as_expr(expr)
    if isinstance(e, (Label, Other)):
        if isinstance(e, Label):
            t = graph.select_labels([e.name])
        else:
            t = graph.triples.where(~F.col("p").isin(sorted(e.excluded)))
        if within is not None:
            nodes = within.select(F.col(within.columns[0]).alias("s")).distinct()
            t = t.join(nodes, "s", "left_semi").join(nodes.withColumnRenamed("s", "o"), "o", "left_semi")
        out = t.select("s", "o").distinct()
        return out.select(F.col("o").alias("s"), F.col("s").alias("o")) if e.inv else out
    if isinstance(e, Inverse):
        return eval_pairs(graph, e.of, within).select(F.col("o").alias("s"), F.col("s").alias("o"))
    if isinstance(e, Seq):
        left = eval_pairs(graph, e.left, within).select("s", F.col("o").alias("m"))
        return left.join(eval_pairs(graph, e.right, within).select(F.col("s").alias("m"), "o"), "m").select("s", "o").distinct()
    if isinstance(e, Alt):
        return eval_pairs(graph, e.left, within).unionByName(eval_pairs(graph, e.right, within)).distinct()
    if isinstance(e, Opt):
        return eval_pairs(graph, e.of, within).unionByName(_terms(graph, within)).distinct()
    if isinstance(e, Plus):
        return closure_of(eval_pairs(graph, e.of, within))
    if isinstance(e, Star):
        return closure_of(eval_pairs(graph, e.of, within)).unionByName(_terms(graph, within)).distinct()
    if isinstance(e, Empty):
        return _terms(graph, within)
    if isinstance(e, Nothing):
        return graph.spark.createDataFrame([], "s string, o string")
    raise TypeError(f"{type(e).__name__} is no expression")
