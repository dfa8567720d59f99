"""Patterns with variables over a graph: joins, optional parts, existence tests, path patterns."""

from __future__ import annotations

from functools import reduce as fold

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.graph import TripleGraph
from .product import reach_from

Pattern = tuple[str, str, str]


def solve(graph: TripleGraph, pattern: Pattern) -> DataFrame:
    """Bindings of one pattern; a term ``?x`` is a variable, anything else a constant. The label may be a variable too."""
    s, p, o = pattern
    rows = graph.match(*[None if t.startswith("?") else t for t in pattern])
    names: dict[str, list[str]] = {}
    for term, column in ((s, "s"), (p, "p"), (o, "o")):
        if term.startswith("?"):
            names.setdefault(term[1:], []).append(column)
    for columns in names.values():
        for other in columns[1:]:
            rows = rows.where(F.col(columns[0]) == F.col(other))
    return rows.select(*[F.col(c[0]).alias(v) for v, c in names.items()]).distinct()


def _shared(a: DataFrame, b: DataFrame) -> list[str]:
    both = [c for c in a.columns if c in b.columns]
    if not both:
        raise ValueError("patterns share no variable")
    return both


def join(graph: TripleGraph, patterns: list[Pattern]) -> DataFrame:
    """Bindings of all patterns together; each next one must share a variable with those before it."""
    return fold(lambda a, b: a.join(b, _shared(a, b)), [solve(graph, p) for p in patterns])


def optional(graph: TripleGraph, bindings: DataFrame, patterns: list[Pattern]) -> DataFrame:
    """Adds the bindings of the patterns where there are any."""
    more = join(graph, patterns)
    return bindings.join(more, _shared(bindings, more), "left_outer")


def exists(graph: TripleGraph, bindings: DataFrame, patterns: list[Pattern], negated: bool = False) -> DataFrame:
    more = join(graph, patterns)
    return bindings.join(more, _shared(bindings, more), "left_anti" if negated else "left_semi")


def path(graph: TripleGraph, bindings: DataFrame, start: str, expr: str, end: str) -> DataFrame:
    """Follows a path expression from the values of variable ``start``; binds ``end``."""
    starts = bindings.select(start).distinct()
    found = reach_from(graph, expr, starts, start).select(start, F.col("node").alias(end)).distinct()
    return bindings.join(found, [start, end] if end in bindings.columns else [start])
