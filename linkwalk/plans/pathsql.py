"""A small SQL surface: graphs and answers as views, and path queries as text."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame

from ..operators.product import reach
from ..operators.search import SearchRun, answers_only, complete, run
from ..sources.graph import TripleGraph

QUERY = re.compile(r"^\s*(?P<start>\S+)\s+(?P<expr>.+?)\s+\?(?P<var>\w+)(?:\s+limit\s+(?P<n>\d+))?\s*$", re.IGNORECASE | re.DOTALL)


def register(graph: TripleGraph, prefix: str = "graph") -> None:
    graph.triples.createOrReplaceTempView(f"{prefix}_triples")
    graph.adjacency().createOrReplaceTempView(f"{prefix}_adjacency")


def register_run(result: SearchRun, prefix: str = "run") -> None:
    result.answers().createOrReplaceTempView(f"{prefix}_answers")
    result.trace().createOrReplaceTempView(f"{prefix}_trace")


def path_query(graph: TripleGraph, text: str) -> DataFrame:
    """``start expression ?x`` gives all nodes as column x with their lengths; ``limit n`` makes it a best-first search for the
    n nearest."""
    m = QUERY.match(text)
    if not m:
        raise ValueError("a path query reads: start expression ?variable [limit n]")
    if m["n"]:
        result = run(graph, m["expr"], m["start"], k=None, batch="bucket", limits=answers_only(int(m["n"])))
        found = complete(result).top(int(m["n"])).select("node", "length")
    else:
        found = reach(graph, m["expr"], m["start"])
    return found.withColumnRenamed("node", m["var"])
