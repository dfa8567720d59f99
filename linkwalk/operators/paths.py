"""Walks: rebuilt from parent links for the wanted answers only."""

from __future__ import annotations

from functools import reduce as fold

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.tables import keep
from ..plans.automaton import compile_path
from ..plans.expr import PathExpr
from ..sources.graph import TripleGraph
from .product import Reached, succeed
from .search import SearchRun

STEP = "struct<step:int,node:string,label:string,inv:boolean>"


def witness(run: SearchRun, answers: DataFrame | None = None, most_hops: int = 10_000) -> DataFrame:
    """``(run, rank, node, steps)``: one walk for each answer. Each hop is a join of the unfinished answers to their parents;
    ``steps`` starts with the start node, which has no label."""
    answers = run.answers() if answers is None else answers
    links = keep(run.state.select("run", F.col("node").alias("n_"), F.col("q").alias("q_"), "parent_node", "parent_q", "via_label", "via_inv"))
    now = keep(answers.select("run", "rank", F.col("node").alias("goal"), F.col("node").alias("n_"), F.col("q").alias("q_"), F.lit(0).alias("back")))
    hops = []
    for _ in range(most_hops):
        at = keep(now.join(links, ["run", "n_", "q_"]))
        hops.append(at.select("run", "rank", "goal", "back", F.col("n_").alias("node"), F.col("via_label").alias("label"), F.col("via_inv").alias("inv")))
        now = at.where("parent_node is not null").select("run", "rank", "goal", F.col("parent_node").alias("n_"), F.col("parent_q").alias("q_"), (F.col("back") + 1).alias("back"))
        if now.isEmpty():
            break
    else:
        raise RuntimeError(f"walks of more than {most_hops} hops")
    rows = fold(DataFrame.unionByName, hops)
    lists = rows.groupBy("run", "rank", "goal").agg(F.array_sort(F.collect_list(F.struct((-F.col("back")).alias("k"), "node", "label", "inv"))).alias("r"))
    steps = F.transform("r", lambda x, i: F.struct(i.alias("step"), x["node"].alias("node"), x["label"].alias("label"), x["inv"].alias("inv")))
    return lists.select("run", "rank", F.col("goal").alias("node"), steps.alias("steps"))


def shortest_walks(graph: TripleGraph, expr: str | PathExpr, reached: Reached, answers: DataFrame | None = None) -> DataFrame:
    """``(seed, node, steps)``: for each answer the shortest walk that is least when read backwards: at every hop the parent of
    least (node, state, label, direction). Fixed by the data, whatever the order of evaluation."""
    a = compile_path(expr)
    table = reached.table
    delta = a.delta(graph.spark)
    adj = graph.adjacency(a.labels).select("node", "p", "inv", "nbr")
    edges = succeed(table.select("seed", "node", "q", "length"), a, delta, adj).select("seed", F.col("nbr").alias("n_"), F.col("q2").alias("q_"), F.col("length").alias("from_"), F.struct("node", "q", F.col("p").alias("label"), "inv").alias("parent"))
    own = table.select("seed", F.col("node").alias("n_"), F.col("q").alias("q_"), "length")
    best = edges.join(own, ["seed", "n_", "q_"]).where("length = from_ + 1").groupBy("seed", "n_", "q_").agg(F.min("parent").alias("parent"))
    links = keep(best)
    if answers is None:
        hits = table.where(F.col("q").isin(sorted(a.finals)))
        answers = hits.groupBy("seed", "node").agg(F.min(F.struct("length", "q")).alias("m")).select("seed", "node", F.col("m.q").alias("q"))
    now = keep(answers.select("seed", F.col("node").alias("goal"), F.col("node").alias("n_"), F.col("q").alias("q_"), F.lit(0).alias("back")))
    hops = []
    while True:
        at = keep(now.join(links, ["seed", "n_", "q_"], "left"))
        hops.append(at.select("seed", "goal", "back", F.col("n_").alias("node"), F.col("parent.label").alias("label"), F.col("parent.inv").alias("inv")))
        now = at.where("parent is not null").select("seed", "goal", F.col("parent.node").alias("n_"), F.col("parent.q").alias("q_"), (F.col("back") + 1).alias("back"))
        if now.isEmpty():
            break
    rows = fold(DataFrame.unionByName, hops)
    lists = rows.groupBy("seed", "goal").agg(F.array_sort(F.collect_list(F.struct((-F.col("back")).alias("k"), "node", "label", "inv"))).alias("r"))
    steps = F.transform("r", lambda x, i: F.struct(i.alias("step"), x["node"].alias("node"), x["label"].alias("label"), x["inv"].alias("inv")))
    return lists.select("seed", F.col("goal").alias("node"), steps.alias("steps"))


def render(steps: Column | str) -> Column:
    """A walk as text: ``a -label-> b <-label- c``."""
    steps = F.col(steps) if isinstance(steps, str) else steps
    hop = lambda s: F.when(s["label"].isNull(), s["node"]).when(s["inv"], F.concat(F.lit("<-"), s["label"], F.lit("- "), s["node"])).otherwise(F.concat(F.lit("-"), s["label"], F.lit("-> "), s["node"]))
    return F.array_join(F.transform(steps, hop), " ")


def hops(steps: Column | str) -> Column:
    return F.size(steps) - 1


def visits(steps: Column, node: str) -> Column:
    return F.exists(steps, lambda s: s["node"] == node)


def uses(steps: Column, label: str) -> Column:
    return F.exists(steps, lambda s: s["label"] == label)


def path_steps(walks: DataFrame) -> DataFrame:
    """One row for each step of each walk."""
    return walks.select(*[c for c in walks.columns if c != "steps"], F.inline("steps"))


def invalid_hops(graph: TripleGraph, walks: DataFrame) -> DataFrame:
    """Steps whose edge is no triple of the graph; empty for correct walks."""
    keys = [c for c in walks.columns if c != "steps"]
    pairs = walks.select(*keys, F.explode(F.transform(F.slice("steps", 2, 1 << 20), lambda s, i: F.struct(F.get("steps", i)["node"].alias("node"), s["label"].alias("p"), s["inv"].alias("inv"), s["node"].alias("nbr")))).alias("h")).select(*keys, "h.*")
    renamed = pairs.withColumnRenamed("node", "from_") if "node" not in keys else walks.select(F.explode(F.transform(F.slice("steps", 2, 1 << 20), lambda s, i: F.struct(F.get("steps", i)["node"].alias("node"), s["label"].alias("p"), s["inv"].alias("inv"), s["node"].alias("nbr")))).alias("h")).select("h.*").withColumnRenamed("node", "from_")
    return renamed.join(graph.adjacency().select(F.col("node").alias("from_"), "p", "inv", "nbr"), ["from_", "p", "inv", "nbr"], "left_anti")
