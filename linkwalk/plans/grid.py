"""The experiment grid: every workload under every strategy and batch size, and the comparisons drawn from it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import measures
from ..operators.client import ClientRun, Job, search_all
from ..operators.deref import Combined, Endpoint, Latency, Lookup, PartialDocs
from ..operators.search import Limits, Spec
from ..sources.graph import from_testdata
from .workloads import GRID, Workload

STRATEGIES = ("astar", "bfs", "dfs")


def combined(graph) -> Lookup:
    """The lookup of the experiments: incomplete documents, helped by an endpoint."""
    return Combined(PartialDocs(graph, 0.5), Endpoint(graph))


#: Calls at once in the published comparison.
CALLS = (1, 10, 20, 40)


def grid_run(spark: SparkSession, sf_dir: str, workloads: list[Workload] = GRID, ks: tuple[int, ...] = CALLS, limits: Limits = Limits(), strategies: tuple[str, ...] = STRATEGIES, latency: Latency = Latency()) -> ClientRun:  # noqa: B008
    """All strategies and batch sizes of the workloads, stopped by the published limits: 1,000 answers, 100,000 triples or ten
    minutes (of simulated lookups)."""
    # Documents of all sources are laid out once; workloads over the same sources share what they fetch.
    every = combined(from_testdata(spark, sf_dir, sorted({src for w in workloads for src in w.sources})))
    views = {w.sources: every.among(*w.sources) for w in workloads}
    jobs = [Job(views[w.sources], w.expr, w.start, Spec(s, k), w.id) for w in workloads for k in ks for s in strategies]
    return search_all(jobs, limits, latency, links=False)


def dominance_rows(run: ClientRun, axes: tuple[str, ...] = ("requests", "seconds"), latency: Latency = Latency()) -> DataFrame:  # noqa: B008
    """``(workload, axis, k, strategy, dominates, share)``; runs are compared with those of their own workload and k."""
    curves, ends = None, None
    for axis in axes:
        c = run.named(measures.curve(run, axis, latency=latency)).withColumn("axis", F.lit(axis))
        e = run.named(measures.finished(run, axis, latency)).withColumn("axis", F.lit(axis))
        curves, ends = (c, e) if curves is None else (curves.unionByName(c), ends.unionByName(e))
    got = measures.dominance(curves, ends, by=("axis", "name", "k"))
    who = run.spark.createDataFrame([(s.number, s.spec.strategy) for s in run.searches], "run int, strategy string")
    return got.join(F.broadcast(who), "run").select(F.col("name").alias("workload"), "axis", "k", "strategy", "dominates", "share")
