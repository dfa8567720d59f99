"""Measures of search runs: curves, dominance, lengths, speed-up, memory, optimality, recall."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .deref import Latency
from .product import Reached
from .search import SearchRun, timed


def requests(run: SearchRun, count: str = "expansion") -> DataFrame:
    """``(run, req, total)``: requests so far after each expansion. ``expansion`` counts each expansion once, ``distinct_doc``
    each node once however often it is expanded, ``paid`` what the lookup charged."""
    t = run.trace()
    if count == "expansion":
        each = F.lit(1)
    elif count == "distinct_doc":
        t = t.withColumn("first_", F.row_number().over(Window.partitionBy("run", "node").orderBy("req")) == 1)
        each = F.col("first_").cast("int")
    elif count == "paid":
        each = F.col("requests")
    else:
        raise ValueError(f"unknown count {count!r}")
    w = Window.partitionBy("run").orderBy("req").rowsBetween(Window.unboundedPreceding, 0)
    return t.select("run", "req", F.sum(each).over(w).cast("long").alias("total"))


def curve(run: SearchRun, x: str = "requests", count: str = "expansion", latency: Latency | None = None, available: int | None = None) -> DataFrame:
    """``(run, x, answers)``: a step for each answer. With ``available`` answers are a share of all that exist."""
    a = run.answers().select("run", "rank", "req_at_emit")
    if x == "requests":
        at = requests(run, count).select("run", F.col("req").alias("req_at_emit"), F.col("total").cast("double").alias("x"))
    elif x == "seconds":
        at = timed(run, latency or Latency()).select("run", F.col("req").alias("req_at_emit"), F.col("seconds").alias("x"))
    else:
        raise ValueError(f"unknown axis {x!r}")
    out = a.join(at, ["run", "req_at_emit"], "left").select("run", F.coalesce("x", F.lit(0.0)).alias("x"), "rank")
    out = out.groupBy("run", "x").agg(F.max("rank").alias("answers"))
    return out if available is None else out.withColumn("answers", F.col("answers") / float(max(1, available)))


def finished(run: SearchRun, x: str = "requests", latency: Latency | None = None) -> DataFrame:
    """``(run, x)``: where each run ended."""
    if x == "requests":
        return run.trace().groupBy("run").agg(F.max("req").cast("double").alias("x"))
    return timed(run, latency or Latency()).groupBy("run").agg(F.max("seconds").alias("x"))


def dominance(curves: DataFrame, ends: DataFrame, share: float = 0.8, points: int = 400, by: tuple[str, ...] = ()) -> DataFrame:
    """``(by, run, dominates, share)``. A run dominates if its curve is at least every other's on ``share`` of the range, which goes
    from nothing to the furthest end; a finished curve keeps its last value. Curves are read at evenly spaced points, each
    taking the last step at or before it. Runs are compared with those that agree on the columns ``by``."""
    by = list(by)
    runs = ends.withColumn("top", F.max("x").over(Window.partitionBy(*by)) if by else F.max("x").over(Window.partitionBy(F.lit(1)))).select(*by, "run", "top").distinct()
    # Each point takes the last step before it: points and steps in one order, the last value carried forward by run.
    steps = curves.select(*by, "run", "x", "answers", F.lit(0).alias("kind"), F.lit(None).cast("int").alias("i"))
    asks = runs.select(*by, "run", "top", F.explode(F.sequence(F.lit(1), F.lit(points))).alias("i"))
    asks = asks.select(*by, "run", (F.col("top") * F.col("i") / points).alias("x"), F.lit(None).cast("double").alias("answers"), F.lit(1).alias("kind"), "i")
    w = Window.partitionBy(*by, "run").orderBy("x", "kind").rowsBetween(Window.unboundedPreceding, 0)
    filled = steps.withColumn("answers", F.col("answers").cast("double")).unionByName(asks).withColumn("value", F.coalesce(F.last("answers", ignorenulls=True).over(w), F.lit(0.0))).where("kind = 1")
    best = filled.withColumn("best", F.max("value").over(Window.partitionBy(*by, "i")))
    got = best.groupBy(*by, "run").agg(F.avg((F.col("value") >= F.col("best")).cast("double")).alias("share"))
    return got.select(*by, "run", (F.col("share") >= share).alias("dominates"), "share")


def tally(rows: DataFrame) -> DataFrame:
    """``rows(axis, k, strategy, dominates)`` → how often each strategy dominates, a column for each."""
    return rows.groupBy("axis", "k").pivot("strategy", ["astar", "bfs", "dfs"]).agg(F.sum(F.col("dominates").cast("int")))


def tally_cube(rows: DataFrame) -> DataFrame:
    """Tallies over every combination of axis, k and strategy."""
    return rows.cube("axis", "k", "strategy").agg(F.sum(F.col("dominates").cast("long")).alias("times"), F.grouping_id().alias("level"))


def tally_rollup(rows: DataFrame) -> DataFrame:
    return rows.rollup("axis", "k", "strategy").agg(F.sum(F.col("dominates").cast("long")).alias("times"), F.grouping_id().alias("level"))


def first_answer(run: SearchRun, skip_start: bool = False) -> DataFrame:
    """``(run, requests)`` when the first answer came; ``skip_start`` passes over one that costs nothing."""
    a = run.answers()
    if skip_start:
        a = a.where("length > 0")
    return a.groupBy("run").agg(F.min("req_at_emit").alias("requests"))


def lengths_at(run: SearchRun, ranks: list[int]) -> DataFrame:
    return run.answers().where(F.col("rank").isin(ranks)).select("run", "rank", "length")


def speed_up(run: SearchRun, base: int, latency: Latency | None = None) -> DataFrame:
    """``(run, answers, speed_up)``: simulated time of run ``base`` over each run's, at the last answer that both have."""
    c = curve(run, "seconds", latency=latency)
    mine = c.where(F.col("run") == base)
    last = mine.agg(F.max("answers").alias("m"))
    common = c.groupBy("run").agg(F.max("answers").alias("n")).join(F.broadcast(last)).select("run", F.least("n", "m").alias("n"))
    at = c.join(F.broadcast(common), "run").where(F.col("answers") >= F.col("n")).groupBy("run", "n").agg(F.min("x").alias("x"))
    of = common.join(mine.select(F.col("answers").alias("a"), F.col("x").alias("b"))).where("a >= n").groupBy("run").agg(F.min("b").alias("b"))
    return at.join(of, "run").select("run", F.col("n").alias("answers"), (F.col("b") / F.col("x")).alias("speed_up"))


def triples(run: SearchRun) -> DataFrame:
    return run.trace().groupBy("run").agg(F.sum("n_triples").alias("triples"))


def memory(run: SearchRun) -> DataFrame:
    """``(run, open_peak, seen, answers, rounds)``."""
    rows = [(i, run.open_peak.get(i, 0), run.seen_size.get(i, 0), run.rounds.get(i, 0)) for i in range(len(run.specs))]
    answers = run.answers()
    held = answers.sparkSession.createDataFrame(rows, "run int, open_peak long, seen long, rounds int")
    return held.join(answers.groupBy("run").agg(F.count(F.lit(1)).alias("answers")), "run", "left").na.fill(0, ["answers"])


def optimality_gap(run: SearchRun, reached: DataFrame) -> DataFrame:
    """``(run, rank, gap)``: the n-th answer's length less the n-th shortest one. ``reached(run, node, length)`` holds the exact
    lengths over the graph that each run discovered; see :func:`discovered_lengths`."""
    ideal = reached.withColumn("rank", F.row_number().over(Window.partitionBy("run").orderBy("length", "node"))).select("run", "rank", F.col("length").alias("ideal"))
    return run.answers().join(ideal, ["run", "rank"]).select("run", "rank", (F.col("length") - F.col("ideal")).cast("int").alias("gap"))


def discovered_lengths(run: SearchRun, steps: DataFrame) -> DataFrame:
    """``(run, node, length)``: least answer lengths over product edges whose source the run expanded. ``steps`` are all
    product edges ``(node, q, node2, q2)``; layers grow as in exact evaluation, with the run as part of every key."""
    from ..functions.tables import keep

    finals = sorted(run.automaton.finals)
    edges = keep(steps.join(run.discovered(), ["node", "q"]).select("run", "node", "q", "node2", "q2").distinct())
    start = run.state.where("parent_node is null").select("run", "node", "q", F.lit(0).alias("length"))
    front = keep(start)
    seen = front
    depth = 0
    while not front.isEmpty():
        depth += 1
        ahead = front.join(edges, ["run", "node", "q"]).select("run", F.col("node2").alias("node"), F.col("q2").alias("q")).distinct()
        front = keep(ahead.join(seen.select("run", "node", "q"), ["run", "node", "q"], "left_anti").withColumn("length", F.lit(depth)))
        seen = keep(seen.unionByName(front))
    return seen.where(F.col("q").isin(finals)).groupBy("run", "node").agg(F.min("length").alias("length"))


def expansion_containment(run: SearchRun, inner: int, outer: int) -> DataFrame:
    """Product nodes that run ``inner`` expanded and run ``outer`` did not. ``outer``, a breadth-first run, should have finished the
    layers up to the length of ``inner``'s last answer: then none is expected."""
    mine = run.trace().where(F.col("run") == inner).select("node", "q")
    theirs = run.trace().where(F.col("run") == outer).select("node", "q")
    return mine.distinct().join(theirs, ["node", "q"], "left_anti")


def recall(found: DataFrame, exact: DataFrame) -> DataFrame:
    """``(found, there, recall)`` of answer nodes."""
    hit = exact.select("node").join(found.select("node").distinct(), "node", "left_semi").agg(F.count(F.lit(1)).alias("found"))
    return hit.join(F.broadcast(exact.agg(F.count(F.lit(1)).alias("there")))).select("found", "there", (F.col("found") / F.greatest(F.col("there"), F.lit(1))).alias("recall"))


def same_lengths(run: SearchRun, a: int, b: int) -> DataFrame:
    """Ranks at which two runs' answers differ in length; empty if they agree."""
    of = lambda i, c: run.answers().where(F.col("run") == i).select("rank", F.col("length").alias(c))
    return of(a, "a").join(of(b, "b"), "rank", "full_outer").where(~F.col("a").eqNullSafe(F.col("b")))


def layer_requests(reached: Reached) -> DataFrame:
    """``(length, expansions)``: what breadth-first search spends on each layer, from the exact layers: no run is needed."""
    live = sorted({q for q, _, _ in reached.automaton.edges})
    hits = reached.table.where(F.col("q").isin(live) & ~F.startswith("node", F.lit('"')))
    return hits.groupBy("length").agg(F.count(F.lit(1)).alias("expansions"))

