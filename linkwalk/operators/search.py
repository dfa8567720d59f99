"""Search over lookups: depth-first, breadth-first and best-first, one by one or in parallel batches.

All runs of a call (strategies, batch sizes, heuristics) advance together: ``run`` is a key column, and a round is one plan
for all of them. The state of a run is a table of product nodes; a round takes each run's next ``k`` open nodes, looks their
documents up, and merges what they lead to. Only a few numbers for each run come to the driver. A round reads and writes the
state that a run has so far; for the reach of a start without order or budget, :func:`.product.explore` is the form that does not.

Order: a document's triples are taken in the order of (transition, label, direction, neighbour). ``seq`` orders product nodes
as they are first generated: by round, then as a run without batches would have come to them; queues take the least, stacks
the greatest. It is a struct that compares, so no task has to number all successors of a round. Best-first order is (f, then
h where ``tie`` is ``low_h``, then seq). Rounds that take all open nodes, or all of least f, need no order among them and rank
none: their nodes count as one place.

Goals are emitted when generated by the two blind strategies. Best-first search holds a goal back until no open node has a
smaller f; its own place in the queue, with the heuristic of a further answer, only decides when it is *expanded*. All
strategies are credited with an answer at the end of the batch that brought it.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass, field, replace

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.tables import drop, keep
from ..functions.terms import is_literal
from ..plans.automaton import INF, Automaton, accepts_empty, compile_path, heuristic
from ..plans.expr import PathExpr
from ..sources.graph import TripleGraph
from .deref import KEY, FullDocs, Latency, Lookup
from .product import keys_of, succeed

EVERYTHING = 1 << 40


@dataclass(frozen=True)
class Limits:
    """When a run stops: enough answers, too many triples or seconds, or no request left."""

    max_answers: int | None = 1000
    max_triples: int | None = 100_000
    max_seconds: float | None = 600
    max_requests: int | None = None


@dataclass(frozen=True)
class Spec:
    """How one run searches. ``k`` None takes the whole frontier in each round; ``batch="bucket"`` takes all nodes of least f."""

    strategy: str = "astar"
    k: int | None = 1
    heuristic: str = "pathmax"
    tie: str = "low_h"
    emit_rule: str = "early"
    batch: str = "top"
    name: str = ""

    def __post_init__(self):
        if self.strategy not in ("bfs", "dfs", "astar") or self.tie not in ("low_h", "fifo", "lifo") or self.emit_rule not in ("early", "on_extract") or self.batch not in ("top", "bucket"):
            raise ValueError(f"unknown option in {self}")
        if self.k is not None and self.k < 1:
            raise ValueError("k is at least 1")


@dataclass
class SearchRun:
    """The state that a call ended with, and tables derived from it."""

    state: DataFrame
    specs: list[Spec]
    automaton: Automaton
    rounds: dict[int, int] = field(default_factory=dict)
    open_peak: dict[int, int] = field(default_factory=dict)
    seen_size: dict[int, int] = field(default_factory=dict)
    stopped: dict[int, str] = field(default_factory=dict)

    def trace(self) -> DataFrame:
        """``(run, req, round, node, q, g, f, n_triples, requests)``: a row for each expansion, numbered in order."""
        e = self.state.select("run", "node", "q", F.explode("expansions").alias("e")).select("run", "node", "q", "e.*")
        return e.withColumn("req", F.row_number().over(Window.partitionBy("run").orderBy("round", "pos", "node", "q"))).select("run", "req", "round", "pos", "node", "q", "g", "f", "n_triples", "requests")

    def answers(self, dedupe: str = "node") -> DataFrame:
        """``(run, rank, node, q, length, req_at_emit, ...)`` in order of emission; a node counts once unless ``dedupe`` is
        ``product_node``."""
        got = self.state.where(F.col("emit_round").isNotNull())
        if dedupe == "node":
            first = Window.partitionBy("run", "node").orderBy("emit_round", "emit_major", "seq")
            got = got.withColumn("r_", F.row_number().over(first)).where("r_ = 1").drop("r_")
        rank = F.row_number().over(Window.partitionBy("run").orderBy("emit_round", "emit_major", "seq"))
        limit = F.create_map(*[x for i, _ in enumerate(self.specs) for x in (F.lit(i), F.lit(self.most or EVERYTHING))])
        out = got.withColumn("rank", rank)
        out = out.where(F.col("rank") <= self.most) if self.most else out.where(F.col("rank") <= F.element_at(limit, F.col("run")))
        return out.select("run", "rank", "node", "q", F.col("g").alias("length"), F.col("emit_req").cast("long").alias("req_at_emit"), "emit_round", "parent_node", "parent_q")

    most: int | None = None

    def discovered(self) -> DataFrame:
        """``(run, node, q)`` of all expanded product nodes."""
        return self.state.where(F.size("expansions") > 0).select(*KEY)

    def length_histogram(self) -> DataFrame:
        return self.answers().groupBy("run", "length").agg(F.count(F.lit(1)).alias("answers"))

    def count_answers(self, approx: bool = False) -> DataFrame:
        return self.answers().groupBy("run").agg((F.approx_count_distinct("node") if approx else F.count_distinct("node")).alias("answers"))

    def top(self, n: int) -> DataFrame:
        """The n first answers by length, then name."""
        return self.answers().orderBy("length", "node", "run").limit(n)

    def write(self, path: str) -> None:
        self.trace().write.mode("overwrite").parquet(f"{path}/trace")
        self.answers().write.mode("overwrite").parquet(f"{path}/answers")
        self.state.write.mode("overwrite").parquet(f"{path}/state")


_STATE = (
    "run int, node string, q int, g double, f double, h double, seq struct<round:int,turn:int,t_rank:int,label:string,inv:boolean,node:string,q:int>, parent_node string, parent_q int, via_label string, via_inv boolean,"
    " open boolean, goal boolean, emit_round int, emit_major double, emit_req long,"
    " expansions array<struct<round:int,pos:int,g:double,f:double,n_triples:long,requests:long>>"
)


def _per_run(values: dict[int, object], kind: str) -> Column:
    pairs = [x for run, v in values.items() for x in (F.lit(run), F.lit(v).cast(kind))]
    return F.element_at(F.create_map(*pairs), F.col("run"))


class _Rounds:
    """One call's loop over rounds."""

    def __init__(self, graph: TripleGraph, expr: str | PathExpr, start: str, specs: list[Spec], limits: Limits, lookup: Lookup | None, costs: dict[str, float] | None):
        self.spark, self.specs, self.limits, self.start = graph.spark, specs, limits, start
        self.automaton = compile_path(expr)
        self.lookup = lookup or FullDocs(graph)
        n = int(self.spark.conf.get("spark.sql.shuffle.partitions"))
        self.delta = self.automaton.delta(self.spark, costs)
        # Documents hold all labels; matching reads the wanted ones only.
        self.adj = self.lookup.edges(self.automaton.labels).select("node", "p", "inv", "nbr").repartition(n, *keys_of(self.automaton)).persist(StorageLevel.MEMORY_AND_DISK)
        self.docs = self.lookup.sizes().repartition(n, "node").persist(StorageLevel.MEMORY_AND_DISK)
        self.guides = {i: heuristic(self.automaton, s.heuristic, costs) if s.strategy == "astar" else dict.fromkeys(range(self.automaton.size), 0.0) for i, s in enumerate(specs)}
        dead = heuristic(self.automaton, "pathmax", costs)
        rows = [(i, q, (None if h == INF or dead[q] == INF else float(h))) for i, by in self.guides.items() for q, h in by.items()]
        self.guide = self.spark.createDataFrame(rows, "run int, q int, h double")
        self.active = set(range(len(specs)))
        self.requests = dict.fromkeys(self.active, 0)
        self.result = SearchRun(self.spark.createDataFrame([], _STATE), specs, self.automaton, most=limits.max_answers)
        self.began = time.time()

    def kind(self, *names: str) -> Column:
        return F.col("run").isin([i for i, s in enumerate(self.specs) if s.strategy in names])

    def seed(self) -> DataFrame:
        rows = []
        for i, s in enumerate(self.specs):
            h = self.guides[i][0]
            live = h < INF and bool(self.automaton.outgoing(0)) and not self.start.startswith('"')
            goal = accepts_empty(self.automaton)
            rows.append((i, self.start, 0, 0.0, h if live else 0.0, h if live else 0.0, (0, 0, 0, "", False, self.start, 0), None, None, None, None, live, goal, 0 if goal else None, 0.0, 0, []))
        return keep(self.spark.createDataFrame(rows, _STATE))

    def pick(self, state: DataFrame) -> DataFrame:
        """Each run's next open nodes with their places in the batch. The rank limit is applied before rows are shuffled."""
        best, queue = self.kind("astar"), self.kind("bfs", "astar")
        lifo = F.col("run").isin([i for i, s in enumerate(self.specs) if s.strategy == "astar" and s.tie == "lifo"])
        low = F.col("run").isin([i for i, s in enumerate(self.specs) if s.tie == "low_h"])
        order = [F.when(best, F.col("f")).otherwise(0.0), F.when(best & low, F.col("h")).otherwise(0.0), F.when(queue & ~lifo, F.col("seq")).asc(), F.when(~(queue & ~lifo), F.col("seq")).desc()]
        left = {i: (s.k or EVERYTHING) if self.limits.max_requests is None else min(s.k or EVERYTHING, max(0, self.limits.max_requests - self.requests[i])) for i, s in enumerate(self.specs)}
        ready = state.where(F.col("open") & F.col("run").isin(sorted(self.active)))
        buckets = [i for i, s in enumerate(self.specs) if s.batch == "bucket"]
        if buckets:
            least = _per_run({i: self.least_f.get(i, 0.0) for i in range(len(self.specs))}, "double")
            ready = ready.where(~F.col("run").isin(buckets) | (F.col("f") <= least))
            left |= {i: EVERYTHING for i in buckets if self.limits.max_requests is None}
        ranked = [i for i, m in left.items() if m < EVERYTHING and i in self.active]
        whole = ready.where(~F.col("run").isin(ranked)).withColumn("pos", F.lit(0))
        if not ranked:
            return whole
        w = Window.partitionBy("run").orderBy(*order)
        # The literal bound lets Spark keep only the first rows of each task; the exact bound differs by run.
        picked = ready.where(F.col("run").isin(ranked)).withColumn("pos", F.row_number().over(w)).where(F.col("pos") <= max(left[i] for i in ranked))
        return picked.where(F.col("pos") <= _per_run(left, "long")).unionByName(whole)

    def step(self, state: DataFrame, number: int) -> DataFrame:
        """One round: picks, lookups, merge."""
        batch = self.pick(state).select(*KEY, "g", "f", "pos")
        batch = batch.persist(StorageLevel.MEMORY_AND_DISK)
        matched = succeed(batch.drop("f"), self.automaton, self.delta, self.adj).where(~is_literal("node"))
        paid = self.lookup.cost(batch, matched, self.automaton, self.docs)
        done = batch.join(paid, KEY).select(*KEY, F.struct(F.lit(number).alias("round"), F.col("pos").alias("pos"), "g", "f", "n_triples", "requests").alias("now"))
        made = matched.select("run", F.col("node").alias("parent_node"), F.col("q").alias("parent_q"), F.col("nbr").alias("node"), F.col("q2").alias("q"), (F.col("g") + F.col("cost")).alias("g"), F.when(self.kind("dfs"), -F.col("pos")).otherwise(F.col("pos")).alias("turn"), "t_rank", F.col("p").alias("via_label"), F.col("inv").alias("via_inv"), F.col("goal").alias("goal"), "pos")
        route = F.struct(F.when(self.kind("astar"), F.col("g")).otherwise(0.0).alias("a"), "turn", "t_rank", "via_label", "via_inv", "parent_node", "parent_q", "g", "goal", "pos")
        best = made.groupBy(*KEY).agg(F.min(route).alias("r")).select(*KEY, "r.*")
        best = best.join(F.broadcast(self.guide), ["run", "q"], "left")
        best = best.withColumn("new_seq", F.struct(F.lit(number).alias("round"), "turn", "t_rank", F.col("via_label").alias("label"), F.col("via_inv").alias("inv"), "node", "q"))
        old = state.select(*KEY, *[F.col(c).alias(f"o_{c}") for c in state.columns if c not in KEY]).join(done, KEY, "left")
        new = best.select(*KEY, *[F.col(c).alias(f"n_{c}") for c in best.columns if c not in KEY])
        both = old.join(new, KEY, "full_outer")
        fresh, found = F.col("o_seq").isNull(), F.col("n_g").isNotNull()
        better = found & (fresh | (self.kind("astar") & (F.col("n_g") < F.col("o_g"))))
        take = lambda c: F.when(better, F.col(f"n_{c}")).otherwise(F.col(f"o_{c}")).alias(c)
        can_open = F.col("n_h").isNotNull() & ~is_literal("node")
        blind = self.kind("bfs", "dfs")
        at_once = fresh & F.col("n_goal") & blind
        out = both.select(
            *KEY,
            take("g"),
            F.when(better, F.when(self.kind("astar"), F.col("n_g") + F.coalesce("n_h", F.lit(0.0))).otherwise(F.col("n_g"))).otherwise(F.col("o_f")).alias("f"),
            F.when(fresh, F.coalesce("n_h", F.lit(0.0))).otherwise(F.col("o_h")).alias("h"),
            F.coalesce("o_seq", "n_new_seq").alias("seq"),
            take("parent_node"),
            take("parent_q"),
            take("via_label"),
            take("via_inv"),
            F.when(better, can_open).when(F.col("now").isNotNull(), F.lit(False)).otherwise(F.coalesce("o_open", F.lit(False))).alias("open"),
            F.coalesce("o_goal", "n_goal").alias("goal"),
            F.when(at_once, F.lit(number)).otherwise(F.col("o_emit_round")).alias("emit_round"),
            F.when(at_once, F.col("n_pos").cast("double")).otherwise(F.col("o_emit_major")).alias("emit_major"),
            "o_emit_req",
            F.when(F.col("now").isNotNull(), F.concat(F.coalesce("o_expansions", F.array().cast(_STATE.rsplit("expansions ")[1])), F.array("now"))).otherwise(F.coalesce("o_expansions", F.array().cast(_STATE.rsplit("expansions ")[1]))).alias("expansions"),
        )
        kept = keep(out.withColumnRenamed("o_emit_req", "emit_req"))
        batch.unpersist()
        return kept

    def survey(self, state: DataFrame) -> tuple[dict, dict]:
        """Per run: totals; and how many goals wait at which g."""
        waits = F.col("goal") & F.col("emit_round").isNull()
        spent = F.aggregate("expansions", F.struct(F.lit(0).cast("long").alias("t"), F.lit(0).cast("long").alias("r")), lambda a, e: F.struct((a["t"] + e["n_triples"]).alias("t"), (a["r"] + e["requests"]).alias("r")))
        rows = state.groupBy("run", F.when(waits, F.col("g")).alias("w")).agg(
            F.count(F.lit(1)).alias("n"),
            F.sum(F.col("open").cast("int")).alias("open"),
            F.min(F.when(F.col("open"), F.col("f"))).alias("f"),
            F.sum(F.col("emit_round").isNotNull().cast("int")).alias("out"),
            F.sum(spent["t"]).alias("triples"),
            F.sum(spent["r"]).alias("paid"),
            F.sum(F.size("expansions")).alias("requests"),
        )
        total: dict[int, dict] = {}
        waiting: dict[int, dict[float, int]] = {}
        for r in rows.collect():
            t = total.setdefault(r["run"], dict.fromkeys(("n", "open", "out", "triples", "paid", "requests"), 0) | {"f": INF})
            for c in ("n", "open", "out", "triples", "paid", "requests"):
                t[c] += r[c]
            t["f"] = min(t["f"], INF if r["f"] is None else r["f"])
            if r["w"] is not None:
                waiting.setdefault(r["run"], {})[r["w"]] = r["n"]
        return total, waiting

    def release(self, state: DataFrame, number: int) -> DataFrame:
        """Marks waiting goals that nothing open can undercut; what was emitted in this round is credited at its end."""
        early = {i: self.least_f.get(i, INF) for i in range(len(self.specs))}
        bound = _per_run({i: (1e300 if f == INF else f) for i, f in early.items()}, "double")
        strict = F.col("run").isin([i for i, s in enumerate(self.specs) if s.emit_rule == "on_extract"])
        reached = F.when(strict, (F.col("g") < bound) | (F.size("expansions") > 0)).otherwise(F.col("g") <= bound)
        free = F.col("goal") & F.col("emit_round").isNull() & self.kind("astar") & reached
        out = free | F.col("emit_round").isNotNull()
        return state.withColumns({"emit_round": F.when(free, F.lit(number)).otherwise(F.col("emit_round")), "emit_major": F.when(free, F.col("g")).otherwise(F.col("emit_major")), "emit_req": F.when(out, F.coalesce("emit_req", _per_run(self.requests, "long"))).cast("long")})

    def loop(self) -> Iterator[SearchRun]:
        state, number = self.seed(), 0
        while True:
            total, waiting = self.survey(state)
            self.least_f = {i: t["f"] for i, t in total.items()}
            self.requests |= {i: t["requests"] for i, t in total.items()}
            released = self.release(state, number)
            # A node that answers in several states is one answer, and goals may wait for their own lookup: then answers are
            # counted by node, otherwise the totals tell.
            answers = {}
            if self.limits.max_answers is not None and (len(self.automaton.finals) > 1 or any(s.emit_rule == "on_extract" for s in self.specs)):
                answers = {r["run"]: r["n"] for r in released.where("emit_round is not null").groupBy("run").agg(F.count_distinct("node").alias("n")).collect()}
            for i, t in total.items():
                if i not in self.active:
                    continue
                ready = sum(n for g, n in waiting.get(i, {}).items() if g <= t["f"]) if self.specs[i].strategy == "astar" else 0
                out = answers.get(i, t["out"] + ready if not answers else 0)
                self.result.open_peak[i] = max(self.result.open_peak.get(i, 0), t["open"])
                self.result.seen_size[i], self.result.rounds[i] = t["n"], number
                lim = self.limits
                why = (
                    "exhausted" if not t["open"]
                    else "answers" if lim.max_answers is not None and out >= lim.max_answers
                    else "triples" if lim.max_triples is not None and t["triples"] > lim.max_triples
                    else "requests" if lim.max_requests is not None and t["requests"] >= lim.max_requests
                    else "seconds" if lim.max_seconds is not None and time.time() - self.began > lim.max_seconds
                    else ""
                )
                if why:
                    self.result.stopped[i] = why
                    self.active.discard(i)
            self.result.state = released
            yield self.result
            if not self.active:
                break
            number += 1
            after = self.step(released, number)
            drop(state)
            state = after
        self.result.state = keep(self.result.state)
        self.adj.unpersist()
        self.docs.unpersist()


def run_many(graph: TripleGraph, expr: str | PathExpr, start: str, specs: list[Spec], limits: Limits = Limits(), lookup: Lookup | None = None, costs: dict[str, float] | None = None) -> SearchRun:  # noqa: B008
    """All runs to their end."""
    out = None
    for out in _Rounds(graph, expr, start, specs, limits, lookup, costs).loop():
        pass
    return out


def run(graph: TripleGraph, expr: str | PathExpr, start: str, strategy: str = "astar", k: int | None = 1, limits: Limits = Limits(), lookup: Lookup | None = None, costs: dict[str, float] | None = None, **spec) -> SearchRun:  # noqa: B008
    """One run to its end."""
    return run_many(graph, expr, start, [Spec(strategy, k, **spec)], limits, lookup, costs)


def answers_only(n: int) -> Limits:
    """Limits of a search whose contract is its number of answers: nothing else stops it."""
    return Limits(max_answers=n, max_triples=None, max_seconds=None, max_requests=None)


def complete(result: SearchRun) -> SearchRun:
    """The same run; raises where a run stopped before its answers or its graph were at an end."""
    short = {i: why for i, why in result.stopped.items() if why not in ("answers", "exhausted")}
    if short:
        raise RuntimeError(f"search stopped early, by run: {short}")
    return result


def iter_answers(graph: TripleGraph, expr: str | PathExpr, start: str, limits: Limits = Limits(), lookup: Lookup | None = None, **spec) -> Iterator[DataFrame]:  # noqa: B008
    """Answers as they come: after each round the table of those that the round released, in files of its own, which stay when
    the search has gone on."""
    rounds = _Rounds(graph, expr, start, [Spec(**spec)], limits, lookup, None)
    for number, now in enumerate(rounds.loop()):
        yield keep(now.answers().where(F.col("emit_round") == number))


def timed(run: SearchRun, latency: Latency) -> DataFrame:
    """The trace with ``seconds``: the simulated end of each round, whose length is that of its slowest lookup."""
    t = run.trace().withColumn("each", latency.seconds())
    rounds = t.groupBy("run", "round").agg(F.max("each").alias("took"))
    ends = rounds.withColumn("seconds", F.sum("took").over(Window.partitionBy("run").orderBy("round").rowsBetween(Window.unboundedPreceding, 0)))
    return t.drop("each").join(ends.drop("took"), ["run", "round"])


def at_k(specs: list[Spec], ks: list[int | None]) -> list[Spec]:
    return [replace(s, k=k) for s in specs for k in ks]
