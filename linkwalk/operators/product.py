"""Exact evaluation: layers of the product of graph and automaton, grown from the start.

Each round joins the frontier to the automaton's transitions (broadcast: a few dozen rows) and to the adjacency, which is
partitioned by (node, label, direction) once and stays where it is, as does what is seen, by (seed, node, state): a round moves
the frontier to the adjacency and its successors to what is seen, and nothing else. Rounds end in a written table, so a lost
executor costs a re-read. While layers are narrow, several layers go into one job.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark import StorageLevel
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from ..functions.tables import drop, keep
from ..functions.terms import is_literal
from ..plans.automaton import Automaton, Symbol, accepts_empty, compile_path
from ..plans.expr import PathExpr
from ..sources.graph import TripleGraph

#: A layer up to this size counts as narrow; then up to this many layers share a job.
NARROW, STRIDE = 2000, 6
#: From this many triples of one node, label and direction on, they are cut into shards. Seen parts are merged beyond ``PARTS``.
#: A layer of fewer than ``MADE`` rows is dealt out when the next round needs it.
HUB, PARTS, MADE = 1_000_000, 12, 100_000
#: From this many starts on, pairs are grown from the ends where those are fewer.
MANY = 10_000


def keys_of(a: Automaton) -> list[str]:
    """What an edge is looked up by. A transition that reads any label but some can only be looked up by node; where all read one
    label, it tells no edges apart (and as a constant would hide the partitioning from the planner)."""
    return ["node"] if a.labels is None else ["node", "inv"] if len(a.labels) == 1 else ["node", "p", "inv"]


def succeed(front: DataFrame, a: Automaton, delta: DataFrame, adj: DataFrame, small: bool = False) -> DataFrame:
    """Product steps out of ``front``: its columns plus transition and edge columns. Transitions of ``a`` are unfolded first, so
    a node meets only its edges with the label and direction that one of them reads; ``adj`` holds labels of ``a`` alone. A small frontier is sent to the adjacency
    instead of both being shuffled; the caller vouches for its size."""
    wanted = front.join(F.broadcast(delta), "q")
    if a.labels is not None:
        keys = keys_of(a) + ["salt"] * ("salt" in adj.columns)
        wanted = wanted.drop("negated", "excluded").withColumnsRenamed({"label": "p", "t_inv": "inv"})
        wanted = wanted if "p" in keys else wanted.drop("p")
        return (F.broadcast(wanted) if small else wanted).join(adj, keys).drop("salt")
    read = (F.col("t_inv") == F.col("inv")) & F.when(F.col("negated"), ~F.array_contains("excluded", F.col("p"))).otherwise(F.col("label") == F.col("p"))
    keys = ["node", "salt"] if "salt" in adj.columns else ["node"]
    return (F.broadcast(wanted) if small else wanted).join(adj, keys).where(read).drop("salt")


def salted(adj: DataFrame, hubs: DataFrame, shards: int) -> DataFrame:
    """Adjacency with a ``salt``: the rows of each node in ``hubs(node)`` are cut into shards, all others have salt 0. ``hubs``
    is broadcast, so its size is checked: a graph has few nodes of very high degree, and no more than 100,000 are salted."""
    n = hubs.limit(100_001).count()
    if n > 100_000:
        raise ValueError("more than 100,000 hubs: raise the degree from which a node counts as one")
    marked = adj.join(F.broadcast(hubs.select("node").distinct().withColumn("hub", F.lit(True))), "node", "left")
    return marked.withColumn("salt", F.when(F.col("hub"), F.pmod(F.xxhash64("p", "nbr"), F.lit(shards))).otherwise(0).cast("int")).drop("hub")


def spread_out(front: DataFrame, hubs: DataFrame, shards: int) -> DataFrame:
    """A frontier that meets :func:`salted` adjacency: rows at hubs are copied to every shard, all others keep to salt 0."""
    marked = front.join(F.broadcast(hubs.select("node").distinct().withColumn("hub", F.lit(True))), "node", "left")
    return marked.withColumn("salt", F.explode(F.when(F.col("hub"), F.sequence(F.lit(0), F.lit(shards - 1))).otherwise(F.array(F.lit(0))))).drop("hub")


def node_tests(succ: DataFrame, tests: dict[str, DataFrame] | None) -> DataFrame:
    """Keeps steps whose next node passes the transition's test; ``tests`` has a table of nodes for each name."""
    for name, nodes in (tests or {}).items():
        passed = nodes.select(nodes[nodes.columns[0]].alias("nbr")).distinct().withColumn("passed", F.lit(True))
        succ = succ.join(passed, "nbr", "left").where((F.col("test").isNull()) | (F.col("test") != name) | F.col("passed")).drop("passed")
    return succ


@dataclass
class Reached:
    """Product nodes with their least length: ``(seed, node, q, length)``, and the automaton that led there."""

    table: DataFrame
    automaton: Automaton
    layers: int

    def answers(self, dedupe: str = "node", iri_only: bool = False) -> DataFrame:
        """``(seed, node[, q], length)``: reached in a final state. A node under two final states is one answer unless
        ``dedupe`` is ``product_node``."""
        hits = self.table.where(F.col("q").isin(sorted(self.automaton.finals)))
        if iri_only:
            hits = hits.where(~is_literal("node"))
        keys = ["seed", "node"] + (["q"] if dedupe == "product_node" else [])
        return hits.groupBy(*keys).agg(F.min("length").alias("length"))


def explore(graph: TripleGraph, expr: str | PathExpr, seeds: DataFrame, zero_length: str = "always", tests: dict[str, DataFrame] | None = None, most_layers: int = 10_000, hubs: DataFrame | None = None, shards: int = 16, hub: int = HUB) -> Reached:
    """All product nodes reachable from ``seeds(seed)``. ``zero_length="graph_terms"`` leaves out seeds that no triple of the
    graph mentions; otherwise a seed answers a nullable expression even where it does not exist. Nodes with ``hub`` or more edges of one
    label and direction, or those that ``hubs(node)`` names, have their edges cut into ``shards``, so that no task gets all of
    them. More than ``most_layers`` layers raise."""
    spark = seeds.sparkSession
    a = compile_path(expr)
    delta = a.delta(spark)
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    keys = keys_of(a)
    # Successors are made distinct in every round, so repeats of a triple may stay: dropping them would be one more exchange of all.
    adj = graph.repeated_adjacency(a.labels).select("node", "p", "inv", "nbr").repartition(n, *keys).persist(StorageLevel.MEMORY_AND_DISK)
    found = merged = None
    if hubs is None:
        found = keep(adj.groupBy("node", "p", "inv").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= hub).select("node").distinct())
        hubs = None if found.isEmpty() else found
    if hubs is not None:
        plain, adj = adj, salted(adj, hubs, shards).repartition(n, *keys, "salt").persist(StorageLevel.MEMORY_AND_DISK)
        adj.count()
        plain.unpersist()
    first = seeds.where("seed is not null").select(F.col("seed").cast("string").alias("seed")).distinct()
    if zero_length == "graph_terms":
        first = first.join(graph.adjacency().select(F.col("node").alias("seed")).distinct(), "seed", "left_semi")
    layer = keep(first.select("seed", F.col("seed").alias("node"), F.lit(0).alias("q"), F.lit(0).alias("length")))
    parts, depth, size, narrow = [layer], 0, layer.count(), 0
    product = ["seed", "node", "q"]

    def settled(df: DataFrame) -> DataFrame:
        """A part of what is seen, dealt out by its key and held; how it is dealt out is known to the planner once it is made."""
        out = df.select(*product).repartition(n, *product).persist(StorageLevel.MEMORY_AND_DISK)
        if size >= MADE:
            out.count()
        return out

    seen = [settled(layer)]
    while size:
        if depth >= most_layers:
            raise RuntimeError(f"walks go on after {most_layers} layers")
        # Only after several narrow layers in a row is the graph taken for thin; elsewhere inner layers without an
        # anti-join would repeat what is seen.
        narrow = narrow + 1 if size <= NARROW else 0
        stride = STRIDE if narrow > 6 else 1
        step, steps = layer, []
        for k in range(1, stride + 1):
            small = size <= NARROW and k == 1
            front = step.select("seed", "node", "q")
            succ = node_tests(succeed(front if hubs is None else spread_out(front, hubs, shards), a, delta, adj, small), tests)
            step = succ.select("seed", F.col("nbr").alias("node"), F.col("q2").alias("q")).distinct().withColumn("length", F.lit(depth + k))
            steps.append(step)
        every = steps[0]
        for x in steps[1:]:
            every = every.unionByName(x)
        if stride > 1:
            every = every.groupBy("seed", "node", "q").agg(F.min("length").alias("length"))
        for x in seen:
            every = every.join(x, product, "left_anti")
        depth += stride
        # Nodes of the inner layers were expanded in this very job; only the last layer is open.
        last = Observation()
        fresh = keep(every.observe(last, F.count(F.when(F.col("length") == depth, 1)).alias("n")))
        parts.append(fresh)
        layer, size = fresh.where(F.col("length") == depth), last.get["n"]
        if not size:
            break
        seen.append(settled(fresh))
        if len(seen) > PARTS:
            whole = seen[0]
            for x in seen[1:]:
                whole = whole.unionByName(x)
            older, merged = merged, keep(whole)
            for x in seen:
                x.unpersist()
            drop(older)
            seen = [settled(merged)]
    for x in [adj, *seen]:
        x.unpersist()
    # Layers make up the result; what only the rounds read goes.
    for x in (found, merged):
        drop(x)
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return Reached(out, a, depth)


def _one(spark: SparkSession, start: str) -> DataFrame:
    return spark.createDataFrame([(start,)], "seed string")


def reach(graph: TripleGraph, expr: str | PathExpr, start: str, **options) -> DataFrame:
    """``(node, length)``: nodes that a matching walk from ``start`` leads to, with the least length."""
    iri = options.pop("iri_only", False)
    return explore(graph, expr, _one(graph.spark, start), **options).answers(iri_only=iri).select("node", "length")


def reach_from(graph: TripleGraph, expr: str | PathExpr, starts: DataFrame, col: str, **options) -> DataFrame:
    """``starts`` joined to what each value of ``col`` reaches: its columns plus ``node`` and ``length``."""
    if not options and starts.select(col).distinct().limit(MANY).count() == MANY:
        ends = ends_of(graph, compile_path(expr))
        if ends.count() < starts.select(col).distinct().count():
            return from_ends(graph, expr, starts, col, ends)
        drop(ends)
    found = explore(graph, expr, starts.select(F.col(col).alias("seed")), **options).answers()
    return starts.join(found.withColumnRenamed("seed", col), col)


def _edges(graph: TripleGraph, symbol: Symbol) -> DataFrame:
    """``(here, there)`` of all steps that a symbol reads, repeats included."""
    t = graph.select_labels(None if symbol.label is None else [symbol.label], repeats=True)
    if symbol.label is None and symbol.excluded:
        t = t.where(~F.col("p").isin(sorted(symbol.excluded)))
    here, there = ("o", "s") if symbol.inv else ("s", "o")
    return t.select(F.col(here).alias("here"), F.col(there).alias("there"))


def ends_of(graph: TripleGraph, a: Automaton) -> DataFrame:
    """``(node, q, chunk, bits)``: the nodes that a last step may lead to, each with a bit of its own within its chunk of 64."""
    last = sorted({(s, t) for _, s, t in a.edges if t in a.finals}, key=str)
    nodes = None
    for s in dict.fromkeys(s for s, _ in last):
        more = _edges(graph, s).select(F.col("there").alias("node"))
        nodes = more if nodes is None else nodes.unionByName(more)
    if nodes is None:
        nodes = graph.spark.createDataFrame([], "node string")
    # Written before it is read: the numbers are given once.
    return keep(nodes.distinct().withColumn("id", F.monotonically_increasing_id()).select("node", F.shiftright("id", 6).alias("chunk"), F.expr("shiftleft(1L, cast(id & 63 as int))").alias("bits")))


def from_ends(graph: TripleGraph, expr: str | PathExpr, starts: DataFrame, col: str, ends: DataFrame) -> DataFrame:
    """:func:`reach_from` for very many starts and fewer ends. Walks are grown backwards from all ends at once: a row
    ``(node, q, chunk, bits)`` stands for the up to 64 ends that ``node`` leads to, so a layer has a row for each node and not for
    each pair. A step reads the tables of its labels anew and holds no adjacency; repeats of a triple set the same bits."""
    a = compile_path(expr)
    product = ["node", "q", "chunk"]
    loops = _has_cycle(a)
    layer = keep(ends.withColumn("q", F.explode(F.array(*[F.lit(q) for q in sorted(a.finals)]))).select(*product, "bits"))
    seen, parts, states, depth = (layer if loops else None), [], set(a.finals), 0
    while states:
        depth += 1
        steps = [(q, s, t) for q, s, t in a.edges if t in states]
        step = None
        for s in dict.fromkeys(s for _, s, _ in steps):
            moves = F.array(*[F.struct(F.lit(t).alias("q"), F.lit(q).alias("q1")) for q, x, t in steps if x == s])
            back = layer.join(F.broadcast(graph.spark.range(1).select(F.inline(moves))), "q").withColumnRenamed("node", "there")
            more = back.join(_edges(graph, s), "there").select(F.col("here").alias("node"), F.col("q1").alias("q"), "chunk", "bits")
            step = more if step is None else step.unionByName(more)
        states = {q for q, _, _ in steps}
        if step is None:
            break
        step = step.groupBy(*product).agg(F.bit_or("bits").alias("bits"))
        if loops:
            step = step.join(seen.withColumnRenamed("bits", "old"), product, "left").withColumn("bits", F.expr("bits & ~coalesce(old, 0L)")).where("bits <> 0").drop("old")
        older, layer = layer, keep(step)
        if 0 in states:
            parts.append(keep(layer.where("q = 0").select(F.col("node").alias(col), "chunk", "bits").join(starts.select(col).distinct(), col, "left_semi").withColumn("length", F.lit(depth))))
        if loops:
            whole = keep(seen.unionByName(layer).groupBy(*product).agg(F.bit_or("bits").alias("bits")))
            if seen is not older:
                drop(seen)
            seen = whole
            if layer.isEmpty():
                states = set()
        drop(older)
    for x in (layer, seen):
        drop(x)
    name = ends.select("chunk", F.col("bits").alias("bit"), "node")
    found = None
    for x in parts:
        met = x.withColumn("bit", F.explode(F.expr("transform(filter(sequence(0, 63), i -> getbit(bits, i) = 1), i -> shiftleft(1L, i))")))
        met = met.join(name, ["chunk", "bit"]).select(col, "node", "length")
        found = met if found is None else found.unionByName(met)
    if accepts_empty(a):
        itself = starts.where(F.col(col).isNotNull()).select(col).distinct().select(col, F.col(col).alias("node"), F.lit(0).alias("length"))
        found = itself if found is None else found.unionByName(itself)
    if found is None:
        found = starts.select(col).limit(0).select(col, F.col(col).alias("node"), F.lit(0).alias("length"))
    # A pair met in one layer only has one row: bits are merged by node there.
    if len(parts) + accepts_empty(a) > 1:
        found = found.groupBy(col, "node").agg(F.min("length").alias("length"))
    return starts.join(found, col)


def _has_cycle(a: Automaton) -> bool:
    left = {(q, t) for q, _, t in a.edges}
    while left:
        ahead = {q for q, _ in left}
        more = {(q, t) for q, t in left if t in ahead}
        if more == left:
            return True
        left = more
    return False


def all_pairs(graph: TripleGraph, expr: str | PathExpr, seeds: DataFrame | None = None, allow_full: bool = False) -> DataFrame:
    """``(s, o)`` for many starts at once. Without ``seeds`` every node is a start, which must be asked for."""
    if seeds is None:
        if not allow_full:
            raise ValueError("evaluation from every node grows with the square of the graph; pass seeds or allow_full=True")
        seeds = graph.adjacency().select(F.col("node").alias("seed")).distinct()
    return explore(graph, expr, seeds).answers().select(F.col("seed").alias("s"), F.col("node").alias("o"))


def materialize(graph: TripleGraph, automaton: Automaton) -> DataFrame:
    """The whole labelled product graph: ``(node, q, label, inv, node2, q2)``."""
    delta = automaton.delta(graph.spark)
    adj = graph.adjacency(automaton.labels)
    read = (F.col("t_inv") == F.col("inv")) & F.when(F.col("negated"), ~F.array_contains("excluded", F.col("p"))).otherwise(F.col("label") == F.col("p"))
    return adj.join(F.broadcast(delta), read).select("node", "q", F.col("p").alias("label"), "inv", F.col("nbr").alias("node2"), "q2")


def connected(graph: TripleGraph, expr: str | PathExpr, start: str, end: str, two_sided: bool = True) -> bool:
    """Whether (start, end) is an answer. Two-sided search grows layers from both ends, the smaller first, until they meet."""
    spark = graph.spark
    a = compile_path(expr)
    if start == end and accepts_empty(a):
        return True
    if not a.finals:
        return False
    if not two_sided:
        return not explore(graph, expr, _one(spark, start)).answers().where(F.col("node") == end).isEmpty()
    adj = graph.adjacency(a.labels).select("node", "p", "inv", "nbr").repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), *keys_of(a)).persist(StorageLevel.MEMORY_AND_DISK)
    ahead = a.delta(spark)
    back = ahead.select(F.col("q2").alias("q"), "label", (~F.col("t_inv")).alias("t_inv"), "negated", "excluded", F.col("q").alias("q2"))
    fronts = [keep(spark.createDataFrame([(start, 0)], "node string, q int")), keep(spark.createDataFrame([(end, q) for q in a.finals], "node string, q int"))]
    seen = list(fronts)
    sizes = [1, len(a.finals)]
    met = False
    while all(sizes) and not met:
        k = 0 if sizes[0] <= sizes[1] else 1
        succ = succeed(fronts[k], a, (ahead, back)[k], adj).select(F.col("nbr").alias("node"), F.col("q2").alias("q")).distinct()
        old = (fronts[k], seen[k])
        fronts[k] = keep(succ.join(seen[k], ["node", "q"], "left_anti"))
        seen[k] = keep(seen[k].unionByName(fronts[k]))
        for x in old:
            drop(x)
        sizes[k] = fronts[k].count()
        met = not fronts[k].join(seen[1 - k], ["node", "q"], "left_semi").isEmpty()
    adj.unpersist()
    for x in (*fronts, *seen):
        drop(x)
    return met


def closure(edges: DataFrame, rounds: int = 40) -> DataFrame:
    """Transitive closure ``(s, o, length)`` of ``edges(s, o)`` by squaring: rounds grow with the logarithm of the depth. For
    long, thin relations such as chains; the result has a row for each connected pair. Raises where ``rounds`` do not do."""
    now = keep(edges.select("s", "o").distinct().withColumn("length", F.lit(1)))
    size = now.count()
    for _ in range(rounds):
        left = now.select("s", F.col("o").alias("m"), F.col("length").alias("a"))
        right = now.select(F.col("s").alias("m"), "o", F.col("length").alias("b"))
        longer = left.join(right, "m").select("s", "o", (F.col("a") + F.col("b")).alias("length"))
        grown = keep(now.unionByName(longer).groupBy("s", "o").agg(F.min("length").alias("length")))
        drop(now)
        now, after = grown, grown.count()
        if after == size:
            return now
        size = after
    raise RuntimeError(f"no closure after {rounds} rounds")
