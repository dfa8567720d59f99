import random

import pytest
from pyspark.sql import functions as F
from simulate import G1, G2, G3, exact, simulate

from linkwalk.operators import algebra, client, measures, paths, product
from linkwalk.operators.deref import Combined, Endpoint, FullDocs, Latency, MultiSource, PartialDocs, PatternPages
from linkwalk.operators.search import Limits, Spec, answers_only, complete, iter_answers, run, run_many, timed
from linkwalk.plans.automaton import compile_path
from linkwalk.sources.graph import TripleGraph, from_triples


def graph(spark, triples):
    return from_triples(spark.createDataFrame(triples, "s string, p string, o string").coalesce(1))


def lists(result, i=0):
    trace = [r["node"] for r in result.trace().where(F.col("run") == i).orderBy("req").collect()]
    answers = [(r["node"], int(r["length"]), r["req_at_emit"]) for r in result.answers().where(F.col("run") == i).orderBy("rank").collect()]
    return trace, answers


COAUTHORS, NAMES = "(^c/c)*", "(^c/c)*/name"
GOLDEN = {
    (COAUTHORS, "bfs", "pathmax"): ("A P1 P2 B C P3 D P4 E", "A@0 B@2 C@3 D@6 E@8"),
    (COAUTHORS, "dfs", "pathmax"): ("A P2 C P1 B P3 D P4 E", "A@0 C@2 B@4 D@6 E@8"),
    (COAUTHORS, "astar", "pathmax"): ("A P1 P2 B P3 C D P4 E", "A@0 B@2 C@3 D@5 E@8"),
    (COAUTHORS, "astar", "state"): ("A P1 B P2 C P3 D P4 E", "A@0 B@2 C@4 D@6 E@8"),
    (NAMES, "bfs", "pathmax"): ("A P1 P2 B C P3 D P4 E", '"nA@1 "nB@4 "nC@5 "nD@7 "nE@9'),
    (NAMES, "dfs", "pathmax"): ("A P2 C P1 B P3 D P4 E", '"nA@1 "nC@3 "nB@5 "nD@7 "nE@9'),
    (NAMES, "astar", "pathmax"): ("A P1 B P2 C P3 D P4 E", '"nA@1 "nB@3 "nC@5 "nD@7 "nE@9'),
}


def test_simulator_gives_the_known_orders():
    for (expr, strategy, guide), (trace, answers) in GOLDEN.items():
        t, a = simulate(G1, expr, "A", strategy, guide=guide)
        assert " ".join(t) == trace and " ".join(f"{n}@{r}" for n, _, r in a) == answers


@pytest.mark.parametrize("expr", [COAUTHORS, NAMES])
def test_known_orders(spark, expr):
    wanted = {k[1:]: v for k, v in GOLDEN.items() if k[0] == expr}
    specs = [Spec(s, 1, heuristic=h) for s, h in wanted]
    result = run_many(graph(spark, G1), expr, "A", specs)
    for i, (trace, answers) in enumerate(wanted.values()):
        t, a = lists(result, i)
        assert " ".join(t) == trace and " ".join(f"{n}@{r}" for n, _, r in a) == answers
    assert set(result.stopped.values()) == {"exhausted"}
    walks = paths.witness(result)
    assert paths.invalid_hops(graph(spark, G1), walks).count() == 0
    assert walks.join(result.answers(), ["run", "rank", "node"]).where(F.size("steps") - 1 != F.col("length")).count() == 0


def test_batches_against_the_simulator(spark):
    specs = [Spec(s, k) for s in ("bfs", "dfs", "astar") for k in (2, 3, None)]
    result = run_many(graph(spark, G1), COAUTHORS, "A", specs)
    for i, s in enumerate(specs):
        assert lists(result, i) == simulate(G1, COAUTHORS, "A", s.strategy, s.k)
    assert [x for x in result.rounds.values()][:1] == [7]
    whole = [i for i, s in enumerate(specs) if s.k is None]
    assert len({result.rounds[i] for i in whole}) == 1 and len({frozenset(n for n, _, _ in lists(result, i)[1]) for i in whole}) == 1


def test_stack_search_takes_longer_walks(spark):
    result = run_many(graph(spark, G2), COAUTHORS, "A", [Spec("dfs"), Spec("bfs"), Spec("astar")])
    assert dict(x[:2] for x in lists(result, 0)[1]) == {"A": 0, "C": 2, "B": 4}
    assert all(dict(x[:2] for x in lists(result, i)[1]) == {"A": 0, "B": 2, "C": 2} for i in (1, 2))


def test_semantics(spark):
    g = graph(spark, G3)
    nodes = lambda e, s, **o: {r["node"] for r in product.reach(g, e, s, **o).collect()}
    assert nodes("a*", "x") == {"x", "y"}
    assert nodes("n/^n", "x") == {"x", "z"} and lists(run(g, "n/^n", "x"))[1] == []
    assert nodes("!(a)", "x") == {"y", '"t'} and nodes("!(^a)", "y") == {"x"}
    assert nodes("a?", "u") == {"u"} and nodes("a?", "u", zero_length="graph_terms") == set()
    assert nodes("n", "x", iri_only=True) == set()
    assert g.triples.count() == 5
    tests = {"t": spark.createDataFrame([("y",)], "node string")}
    assert {r["node"] for r in product.reach(g, "(a|b)[t]", "x", tests=tests).collect()} == {"y"}
    both = graph(spark, [("s", "a", "m"), ("m", "b", "m")])
    reached = product.explore(both, "a|a/b?", both.spark.createDataFrame([("s",)], "seed string"))
    assert reached.answers().count() == 1


def test_salted_hubs_change_nothing(spark):
    star = [("hub", "a", f"x{i}") for i in range(200)] + [("x5", "b", "end")]
    g = graph(spark, star)
    hubs = g.hubs(100)
    assert [r["node"] for r in hubs.collect()] == ["hub"]
    adj = product.salted(g.adjacency(), hubs, 8)
    assert adj.where("node = 'hub'").select("salt").distinct().count() == 8 and adj.where("node <> 'hub' and salt <> 0").count() == 0
    plain = {tuple(r) for r in product.reach(g, "a/b?", "hub").collect()}
    assert {tuple(r) for r in product.reach(g, "a/b?", "hub", hubs=hubs, shards=8).collect()} == plain and len(plain) == 201


def random_graph(r):
    nodes = [f"n{i}" for i in range(r.randint(4, 14))]
    return [(r.choice(nodes), r.choice("abc"), r.choice(nodes)) for _ in range(r.randint(4, 30))]


EXPRESSIONS = ["(a|^b)*", "a/b*/^c?", "(a/(b|^c))+", "!(a|^b)*", "^(a/b)|c+", "(a*/b)*"]


def test_random_graphs(spark):
    r = random.Random(7)
    for expr in EXPRESSIONS:
        triples = random_graph(r)
        g = graph(spark, triples)
        want = exact(triples, expr, "n0")
        got = {x["node"]: x["length"] for x in product.reach(g, expr, "n0").collect()}
        assert got == want
        known = {n for t in triples for n in (t[0], t[2])}
        pairs = {x["o"] for x in algebra.eval_pairs(g, expr).where("s = 'n0'").collect()}
        assert pairs == (set(want) if "n0" in known else set())
        specs = [Spec("bfs", 3), Spec("dfs", 2), Spec("astar", 1), Spec("astar", 7), Spec("astar", None, batch="bucket"), Spec("astar", 2, heuristic="zero"), Spec("astar", 3, heuristic="state")]
        result = run_many(g, expr, "n0", specs, Limits(max_answers=None))
        by_client = client.search(g, expr, "n0", specs, Limits(max_answers=None, max_triples=10**9, max_seconds=None))
        for i, s in enumerate(specs):
            trace, answers = lists(result, i)
            assert {n for n, _, _ in answers} == set(want)
            if s.strategy != "dfs":
                assert [n for _, n, _ in answers] == sorted(want.values())
            assert lists(by_client, i) == (trace, answers)
            if s.batch == "top":
                assert (trace, answers) == simulate(triples, expr, "n0", s.strategy, s.k, s.heuristic)
        gap = measures.optimality_gap(result, measures.discovered_lengths(result, product.materialize(g, result.automaton)))
        assert gap.where(F.col("run").isin([0, 2, 3, 4, 5, 6]) & (F.col("gap") != 0)).count() == 0
        assert measures.expansion_containment(result, 2, 0).count() == 0
        if want:
            end = max(want)
            assert product.connected(g, expr, "n0", end) and product.connected(g, expr, "n0", end, two_sided=False)
        assert not product.connected(g, expr, "n0", "nowhere")


def test_limits_and_increments(spark):
    g = graph(spark, G1)
    result = run(g, COAUTHORS, "A", "astar", 1, Limits(max_requests=3))
    assert result.stopped == {0: "requests"} and len(lists(result)[0]) == 3
    assert run(g, COAUTHORS, "A", "bfs", 1, Limits(max_answers=2)).answers().count() == 2
    assert run(g, COAUTHORS, "A", "bfs", 2, Limits(max_triples=4)).stopped == {0: "triples"}
    assert [r["node"] for t in iter_answers(g, COAUTHORS, "A", k=2) for r in t.orderBy("rank").collect()] == ["A", "B", "C", "D", "E"]
    assert lists(run(g, COAUTHORS, "nobody"))[1] == [("nobody", 0, 0)]
    late = lists(run(g, COAUTHORS, "A", emit_rule="on_extract"))[1]
    assert [x[0] for x in late] == list("ABCDE") and all(a[2] >= b[2] for a, b in zip(late, lists(run(g, COAUTHORS, "A"))[1], strict=True))


def test_clients_and_tables_agree(spark):
    """Both engines, over every lookup: the same lookups in the same order, answers, triples, requests and ends."""
    from linkwalk.operators.client import Job, search_all

    r = random.Random(3)
    triples = [(f"n{r.randint(0, 25)}", r.choice("abc"), f"n{r.randint(0, 25)}") for _ in range(90)]
    g = graph(spark, triples)
    expr, limits = "(a|^b)*/c?", Limits(max_answers=8, max_triples=40, max_seconds=None)
    specs = [Spec("bfs", 2), Spec("dfs", 2), Spec("astar", 3), Spec("astar", 2, emit_rule="on_extract"), Spec("astar", 2, tie="lifo")]
    for lookup in (FullDocs(g), Combined(PartialDocs(g, 0.5), Endpoint(g), "each")):
        tables = run_many(g, expr, "n0", specs, limits, lookup)
        mine = client.search(g, expr, "n0", specs, limits, lookup)
        of = lambda x, *c: [tuple(y) for y in x.select("run", *c).orderBy("run", c[0]).collect()]
        columns = ("req", "round", "node", "q", "g", "f", "n_triples", "requests")
        assert of(mine.trace(), *columns) == of(tables.trace(), *columns)
        assert of(mine.answers(), "rank", "node", "q", "length", "req_at_emit") == of(tables.answers(), "rank", "node", "q", "length", "req_at_emit")
        assert mine.stopped == tables.stopped and mine.rounds == tables.rounds
        walks = paths.witness(mine)
        assert paths.invalid_hops(g, walks).count() == 0
    # Fetching by rounds instead of whole, and a document too large to bring.
    for local, ahead in ((0, 1), (0, 40)):
        old = client.LOCAL, client.AHEAD
        client.LOCAL, client.AHEAD = local, ahead
        try:
            again = client.search(g, expr, "n0", specs, limits)
        finally:
            client.LOCAL, client.AHEAD = old
        assert [lists(again, i) for i in range(5)] == [lists(client.search(g, expr, "n0", specs, limits), i) for i in range(5)]
    with pytest.raises(ValueError, match="limits"):
        client.search(g, expr, "n0", specs, Limits(None, None, None, None))
    # The same node in two states: with a cache it is paid once.
    plain, cached = (search_all([Job(FullDocs(g), "(a|^b)*/c/(a|b)*", "n0", Spec("bfs", None), cache=c)], Limits(max_answers=None)) for c in (False, True))
    total = lambda x: x.trace().agg(F.sum("requests")).first()[0]
    assert total(cached) == cached.trace().select("node").distinct().count() < total(plain)
    assert lists(plain) == lists(cached)


def test_large_documents_end_a_run(spark, monkeypatch):
    hub = spark.range(500).selectExpr("'A' AS s", "'c' AS p", "'x' || id AS o")
    g = from_triples(hub.unionByName(spark.createDataFrame([("S", "c", "A"), ("S", "c", "B")], "s string, p string, o string")))
    monkeypatch.setattr(client, "LOCAL", 0)
    monkeypatch.setattr(client, "ROUND", 100)
    got = client.search(g, "c*", "S", [Spec("bfs", 1)], Limits(max_triples=50))
    assert got.stopped == {0: "triples"} and [r["node"] for r in got.trace().orderBy("req").collect()] == ["S", "A"]


def test_costs(spark):
    g = graph(spark, [("s", "a", "m"), ("m", "a", "t"), ("s", "b", "t")])
    got = lists(run(g, "a/a|b", "s", costs={"b": 5.0}))[1]
    assert got == [("t", 2, 2)]


def test_lookups(spark):
    g = graph(spark, G1)
    every = {n for n in "ABCDE"}
    part = PartialDocs(g, 0.5)
    alone = {r["node"] for r in run(g, COAUTHORS, "A", "bfs", None, lookup=part).answers().collect()}
    helped = run(g, COAUTHORS, "A", "bfs", None, lookup=Combined(part, Endpoint(g), "each"))
    assert alone <= every == {r["node"] for r in helped.answers().collect()}
    assert helped.trace().where("node = 'A'").first()["requests"] == 2
    end = run(g, NAMES, "A", "bfs", None, lookup=Endpoint(g))
    assert end.trace().where("node = 'A'").first()["requests"] == 2
    assert run(g, COAUTHORS, "A", "bfs", None).trace().where("node = 'A'").first()["n_triples"] == 3
    pages = run(g, COAUTHORS, "A", "bfs", None, lookup=PatternPages(g, 1))
    assert pages.trace().where("node = 'A'").first()["requests"] == 2
    assert [r["nbr"] for r in PatternPages(g, 1).pages("A", "c", True).orderBy("page").collect()] == ["P1", "P2"]
    assert run(g, COAUTHORS, "A", "bfs", None, lookup=MultiSource(g)).trace().first()["requests"] == 1
    assert FullDocs(g).edges({"c"}).count() == 16
    recalled = measures.recall(part.edges(None).select("node").distinct(), g.adjacency().select("node").distinct()).first()
    assert 0 < recalled["recall"] <= 1


def test_measures(spark):
    result = run_many(graph(spark, G1), COAUTHORS, "A", [Spec("astar"), Spec("bfs"), Spec("dfs"), Spec("bfs", None)])
    c = measures.curve(result)
    rows = {(r["run"], r["x"]): r["answers"] for r in c.collect()}
    assert rows[0, 0.0] == 1 and rows[0, 2.0] == 2 and rows[0, 8.0] == 5
    d = {r["run"]: r["dominates"] for r in measures.dominance(c, measures.finished(result)).collect()}
    assert d[0]
    assert {r["run"]: r["requests"] for r in measures.first_answer(result, skip_start=True).collect()}[0] == 2
    assert {(r["run"], r["rank"]): r["length"] for r in measures.lengths_at(result, [5]).collect()}[0, 5] == 6
    s = {r["run"]: r["speed_up"] for r in measures.speed_up(result, 1, Latency(spread=0.0)).collect()}
    assert s[1] == 1.0 and s[3] > 1
    assert timed(result, Latency(spread=0.0)).where("run = 0").agg(F.max("seconds")).first()[0] == 9.0
    assert measures.requests(result, "distinct_doc").where("run = 0").agg(F.max("total")).first()[0] == 9
    m = {r["run"]: r for r in measures.memory(result).collect()}
    assert m[0]["answers"] == 5 and m[0]["seen"] == 9 and m[0]["open_peak"] >= 2
    assert measures.same_lengths(result, 0, 1).count() == 0
    t = spark.createDataFrame([("requests", 1, s, True) for s in ("astar", "bfs")] + [("requests", 1, "dfs", False)], "axis string, k int, strategy string, dominates boolean")
    assert tuple(measures.tally(t).first()) == ("requests", 1, 1, 1, 0)
    assert measures.tally_cube(t).where("level = 7").first()["times"] == 2 and measures.tally_rollup(t).count() == 6
    reached = product.explore(graph(spark, G1), COAUTHORS, spark.createDataFrame([("A",)], "seed string"))
    assert sum(r["expansions"] for r in measures.layer_requests(reached).collect()) == 9


def test_walks(spark):
    g = graph(spark, G1)
    reached = product.explore(g, NAMES, spark.createDataFrame([("A",)], "seed string"))
    walks = paths.shortest_walks(g, NAMES, reached)
    text = {r["node"]: r["t"] for r in walks.select("node", paths.render("steps").alias("t")).collect()}
    assert text['"nB'] == 'A <-c- P1 -c-> B -name-> "nB'
    assert walks.where(paths.visits(F.col("steps"), "P3")).count() == 2 and walks.where(paths.uses(F.col("steps"), "c")).count() == 4
    assert paths.path_steps(walks).count() == 2 + 4 + 4 + 6 + 8


def test_path_query_gives_all_nearest_past_the_triple_limit(spark):
    # One hub holds more triples than the experiments' limit.
    from linkwalk.plans.pathsql import path_query

    hub = spark.range(100_500).selectExpr("'A' AS s", "'c' AS p", "'x' || id AS o")
    more = spark.createDataFrame([("x7", "d", "B"), ("B", "d", "C")], "s string, p string, o string")
    got = path_query(from_triples(hub.unionByName(more)), "A c/d/d? ?x limit 2").collect()
    assert [(r["x"], int(r["length"])) for r in got] == [("B", 2), ("C", 3)]


def test_stopped_searches_are_told(spark):
    g = graph(spark, [("A", "c", "B"), ("B", "c", "C"), ("C", "c", "D")])
    with pytest.raises(RuntimeError, match="requests"):
        complete(run(g, "c*", "A", limits=Limits(max_requests=1)))
    assert complete(run(g, "c*", "A", limits=answers_only(9))).answers().count() == 4


def test_documents_are_laid_out_and_read_by_name(spark, monkeypatch):
    """A lookup reads the files around its node and starts no job; views of one lookup share what is stored."""
    from linkwalk.operators import store
    from linkwalk.operators.deref import Latency

    monkeypatch.setattr(store, "GROUP", 2000)
    monkeypatch.setattr(client, "LOCAL", 0)
    rows = spark.range(4000).selectExpr("'n' || id % 500 AS s", "'a' AS p", "'n' || (id * 7 + 1) % 501 AS o", "IF(id % 3 = 0, 'x', 'y') AS src")
    g = from_triples(rows.unionByName(rows.where("src = 'x'").withColumn("src", F.lit("y"))))
    lookup = Combined(PartialDocs(g, 0.5), Endpoint(g))
    held = store.Store(lookup, Latency())
    try:
        names = {"n0", "n7", "n500", "nobody"}
        before = spark.sparkContext._jsc.sc().dagScheduler().nextJobId()
        book = client._Book(lookup, held, 1000)
        for table in held.read(names, 1000, book.large):
            book.take(table)
        assert spark.sparkContext._jsc.sc().dagScheduler().nextJobId() == before
        want = lookup.rows().where(F.col("node").isin(sorted(names))).collect()
        assert {(n, p, inv, o) for n in names & set(book.docs) for (p, inv), found in book.docs[n].items() for o in found} == {(r["node"], r["p"], r["inv"], r["nbr"]) for r in want}
        assert all(book.shown[n] == sum(r["shown"] for r in want if r["node"] == n) for n in names - {"nobody"})
        over: set = set()
        assert not list(held.read({"n7"}, 3, over)) or over == {"n7"}
    finally:
        held.close()


def test_streams_of_other_stores(spark, tmp_path):
    """Where the shared folder is not mounted, Hadoop's streams bring the same rows."""
    import pyarrow.parquet as pq
    from linkwalk.operators.store import _File, _Stream

    spark.range(5000).selectExpr("printf('n%05d', id) AS node", "id AS v").coalesce(1).write.option("parquet.block.size", "4000").parquet(str(tmp_path / "t"))
    f = next((tmp_path / "t").glob("*.parquet"))
    path = spark._jvm.org.apache.hadoop.fs.Path(str(f))
    far, near = _File(_Stream(path.getFileSystem(spark._jsc.hadoopConfiguration()), path)), _File(str(f))
    assert far.first == near.first and len(near.first) > 1
    assert far.file.read_row_groups(list(far.groups("n03000"))).equals(near.file.read_row_groups(list(near.groups("n03000"))))
    assert far.file.read().equals(pq.read_table(f))


@pytest.mark.parametrize("expr", ["a*/b?", "a|a/b"])
def test_pairs_from_the_ends(spark, monkeypatch, expr):
    """Very many starts: walks grown backwards from the ends give the pairs and lengths of layers grown from the starts."""
    rng = random.Random(expr)
    rows = [(f"n{rng.randrange(90)}", rng.choice("abc"), f"n{rng.randrange(90)}") for _ in range(150)]
    g = from_triples(spark.createDataFrame(rows + rows[:20], "s string, p string, o string"))
    starts = spark.createDataFrame([(f"n{i}", i) for i in range(95)] + [("n1", -1), (None, 0)], "at string, i int")
    want = sorted(map(tuple, product.explore(g, expr, starts.select(F.col("at").alias("seed"))).answers().collect()))
    a = compile_path(expr)
    got = product.from_ends(g, expr, starts.where("i >= 0"), "at", product.ends_of(g, a))
    assert sorted((r["at"], r["node"], r["length"]) for r in got.collect()) == want
    grown = []
    monkeypatch.setattr(product, "MANY", 5)
    monkeypatch.setattr(product, "ends_of", lambda *x: spark.createDataFrame([("n0", 0, 1)], "node string, chunk long, bits long"))
    monkeypatch.setattr(product, "from_ends", lambda *x: grown.append(x))
    product.reach_from(g, expr, starts, "at")
    assert grown


def test_layouts_hold_what_is_read(spark, monkeypatch):
    """Where no size of a document counts, only rows that a transition reads are laid out; the order and the answers stay."""
    rows = [("A", "c", "B"), ("B", "d", "A"), ("C", "c", "B"), ("C", "e", "A"), ("C", "name", '"C'), ("A", "name", '"A'), ("A", "f", "C")]
    g, sizes, old = graph(spark, rows), [], client.Store.__init__
    monkeypatch.setattr(client.Store, "__init__", lambda self, *x: (old(self, *x), sizes.append(self.size))[0])
    runs = [client.search(g, "(c/^c)*/name", "A", [Spec("dfs"), Spec("astar")], Limits(None, None, None, 9), **how) for how in ({}, {"sizes": False}, {"lookup": Endpoint(g)})]
    # Of each triple both ends; of those read, c from both ends and name from one.
    assert sizes == [14, 6, 6]
    looked = [[(r["run"], r["req"], r["node"], r["q"]) for r in x.trace().orderBy("run", "req").collect()] for x in runs]
    assert looked[0] == looked[1] == looked[2] and [lists(x, 1)[1] for x in runs[1:]] == [lists(runs[0], 1)[1]] * 2
    assert {r["n_triples"] for r in runs[1].trace().collect()} == {None}
    with pytest.raises(ValueError, match="sizes"):
        client.search(g, "c", "A", [Spec("dfs")], Limits(), sizes=False)


def test_seconds_without_spark(spark):
    """A client knows what a lookup takes, also of a node that no row mentions, without a job."""
    names = ["", "part:0", "é" * 3, *("x" * i for i in range(1, 70))]
    for latency in (Latency(), Latency(2.0, 0.3, -7), Latency(seed=1 << 40)):
        got = spark.createDataFrame([(n,) for n in names], "node string").select("node", latency.seconds().alias("t")).collect()
        assert all(r["t"] == latency.of(r["node"]) for r in got)


def test_links_are_made_when_asked_for(spark, monkeypatch):
    """Curves, traces and memory read no table of how nodes were met; walks do, and get it."""
    made, old = [], client._links
    monkeypatch.setattr(client, "_links", lambda *x: (made.append(1), old(*x))[1])
    got = client.search(graph(spark, G1), COAUTHORS, "A", [Spec("dfs"), Spec("astar")], Limits(9, None, None, 9))
    assert measures.curve(got).count() and measures.memory(got).count() == 2 and not made
    assert lists(got, 0) == simulate(G1, COAUTHORS, "A", "dfs") and lists(got, 1) == simulate(G1, COAUTHORS, "A", "astar")
    assert paths.witness(got).count() == 10 and made == [1]


ODD = ["order:5", "order:0", "order:007", "order:", "order:-5", "order:+5", "order: 5", "order:5\n", "order:1:2", "order:x", ":5", "5", "", "nobody:5", "topic:a", "order:36028797018963967", "order:36028797018963968", "order:99999999999999999999", "order:٣", "é:1"]


def test_names_as_numbers(spark):
    """A name is a long only where the long gives back the whole name; Spark and the client agree on it, and on hashes."""
    from linkwalk.functions.codes import name_of, number, number_of
    from linkwalk.functions.terms import hash_of

    got = spark.createDataFrame([(n,) for n in ODD], "node string").select("node", number("node").alias("n"), F.xxhash64("node").alias("h")).collect()
    assert {r["node"]: r["n"] for r in got} == {n: number_of(n) for n in ODD} and all(r["h"] == hash_of(r["node"]) for r in got)
    numbers = {n: number_of(n) for n in ODD if number_of(n) is not None}
    assert set(numbers) == {"order:5", "order:0", "order:36028797018963967"} and all(name_of(x) == n for n, x in numbers.items())
    assert all(r["h"] == hash_of(r["id"]) for r in spark.range(-3, 3).select("id", F.xxhash64("id").alias("h")).collect())


def test_layouts_keep_no_text_of_numbers(spark, monkeypatch, tmp_path):
    """Rows between key columns are laid out as longs and sorted by one, without their names; odd keys and names stay what they are,
    triples given twice count once, and of literals nothing is written."""
    from linkwalk.operators.store import Store
    from linkwalk.sources.graph import _sales, _supply

    monkeypatch.setattr(client, "LOCAL", 0)
    lines = spark.createDataFrame([(1, 2, 3), (1, 2, 4), (-1, 2, None), (0, 1 << 55, 3)], "l_orderkey long, l_partkey long, l_suppkey long")
    orders = spark.createDataFrame([("1", 7, "O"), ("01", 7, None)], "o_orderkey string, o_custkey int, o_orderstatus string").withColumn("o_orderdate", F.lit("1995-01-02").cast("timestamp"))
    tables = {"lineitem": lines, "orders": orders, "customer": spark.createDataFrame([(7, "C")], "c_custkey long, c_name string")}
    parts = {(src, p): df for src, of in (("supply", _supply), ("sales", _sales)) for p, df in of(tables.get).items()}
    odd = spark.createDataFrame([(n, "z:1") for n in ODD], "s string, o string")
    g = TripleGraph({**parts, ("odd", "odd"): odd}, spark)
    lookup = Combined(PartialDocs(g, 0.5), Endpoint(g))
    held = Store(lookup)
    try:
        kept = spark.read.parquet(held.path)
        assert held.size == 2 * (12 + 2 + 2 + 1 + 1 + len(ODD)) and not kept.where(F.startswith("node", F.lit('"'))).count()
        assert kept.where("node = 'order:5' or nbr = 'order:5'").count() == 0
        book, want = client._Book(lookup, held, 1000), lookup.rows().collect()
        names = {r["node"] for r in want if not r["node"].startswith('"')}
        book.fetch(names | {"nobody"})
        assert {(n, p, inv, o) for n, doc in book.docs.items() for (p, inv), found in doc.items() for o in found} == {(r["node"], r["p"], r["inv"], r["nbr"]) for r in want if r["node"] in names}
        assert all(book.shown[n] == sum(r["shown"] for r in want if r["node"] == n) for n in names) and book.docs["nobody"] == {}
        # Without sizes and incomplete documents no name of an end with a number is made at all.
        plan = g.only("supply").numbered_adjacency(["contains"]).select("node_number", "nbr_number")._jdf.queryExecution().optimizedPlan().toString()
        assert "concat" not in plan and "order:" not in plan
    finally:
        held.close()


def test_a_file_is_read_into_one_table(spark):
    """What a round wants of one file is turned into rows at once, not node by node."""
    from linkwalk.operators.store import Store

    g = from_triples(spark.range(3000).selectExpr("'part:' || id % 600 AS s", "'a' AS p", "'n' || id % 7 AS o"))
    held = Store(FullDocs(g))
    try:
        names = {f"part:{i}" for i in range(600)} | {f"n{i}" for i in range(7)}
        tables = list(held.read(names, 1000, set()))
        assert len(tables) <= len(held.files) and sum(t.num_rows for t in tables) == 6000
        assert {d[0] for t in tables for d in held.documents(t)} == names
    finally:
        held.close()


def test_last_batches_are_not_queued(spark, monkeypatch):
    """A batch over the limit of triples is counted and its goals picked in arrays: the same lookups, answers, ends and sizes as if
    all of it had been queued, of numbers, of other names and of literals."""
    from linkwalk.operators.client import Job, search_all

    rng = random.Random(11)
    name = lambda: rng.choice([f"part:{rng.randrange(40)}", f"order:{rng.randrange(40)}", f"n{rng.randrange(20)}"])
    rows = [(name(), rng.choice("abc"), name()) for _ in range(260)] + [(f"part:{i}", "c", f'"{i % 9}') for i in range(40)]
    g = from_triples(spark.createDataFrame(rows, "s string, p string, o string"))
    lookup = Combined(PartialDocs(g, 0.5), Endpoint(g))
    specs = [Spec(s, k, tie=tie, emit_rule=rule) for k in (1, 4, 9) for s, tie, rule in (("bfs", "low_h", "early"), ("dfs", "low_h", "early"), ("astar", "low_h", "early"), ("astar", "lifo", "on_extract"))]
    ended, old = [], client._Search.end
    monkeypatch.setattr(client._Search, "end", lambda self, nodes: (ended.append(self.spec), old(self, nodes))[0])
    of = lambda x: [[tuple(r) for r in t.orderBy("run", t.columns[1]).collect()] for t in (x.trace(), x.answers(), x.answers("product_node"))]
    for expr, costs, limits in (("(a|^b)*/c?", (), Limits(12, 60, None)), ("!(c)*/c", (("a", 3.0),), Limits(None, 90, None)), ("((a|b)/(^a|^b))*", (("b", 0.5),), Limits(30, 40, None))):
        jobs = [Job(lookup, expr, start, s, costs=costs) for start in ("part:1", "order:2") for s in specs]
        kept, bare = search_all(jobs, limits), search_all(jobs, limits, links=False)
        assert of(kept) == of(bare)
        assert (kept.stopped, kept.seen_size, kept.open_peak, kept.rounds) == (bare.stopped, bare.seen_size, bare.open_peak, bare.rounds)
        with pytest.raises(ValueError, match="met"):
            bare.state
    assert len(ended) > 20 and {s.strategy for s in ended} == {"bfs", "dfs", "astar"}


def test_clients_hold_little(spark, monkeypatch):
    """Runs leave their queues behind when they end, few are held at once, and documents of earlier rounds go: rows stay the same."""
    r = random.Random(5)
    g = graph(spark, [(f"n{r.randint(0, 40)}", r.choice("abc"), f"n{r.randint(0, 40)}") for _ in range(200)])
    specs = [Spec(s, k) for s in ("bfs", "dfs", "astar") for k in (1, 3, 20)]
    of = lambda x: [[tuple(y) for y in t.orderBy("run", t.columns[1]).collect()] for t in (x.trace(), x.answers(), x.state.orderBy("run", "q"))]
    want = client.search(g, "(a|^b)*/c?", "n0", specs, Limits(max_triples=300))
    monkeypatch.setattr(client, "LOCAL", 0)
    monkeypatch.setattr(client, "HELD", 0)
    monkeypatch.setattr(client, "TOGETHER", 2)
    held, old = [], client._Book.fetch

    def fetch(self, wanted):
        read = wanted - self.docs.keys()
        old(self, wanted)
        held.append(len(self.docs) - len(wanted) if read else 0)

    monkeypatch.setattr(client._Book, "fetch", fetch)
    got = client.search(g, "(a|^b)*/c?", "n0", specs, Limits(max_triples=300))
    assert [sorted(x, key=str) for x in of(got)] == [sorted(x, key=str) for x in of(want)] and max(held) <= 0
    assert not any(s.seq or s.heap or s.parent or s.book for s in got.searches)


def test_documents_have_no_greatest_size(spark, monkeypatch):
    """A document of more rows than are turned into lists at once is whole: nothing behind a hub is dropped."""
    monkeypatch.setattr(client, "LOCAL", 0)
    monkeypatch.setattr(client, "ROUND", 7)
    hub = spark.range(500).selectExpr("'S' AS s", "'c' AS p", "IF(id % 5 = 0, 'x' || id, 'part:' || id) AS o")
    g = from_triples(hub.unionByName(hub).unionByName(hub.selectExpr("o AS s", "'d' AS p", "'end:' || o AS o")))
    got = client.search(g, "c/d", "S", [Spec("bfs"), Spec("dfs"), Spec("astar")], Limits(None, None, None, 600), sizes=False)
    names = sorted(f"x{i}" if i % 5 == 0 else f"part:{i}" for i in range(500))
    for run in range(3):
        assert [r["node"] for r in got.trace().where(F.col("run") == run).orderBy("req").collect()] == ["S", *(names[::-1] if run == 1 else names)]
    assert got.answers().groupBy("run").count().where("count = 500").count() == 3
