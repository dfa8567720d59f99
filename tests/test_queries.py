"""Registered queries against their SQL twins, and the plans of the parts that must scale."""

import os
import re
from collections import Counter

import duckdb
import pytest
from pyspark.sql import functions as F

from linkwalk.functions.tables import shared_dir
from linkwalk.operators import product
from linkwalk.operators.search import Limits, Spec, run_many
from linkwalk.plans.automaton import compile_path
from linkwalk.plans.registry import ORACLE_SQL, QUERIES
from linkwalk.plans.workloads import GRID, WORKLOADS
from linkwalk.sources.graph import from_testdata, from_triples, read_layout, read_triples, write_layout
from linkwalk.streaming import live

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
FAST = ["reach_coorder", "reach_coorder_names", "customer_reach", "plus_closure", "negated_set", "page_hosts", "multi_star_optional", "algebra_union", "algebra_negated_small", "algebra_star_small", "connected_pair", "reach_from_many", "bfs_layer_requests", "shortest_walks", "partial_docs_recall", "triples_by_label", "degree_stats", "source_overlap", "pattern_optional", "constructed_triples", "tally_cube", "pattern_pages", "session_windows", "state_table", "bucket_lengths_n", "trace_bfs", "optimality_gaps", "expansions_contained", "cheapest_walks", "several_publishers", "cached_documents", "tested_nodes", "helped_docs_share", "helped_docs_recall", "answers_as_they_come", "quote_langs", "order_dfs", "order_dfs_batches", "order_astar", "order_astar_plain", "order_astar_lifo_ties", "order_astar_multi_source", "emission_bfs", "emission_dfs_batches", "emission_astar_fifo_ties", "emission_astar_on_extract", "emission_astar_batches", "emission_dfs_multi_source"]


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    con.execute("set TimeZone='UTC'")
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return con


def norm(x):
    return round(x, 9) if isinstance(x, float) else x


@pytest.mark.parametrize("name", FAST)
def test_query_equals_its_twin(spark, sf, duck, name):
    df = QUERIES[name](spark, sf)
    columns = sorted(df.columns)
    want = duck.sql(ORACLE_SQL[name])
    assert sorted(want.columns) == columns
    got = Counter(tuple(norm(r[c]) for c in columns) for r in df.collect())
    assert got == Counter(tuple(norm(x) for x in r) for r in want.select(*[f'"{c}"' for c in columns]).fetchall())


def test_reach_from_all_starts_everywhere(spark, sf, duck):
    got = Counter(tuple(r) for r in QUERIES["reach_from_all"](spark, sf).select("customer", "node", "length").collect())
    assert got == Counter(duck.sql(f"SELECT customer, node, length FROM ({ORACLE_SQL['reach_from_all']})").fetchall())
    assert len({c for c, _, _ in got}) > 10


def test_registry_is_whole():
    assert set(ORACLE_SQL) <= set(QUERIES) and len(GRID) == 11 and set(WORKLOADS) <= set(QUERIES)


def test_known_counts(spark, sf):
    got = {r["length"]: r["count"] for r in QUERIES["reach_coorder"](spark, sf).groupBy("length").count().collect()}
    assert got == {0: 1, 2: 100, 4: 99}


def test_first_answers_favour_guided_search(spark, sf):
    w = WORKLOADS["reach_coorder_names"]
    first = lambda spec, most: run_many(w.graph(spark, sf), w.expr, w.start, [spec], Limits(max_requests=most)).answers().where("rank = 2").first()["req_at_emit"]
    assert first(Spec("astar"), 4) == 3 and first(Spec("bfs", 8), 45) >= 36


def test_scan_reads_only_what_the_automaton_wants(spark, sf):
    g = from_testdata(spark, sf)
    a = compile_path("(^contains/contains)*")
    plan = g.adjacency(a.labels)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Scan parquet") == 1 and "l_orderkey" in plan and "l_quantity" not in plan
    assert "Python" not in plan


def moved(df):
    """Exchanges of a plan by what they are keyed on, without those inside tables that are held."""
    out, inside = [], None
    for line in df._jdf.queryExecution().executedPlan().toString().split("\n"):
        depth = len(line) - len(line.lstrip(" :+-*"))
        if inside is not None and depth > inside:
            continue
        inside = depth if "InMemoryTableScan" in line else None
        if "Exchange hashpartitioning(" in line or "Exchange rangepartitioning(" in line or "Exchange SinglePartition" in line:
            out.append(re.sub(r"#\d+", "", line.split("partitioning(")[-1].split("),")[0]))
    return out


@pytest.mark.parametrize(("expr", "answers", "key"), [("(^contains/contains)*", 200, "node, inv"), ("(^contains/contains)*/^filled_by?", 200, "node, p, inv")])
def test_a_round_moves_frontiers_only(spark, sf, monkeypatch, expr, answers, key):
    rounds, held = [], product.keep
    monkeypatch.setattr(product, "keep", lambda df: (rounds.append(moved(df)), held(df))[1])
    monkeypatch.setattr(product, "NARROW", -1)
    monkeypatch.setattr(product, "MADE", 0)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        got = product.explore(from_testdata(spark, sf, ["supply"]), expr, spark.createDataFrame([("part:0",)], "seed string"))
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert got.answers().count() == answers
    # The first two tables are the hubs and the seeds. A round moves the frontier to the adjacency and its successors to what is
    # seen: neither the adjacency nor the layers before take part.
    assert len(rounds) >= 6 and all(len(r) == 2 and r[0].startswith("seed, node, q") and r[1].startswith(key) for r in rounds[2:]), rounds


def test_adjacency_is_dealt_out_once(spark, monkeypatch):
    """Before the first round edges move once: triples given twice are told apart where successors are."""
    plans, held = [], product.keep
    monkeypatch.setattr(product, "keep", lambda df: (plans.append(df._jdf.queryExecution().executedPlan().toString()), held(df))[1])
    rows = spark.createDataFrame([("A", "a", "B"), ("A", "a", "B"), ("B", "a", "C"), ("B", "a", "C"), ("C", "a", "A")], "s string, p string, o string")
    got = product.explore(from_triples(rows), "a*", spark.createDataFrame([("A",)], "seed string"))
    assert sorted((r["node"], r["length"]) for r in got.table.collect()) == [("A", 0), ("B", 1), ("C", 2)]
    inside = plans[0].split("InMemoryRelation")[1]
    assert inside.split("Initial Plan")[0].count("Exchange") == 1


def test_no_task_numbers_all_successors(spark, sf):
    from linkwalk.operators import search as engine

    w = WORKLOADS["reach_coorder"]
    for spec in (Spec("bfs", None), Spec("astar", None, batch="bucket")):
        r = engine._Rounds(w.graph(spark, sf), w.expr, w.start, [spec], Limits(None, None, None, None), None, None)
        plans, held = [], engine.keep
        engine.keep = lambda df: (plans.append(df._jdf.queryExecution().executedPlan().toString()), held(df))[1]
        try:
            for i, _ in enumerate(r.loop()):
                if i == 2:
                    break
        finally:
            engine.keep = held
        assert len(plans) >= 2 and not any("Window" in p or "SinglePartition" in p for p in plans)


def test_hubs_are_found_and_cut(spark):
    star = spark.range(300).selectExpr("'hub' AS s", "'a' AS p", "'x' || id AS o").unionByName(spark.createDataFrame([("x7", "b", "end")], "s string, p string, o string"))
    seeds = spark.createDataFrame([("hub",)], "seed string")
    plain, cut = (Counter(tuple(r) for r in product.explore(from_triples(star), "a/b?", seeds, hub=h).answers().collect()) for h in (1000, 100))
    assert plain == cut and len(cut) == 301


def test_budgeted_searches_against_the_simulator(spark, sf):
    """Lookups and answers of the experiments, on the given tables: every strategy, one by one and in batches."""
    from simulate import simulate

    from linkwalk.operators.client import search

    for key in ("reach_coorder_names", "collab_multi_source"):
        w = WORKLOADS[key]
        g = w.graph(spark, sf)
        triples = [tuple(r) for r in g.triples.select("s", "p", "o").collect()]
        specs = [Spec(s, k) for s in ("bfs", "dfs", "astar") for k in (1, 10)]
        got = search(g, w.expr, w.start, specs, Limits(None, None, None, 150))
        trace, answers = got.trace().orderBy("run", "req").collect(), got.answers().orderBy("run", "rank").collect()
        for i, s in enumerate(specs):
            want = simulate(triples, w.expr, w.start, s.strategy, s.k, most=150)
            assert [r["node"] for r in trace if r["run"] == i] == want[0]
            assert [(r["node"], int(r["length"]), r["req_at_emit"]) for r in answers if r["run"] == i] == want[1]


def test_the_published_comparison(spark, sf):
    rows = {(r["axis"], r["k"]): r for r in QUERIES["dominance_tally"](spark, sf).collect()}
    assert set(rows) == {(a, k) for a in ("requests", "seconds") for k in (1, 10, 20, 40)}
    assert all(rows[a, 1]["astar"] > max(rows[a, 1]["bfs"], rows[a, 1]["dfs"]) for a in ("requests", "seconds"))
    lengths = {(r["workload"], r["strategy"], r["rank"]): r["length"] for r in QUERIES["lengths_at_ranks"](spark, sf).collect()}
    assert all(lengths[w, "dfs", n] >= lengths[w, "astar", n] for w, s, n in lengths if s == "dfs" and (w, "astar", n) in lengths)
    faster = {(r["strategy"], r["k"]): r["speed_up"] for r in QUERIES["speed_up_by_k"](spark, sf).collect()}
    assert all(faster[s, 1] == 1 and faster[s, 20] > 3 for s in ("astar", "bfs", "dfs"))


def test_quotes_against_every_pair(spark):
    from linkwalk.sources.graph import quoted

    items = ["one two three four five six", "ab", "x y", "two three four five", " lead and trail ", "tab\tone two three four"]
    texts = ["zone two three four five sixty", "one two three four five six", "cab", "x  y", "x y z", None, "", "a lead and trail b", "tab\tone two three fourth", "one two three"]
    docs, bench = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), spark.createDataFrame(list(enumerate(items)), "item_id long, item string")
    got = Counter((r["doc_id"], r["item_id"]) for r in quoted(docs, bench).collect())
    assert got == Counter((i, j) for i, t in enumerate(texts) for j, x in enumerate(items) if t is not None and x in t)


def test_nearest_in_blocks_equals_the_broadcast_form(spark, sf):
    from linkwalk.sources.graph import nearest, nearest_in_blocks

    v = spark.read.parquet(f"{sf}/embeddings.parquet").where("embedding is not null")
    of = lambda df: sorted(tuple(r) for r in df.collect())
    assert of(nearest_in_blocks(v, 500, block=100)) == of(nearest(v))


def test_layout_prunes_partitions(spark, sf, tmp_path):
    g = from_testdata(spark, sf, ["geo"])
    write_layout(g, str(tmp_path / "adj"))
    rows = read_layout(spark, str(tmp_path / "adj"), ["in_region"])
    plan = rows._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [" in plan and "p#" in plan.split("PartitionFilters: [")[1][:200]
    assert rows.count() == 50


def test_readers(spark, tmp_path):
    path = tmp_path / "t.nt"
    path.write_text('<a> <p> <b> .\n<a> <n> "x \\"y\\""@en .\nnot a triple\n<a> <p> <b> .\n')
    got = sorted(tuple(r) for r in read_triples(spark, str(path)).triples.select("s", "p", "o").collect())
    assert got == [("a", "n", '"x \\"y\\"'), ("a", "p", "b")]
    (tmp_path / "t.csv").write_text("s,p,o\na,p,b\n,p,c\n")
    assert read_triples(spark, str(tmp_path / "t.csv"), "csv").triples.count() == 1
    (tmp_path / "t.json").write_text('{"s": "a", "p": "q", "o": "c"}\n')
    assert read_triples(spark, str(tmp_path / "t.json"), "json").match(p="q").count() == 1
    with pytest.raises(ValueError):
        read_triples(spark, "x", "xml")


def test_live_reach_equals_batch(spark):
    live_ = live.LiveReach(spark, "(^c/c)*", "A")
    batches = [[("P1", "c", "B"), ("P2", "c", "D")], [("P1", "c", "A")], [("P2", "c", "B"), ("P1", "c", "A")]]
    seen = []
    for rows in batches:
        live_.add(spark.createDataFrame(rows, "s string, p string, o string"))
        seen.append({r["node"] for r in live_.answers().collect()})
    assert seen == [{"A"}, {"A", "B"}, {"A", "B", "D"}]
    whole = from_triples(spark.createDataFrame(sum(batches, []), "s string, p string, o string"))
    assert {r["node"] for r in product.reach(whole, "(^c/c)*", "A").collect()} == seen[-1]


def test_stream_rates_drop_late_rows(spark, tmp_path):
    rows = [[("2024-01-01 00:10:00", "a"), ("2024-01-01 05:00:00", "b")], [("2024-01-01 09:00:00", "c")], [("2024-01-01 00:20:00", "late"), ("2024-01-01 20:00:00", "d")]]
    for i, part in enumerate(rows):
        spark.createDataFrame(part, "t string, x string").select(F.to_timestamp("t").alias("ts"), "x").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        del i
    stream = spark.readStream.schema("ts timestamp, x string").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    q = live.answer_rate(stream, lateness="10 minutes").writeStream.format("memory").queryName("rates").outputMode("append").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "cp")).start()
    q.awaitTermination()
    got = {r["start"].hour: r["n"] for r in spark.table("rates").collect()}
    assert got[0] == 1 and got[5] == 1 and got[9] == 1


def test_codes_round_trip(spark, sf):
    from linkwalk.functions.codes import build_dictionary, encode
    from linkwalk.functions.tables import keep

    adj = from_testdata(spark, sf, ["geo"]).adjacency()
    d = keep(build_dictionary(adj, 4))
    assert d.count() == d.select("code").distinct().count() == adj.select("node").distinct().count()
    back = encode(adj, d).join(d.withColumnRenamed("node", "name"), F.col("node") == F.col("code"))
    assert back.count() == adj.count()


def test_only_results_stay_on_disk(spark, monkeypatch):
    """Tables that only the rounds read are deleted; a reach keeps its layers, a closure its last table."""
    chain = from_triples(spark.createDataFrame([(f"n{i}", "next", f"n{i + 1}") for i in range(9)], "s string, p string, o string"))
    tables = lambda: {x for x in os.listdir(shared_dir(spark).removeprefix("file:")) if x.startswith("walk-")}
    before = tables()
    assert product.connected(chain, "next*", "n3", "n5") and not product.connected(chain, "next*", "n8", "n6")
    assert tables() == before
    made = product.closure(spark.createDataFrame([(f"n{i}", f"n{i + 1}") for i in range(5)], "s string, o string"))
    assert made.count() == 15 and len(tables() - before) == 1
    before = tables()
    monkeypatch.setattr(product, "PARTS", 3)  # so that what is seen is merged
    reached = product.explore(chain, "next*", spark.createDataFrame([("n0",)], "seed string"))
    assert len(tables() - before) == len({f.rsplit("/", 2)[-2] for f in reached.table.inputFiles()}) and reached.answers().count() == 10


def test_states_count_the_edges_of_the_tables(spark, sf):
    """Of the two directions of placed_by and contains, and of same_as, each state takes those that its transitions read."""
    got = {r["q"]: r["edges"] for r in QUERIES["state_table"](spark, sf).collect()}
    placed, inside, same = (WORKLOADS["collab_multi_source"].graph(spark, sf).match(p=p).count() for p in ("placed_by", "contains", "same_as"))
    assert got == {0: placed + 2 * same, 1: placed + inside, 2: inside} and placed and inside


def test_whole_searches_leave_the_client(spark, sf, monkeypatch):
    """Searches without a budget are layers of tables: no document comes to the driver."""
    from linkwalk.operators import store

    def refuse(*_):
        raise AssertionError("a whole search asked for documents")

    monkeypatch.setattr(store.Store, "read", refuse)
    monkeypatch.setattr(store.Store, "everything", refuse)
    w = WORKLOADS["reach_orders"]
    cached, helped = (QUERIES[n](spark, sf).first() for n in ("cached_documents", "helped_docs_recall"))
    assert cached["lookups"] >= cached["requests"] > 0
    assert helped["helped"] == w.exact(spark, sf).count() >= helped["alone"] > 0


def test_layers_go_on_past_the_cap_of_the_twin(spark, tmp_path):
    """The twin stops at length 8, which is enough for the given tables; the query has no such bound."""
    spark.range(12).selectExpr("id div 2 AS l_orderkey", "(id + 1) div 2 AS l_partkey", "id AS l_suppkey").write.parquet(str(tmp_path / "lineitem.parquet"))
    got = {(r["length"], r["expansions"]) for r in QUERIES["bfs_layer_requests"](spark, str(tmp_path)).collect()}
    assert got == {(i, 1) for i in range(13)}
    con = duckdb.connect()
    con.execute(f"create view lineitem as select * from '{tmp_path}/lineitem.parquet/*.parquet'")
    assert set(con.execute(ORACLE_SQL["bfs_layer_requests"]).fetchall()) == {x for x in got if x[0] <= 8}


def test_neighbours_come_from_blocks(spark):
    """From a few thousand vectors on, links come from products of blocks; they are those of all pairs, ties included."""
    from linkwalk.sources.graph import _vectors, nearest, nearest_in_blocks

    v = spark.range(3000).selectExpr("id AS vec_id", "array(cast(id % 37 + 1 AS float), cast(id % 11 AS float), cast(id % 2 AS float)) AS embedding", "0 AS label")
    assert "CoGroups" in _vectors(lambda _: v)["near"]()._jdf.queryExecution().executedPlan().toString()
    few = v.where("vec_id < 300 OR vec_id IN (333, 407, 814)")
    # The all-pairs form tells equal directions apart by rounding; whole numbers of one direction here are equal rows.
    ids = lambda df: {(r["vec_id"], r["other"]) for r in df.where("rank = 1").collect()}
    exact = few.selectExpr("vec_id", "array(embedding[0], embedding[1] + vec_id / 7919, embedding[2]) AS embedding")
    assert ids(nearest_in_blocks(exact, 303, block=100)) == ids(nearest(exact))
    pairs = nearest_in_blocks(few, 303, block=64).collect()
    assert len(pairs) == 3 * few.count() and {(r["vec_id"], r["other"]) for r in pairs} == {(r["vec_id"], r["other"]) for r in nearest_in_blocks(few, 303, block=4096).collect()}


def test_whole_evaluation_sees_what_a_lookup_shows(spark, tmp_path):
    """Where documents lack the triple that leads on, evaluation over them alone ends there; with the endpoint's help it goes on."""
    import hashlib

    from linkwalk.operators.deref import Combined, Endpoint, PartialDocs
    from linkwalk.plans.registry import _Seen

    held = lambda i: hashlib.md5(f"order:{i}|contains|part:0".encode()).hexdigest()[:2] < "80"
    spark.range(40).selectExpr("id AS l_orderkey", "0L AS l_partkey", "0L AS l_suppkey").write.parquet(str(tmp_path / "lineitem.parquet"))
    shown = {f"order:{i}" for i in range(40) if held(i)}
    assert 0 < len(shown) < 40
    g = from_testdata(spark, str(tmp_path), ["supply"])
    docs = PartialDocs(g, 0.5)
    assert {r["node"] for r in product.reach(_Seen(docs), "^contains", "part:0").collect()} == shown
    assert product.reach(_Seen(Combined(docs, Endpoint(g))), "^contains", "part:0").count() == 40
    assert tuple(QUERIES["helped_docs_recall"](spark, str(tmp_path)).first()) == (len(shown), 40)


@pytest.mark.parametrize("name, w", [("dfs", WORKLOADS["reach_coorder_names"]), ("dfs_multi_source", WORKLOADS["collab_multi_source"])])
def test_depth_first_search_goes_to_its_end(spark, sf, duck, name, w):
    """Every product node with a way on is looked up once, every answer is named, and the SQL has the same, past 300 lookups."""
    order, emission = (QUERIES[f"{x}_{name}"](spark, sf) for x in ("order", "emission"))
    looked, answers = [tuple(r) for r in order.orderBy("req").collect()], [tuple(r) for r in emission.orderBy("rank").collect()]
    a = compile_path(w.expr)
    seen = product.explore(w.graph(spark, sf), w.expr, spark.createDataFrame([(w.start,)], "seed string")).table
    live = {(r["node"], r["q"]) for r in seen.collect() if r["q"] in {q for q, _, _ in a.edges} and not r["node"].startswith('"')}
    assert {x[1:3] for x in looked} == live and len(looked) == len(live) > 300
    assert {x[1] for x in answers} == {r["node"] for r in w.exact(spark, sf).collect()}
    assert looked == sorted(duck.sql(ORACLE_SQL[f"order_{name}"]).select("req", "node", "q", "g").fetchall())
    assert answers == sorted(duck.sql(ORACLE_SQL[f"emission_{name}"]).select("rank", "node", "length", "req_at_emit").fetchall())


def test_containment_holds_for_all_answers(spark, tmp_path):
    """The 41st answer and those behind it count: a chain of one new name for each step is followed to its last name."""
    spark.range(121).selectExpr("id div 2 AS l_orderkey", "(id + 1) div 2 AS l_partkey", "id AS l_suppkey").where("l_partkey < 5").write.parquet(str(tmp_path / "lineitem.parquet"))
    spark.range(60).selectExpr("id AS p_partkey", "IF(id < 5, 'n' || id, NULL) AS p_name", "'b' AS p_brand", "'t' AS p_type").unionByName(spark.range(80).selectExpr("0L AS p_partkey", "'first ' || id AS p_name", "'b' AS p_brand", "'t' AS p_type")).write.parquet(str(tmp_path / "part.parquet"))
    con = duckdb.connect()
    for t in ("lineitem", "part"):
        con.execute(f"create view {t} as select * from '{tmp_path}/{t}.parquet/*.parquet'")
    got = tuple(QUERIES["expansions_contained"](spark, str(tmp_path)).first())
    assert got == con.execute(ORACLE_SQL["expansions_contained"]).fetchall()[0] == (9, 0)
