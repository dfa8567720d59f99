"""Triples, adjacency, and the tables that they come from."""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import dataclass
from functools import reduce as fold

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.codes import number, number_in
from ..functions.terms import host_of, lit_date, literal, named

TRIPLE = "s string, p string, o string, src string"


def _read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _numbered(df: DataFrame, s: tuple[str, str], o: tuple[str, str] | Column) -> DataFrame:
    """Triples from a key column, given as its kind and name, to another or to names that are no numbers, with ``s_number`` and
    ``o_number``: the ends as longs, so that who needs no names makes none. Keys that are no whole numbers are left to their names."""
    pair = df.select(named(*s).alias("s"), (named(*o) if isinstance(o, tuple) else o).alias("o"), number_in(*s).alias("s_number"), (number_in(*o) if isinstance(o, tuple) else F.lit(None).cast("long")).alias("o_number"))
    whole = all(df.schema[x[1]].dataType.typeName() in ("long", "integer", "short", "byte") for x in (s, o) if isinstance(x, tuple))
    return pair if whole else pair.select("s", "o")


def _supply(t) -> dict[str, DataFrame]:
    li = t("lineitem")
    order, part, supplier = ("order", "l_orderkey"), ("part", "l_partkey"), ("supplier", "l_suppkey")
    return {"contains": _numbered(li, order, part), "filled_by": _numbered(li, order, supplier), "supplies": _numbered(li, supplier, part)}


def _sales(t) -> dict[str, DataFrame]:
    o = t("orders")
    order = ("order", "o_orderkey")
    return {
        "placed_by": _numbered(o, order, ("customer", "o_custkey")),
        "dated": _numbered(o, order, lit_date("o_orderdate")),
        "status": _numbered(o, order, literal("o_orderstatus")),
        "name": _numbered(t("customer"), ("customer", "c_custkey"), literal("c_name")),
    }


def _geo(t) -> dict[str, DataFrame]:
    c, s, n, r = t("customer"), t("supplier"), t("nation"), t("region")
    live = c.select(named("customer", "c_custkey"), named("nation", "c_nationkey")).union(s.select(named("supplier", "s_suppkey"), named("nation", "s_nationkey")))
    names = n.select(named("nation", "n_nationkey"), literal("n_name")).union(r.select(named("region", "r_regionkey"), literal("r_name"))).union(s.select(named("supplier", "s_suppkey"), literal("s_name")))
    inside = n.join(r, n["n_regionkey"] == r["r_regionkey"]).select(named("nation", "n_nationkey"), named("region", "r_regionkey"))
    return {"in_nation": live, "in_region": inside, "name": names}


def _catalog(t) -> dict[str, DataFrame]:
    p = t("part")
    part = ("part", "p_partkey")
    return {"label": _numbered(p, part, literal("p_name")), "brand": _numbered(p, part, literal("p_brand")), "kind": _numbered(p, part, literal("p_type"))}


def _clicks(t) -> dict[str, DataFrame]:
    e, c = t("events"), t("customer")
    event, user = ("event", "event_id"), ("user", "user_id")
    topic = F.concat(F.lit("topic:"), F.get_json_object("props", "$.k"))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    after = e.select("event_id", F.lead("event_id").over(w).alias("next")).where("next is not null")
    same = e.select("user_id").distinct().join(c, F.col("user_id") == F.col("c_custkey"))
    return {
        "actor": _numbered(e, event, user),
        "about": _numbered(e, event, topic),
        "followed_by": after.select(named(*event), named("event", "next")),
        "same_as": same.select(named(*user), named("customer", "c_custkey")),
    }


def links_from_pages(pages: DataFrame) -> dict[str, DataFrame]:
    """Links of raw pages: to the host, to the resolved target, and to the unresolved reference."""
    page = named("page", "page_id")
    refs = pages.select(page.alias("page"), host_of("url").alias("host"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href"))
    return {
        "on_host": pages.select(page, F.concat(F.lit("host:"), host_of("url"))),
        "links_to": refs.select("page", F.concat(F.lit("url:"), "host", "href")),
        "anchors": refs.select("page", F.concat(F.lit("ref:"), "href")),
    }


def _web(t) -> dict[str, DataFrame]:
    return links_from_pages(t("pages"))


#: Words of an anchor, and how many items too short for one may be compared with every text.
ANCHOR, SHORT = 3, 10_000


def quoted(docs: DataFrame, items: DataFrame) -> DataFrame:
    """``(doc_id, text, item_id, item)`` where the text holds the item. An item's words but its first and last stand between blanks
    in any text that holds it, so ``ANCHOR`` of them in a row are looked up among the texts' word runs, and what meets is verified.
    Items too short for an anchor are compared with every text; they are few, which is checked."""
    words = items.where("item is not null").withColumn("w", F.split("item", " "))
    long_ = words.where(F.size("w") >= ANCHOR + 2).select("item_id", "item", F.array_join(F.slice("w", 2, ANCHOR), " ").alias("anchor"))
    short = words.where(F.size("w") < ANCHOR + 2).select("item_id", "item")
    if short.limit(SHORT + 1).count() > SHORT:
        raise ValueError(f"more than {SHORT} items of fewer than {ANCHOR + 2} words")
    texts = docs.where("text is not null").select("doc_id", "text")
    runs = texts.select("doc_id", F.split("text", " ").alias("w")).where(F.size("w") >= ANCHOR)
    runs = runs.select("doc_id", F.explode(F.transform(F.sequence(F.lit(1), F.size("w") - ANCHOR + 1), lambda i: F.array_join(F.slice("w", i, ANCHOR), " "))).alias("anchor"))
    met = runs.join(long_, "anchor").select("doc_id", "item_id", "item").distinct()
    found = met.join(texts, "doc_id").where(F.contains("text", "item")).select("doc_id", "text", "item_id", "item")
    return found.unionByName(texts.join(F.broadcast(short), F.contains("text", "item")).select("doc_id", "text", "item_id", "item"))


def _corpus(t) -> dict[str, DataFrame]:
    d, b, labels = t("documents"), t("benchmark"), t("labels")
    doc = named("doc", "doc_id")
    first = d.groupBy(F.sha2(F.col("text").cast("binary"), 256).alias("h")).agg(F.min("doc_id").alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1")
    copies = d.select("doc_id", F.sha2(F.col("text").cast("binary"), 256).alias("h")).join(first, "h").where("doc_id <> first")
    return {
        "in_lang": d.select(doc, F.concat(F.lit("lang:"), "lang")),
        "from_source": d.select(doc, F.concat(F.lit("source:"), "source")),
        "copy_of": copies.select(doc, named("doc", "first")),
        "quotes": lambda: quoted(d.select("doc_id", "text"), b.select("item_id", F.col("text").alias("item"))).select(doc, named("item", "item_id")),
        "rated": labels.select(doc, named("quality", "quality")),
    }


def _dialog(t) -> dict[str, DataFrame]:
    c = t("conversations")
    after = c.select("conv_id", "turn", F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn")).alias("next")).where("next is not null")
    return {"next": after.select(named("turn", "conv_id", "turn"), named("turn", "conv_id", "next"))}


def nearest(vectors: DataFrame, m: int = 3) -> DataFrame:
    """``(vec_id, other, rank)``: the m nearest by cosine, ties to the smaller id. All vectors are compared with the broadcast
    table, which the caller has checked to be small; see :func:`nearest_in_blocks` for more."""
    v = vectors.select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("x"))
    v = v.withColumn("norm", F.sqrt(F.aggregate("x", F.lit(0.0), lambda a, b: a + b * b)))
    o = v.select(F.col("vec_id").alias("other"), F.col("x").alias("y"), F.col("norm").alias("norm_o"))
    dot = F.aggregate(F.zip_with("x", "y", lambda a, b: a * b), F.lit(0.0), lambda a, b: a + b)
    scored = v.join(F.broadcast(o), F.col("vec_id") != F.col("other")).select("vec_id", "other", (dot / (F.col("norm") * F.col("norm_o"))).alias("cos"))
    rank = F.row_number().over(Window.partitionBy("vec_id").orderBy(F.desc("cos"), "other"))
    return scored.withColumn("rank", rank).where(F.col("rank") <= m).select("vec_id", "other", "rank")


def nearest_in_blocks(vectors: DataFrame, n: int, m: int = 3, block: int = 4096) -> DataFrame:
    """The same for any number of vectors: blocks meet pairwise, each pair as one product of matrices in a task that holds two
    blocks, and the m best of each pair are merged. Cosines are compared to 12 decimals, so that equal vectors tie."""
    k = max(1, -(-n // block))
    every = F.sequence(F.lit(0), F.lit(k - 1))
    own = vectors.select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("x"), F.pmod(F.xxhash64("vec_id"), F.lit(k)).cast("int").alias("b"))
    left = own.select(F.col("b").alias("i"), F.explode(every).alias("j"), "vec_id", "x")
    right = own.select(F.explode(every).alias("i"), F.col("b").alias("j"), "vec_id", "x")

    def compare(a, b):
        import numpy as np
        import pyarrow as pa

        of = lambda t: np.array(t["x"].to_pylist(), float)
        x, y, ids, others = of(a), of(b), a["vec_id"].to_numpy(), b["vec_id"].to_numpy()
        out = {"vec_id": [], "other": [], "cos": []}
        if len(ids) and len(others):
            y = y / np.linalg.norm(y, axis=1, keepdims=True)
            for lo in range(0, len(ids), 512):
                c = np.round(x[lo : lo + 512] / np.linalg.norm(x[lo : lo + 512], axis=1, keepdims=True) @ y.T, 12)
                c[ids[lo : lo + 512, None] == others[None, :]] = -np.inf
                k = min(m, c.shape[1])
                # Only what reaches the k-th best is sorted, with all that tie with it.
                i, j = np.nonzero((c >= np.partition(c, -k, axis=1)[:, -k, None]) | np.isnan(c).any(axis=1, keepdims=True))
                order = np.lexsort((others[j], -c[i, j], i))
                i, j = i[order], j[order]
                first = np.arange(len(i)) - np.searchsorted(i, np.arange(len(c)))[i] < k
                i, j = i[first], j[first]
                out["vec_id"] += ids[lo + i].tolist()
                out["other"] += others[j].tolist()
                out["cos"] += c[i, j].tolist()
        return pa.table({"vec_id": pa.array(out["vec_id"], pa.int64()), "other": pa.array(out["other"], pa.int64()), "cos": pa.array(out["cos"], pa.float64())})

    best = left.groupBy("i", "j").cogroup(right.groupBy("i", "j")).applyInArrow(compare, "vec_id long, other long, cos double").where("vec_id <> other")
    rank = F.row_number().over(Window.partitionBy("vec_id").orderBy(F.desc("cos"), "other"))
    return best.withColumn("rank", rank).where(F.col("rank") <= m).select("vec_id", "other", "rank")


#: Vectors up to which all are broadcast.
BROADCAST = 2_000


def _vectors(t) -> dict:
    v = t("embeddings")

    def near() -> DataFrame:
        n = v.count()
        found = nearest(v) if n <= BROADCAST else nearest_in_blocks(v, n)
        return found.select(named("vec", "vec_id"), named("vec", "other"))

    return {"near": near, "cluster": v.select(named("vec", "vec_id"), named("cluster", "label"))}


SOURCES: dict[str, Callable] = {"supply": _supply, "sales": _sales, "geo": _geo, "catalog": _catalog, "clicks": _clicks, "web": _web, "corpus": _corpus, "dialog": _dialog, "vectors": _vectors}
#: Labels by source; only the sources that hold a wanted label are read.
LABELS = {
    "supply": ["contains", "filled_by", "supplies"],
    "sales": ["placed_by", "dated", "status", "name"],
    "geo": ["in_nation", "in_region", "name"],
    "catalog": ["label", "brand", "kind"],
    "clicks": ["actor", "about", "followed_by", "same_as"],
    "web": ["on_host", "links_to", "anchors"],
    "corpus": ["in_lang", "from_source", "copy_of", "quotes", "rated"],
    "dialog": ["next"],
    "vectors": ["near", "cluster"],
}


def _ends(t: DataFrame) -> DataFrame:
    ends = F.array(F.struct(F.col("s").alias("node"), F.lit(False).alias("inv"), F.col("o").alias("nbr")), F.struct(F.col("o").alias("node"), F.lit(True).alias("inv"), F.col("s").alias("nbr")))
    return t.select("p", "src", F.inline(ends)).select("node", "p", "inv", "nbr", "src")


def _made(part: DataFrame | Callable[[], DataFrame]) -> DataFrame:
    t = part() if callable(part) else part
    return t if "s_number" in t.columns else t.toDF("s", "o")


@dataclass
class TripleGraph:
    """A set of triples ``(s, p, o, src)``, held apart by (source, label) so that unread labels cost nothing. A part may be a
    function that builds its table when the label is read."""

    parts: dict[tuple[str, str], DataFrame | Callable[[], DataFrame]]
    spark: SparkSession

    @property
    def triples(self) -> DataFrame:
        """All triples, each once; null ends are dropped."""
        return self.select_labels(None)

    def select_labels(self, labels: Iterable[str] | None, repeats: bool = False) -> DataFrame:
        """Triples of some labels; ``repeats`` leaves it to the caller to drop those that are given twice."""
        wanted = None if labels is None else set(labels)
        found = [_made(df).select("s", F.lit(p).alias("p"), "o", F.lit(src).alias("src")) for (src, p), df in self.parts.items() if p != "*" and (wanted is None or p in wanted)]
        found += [df.select("s", "p", "o", "src") if wanted is None else df.select("s", "p", "o", "src").where(F.col("p").isin(sorted(wanted))) for (_, p), df in self.parts.items() if p == "*"]
        if not found:
            return self.spark.createDataFrame([], TRIPLE)
        out = fold(DataFrame.unionByName, found)
        out = out.where("s is not null and p is not null and o is not null")
        return out if repeats else out.dropDuplicates(["s", "p", "o"])

    def adjacency(self, labels: Iterable[str] | None = None) -> DataFrame:
        """``(node, p, inv, nbr, src)``: every triple from both of its ends."""
        return _ends(self.select_labels(labels))

    def repeated_adjacency(self, labels: Iterable[str] | None = None) -> DataFrame:
        """The same rows, once or more often: for a caller that deals them out by node, and drops repeats then."""
        return _ends(self.select_labels(labels, repeats=True))

    def numbered_adjacency(self, labels: Iterable[str] | None = None) -> DataFrame:
        """The same, with ``node_number`` and ``nbr_number``: names as longs, where they are such. Key columns are read once for
        either end, so that an end's name is made only where it is used."""
        wanted = None if labels is None else set(labels)
        parts = {k: _made(df) if k[1] != "*" else df for k, df in self.parts.items() if wanted is None or k[1] in wanted or k[1] == "*"}
        keyed = {k: df for k, df in parts.items() if "s_number" in df.columns}
        out = []
        for (src, p), df in keyed.items():
            for a, b, inv in (("s", "o", False), ("o", "s", True)):
                out.append(df.where("s is not null and o is not null").select(F.col(a).alias("node"), F.lit(p).alias("p"), F.lit(inv).alias("inv"), F.col(b).alias("nbr"), F.lit(src).alias("src"), F.col(f"{a}_number").alias("node_number"), F.col(f"{b}_number").alias("nbr_number")))
        if len(keyed) < len(parts) or not parts:
            rest = TripleGraph({k: df for k, df in parts.items() if k not in keyed}, self.spark).repeated_adjacency(labels)
            out.append(rest.withColumns({f"{c}_number": number(c) for c in ("node", "nbr")}))
        return fold(DataFrame.unionByName, out)

    def match(self, s: str | None = None, p: str | None = None, o: str | None = None) -> DataFrame:
        """Triples with the given ends and label."""
        out = self.select_labels(None if p is None else [p])
        for column, value in (("s", s), ("o", o)):
            if value is not None:
                out = out.where(F.col(column) == value)
        return out

    def degrees(self) -> DataFrame:
        """``(node, p, inv, degree)``."""
        return self.adjacency().groupBy("node", "p", "inv").agg(F.count(F.lit(1)).alias("degree"))

    def hubs(self, least: int) -> DataFrame:
        """Nodes with at least ``least`` triples under one label and direction."""
        return self.degrees().where(F.col("degree") >= least)

    def by_label(self) -> DataFrame:
        return self.triples.groupBy("src", "p").agg(F.count(F.lit(1)).alias("n"))

    def source_overlap(self) -> DataFrame:
        """``(a, b, nodes)``: how many nodes two sources share."""
        nodes = self.adjacency().select("node", "src").distinct()
        other = nodes.select("node", F.col("src").alias("b"))
        return nodes.withColumnRenamed("src", "a").join(other, "node").where("a < b").groupBy("a", "b").agg(F.count(F.lit(1)).alias("nodes"))

    def only(self, *sources: str) -> TripleGraph:
        return TripleGraph({k: v for k, v in self.parts.items() if k[0] in sources}, self.spark)


def from_testdata(spark: SparkSession, sf_dir: str, sources: Iterable[str] | None = None) -> TripleGraph:
    """Triples of the given tables, by source."""
    parts = {}
    for src in sources or SOURCES:
        for p, df in SOURCES[src](lambda name: _read(spark, sf_dir, name)).items():
            parts[src, p] = df
    return TripleGraph(parts, spark)


def from_triples(triples: DataFrame, src: str = "given") -> TripleGraph:
    """A graph of any ``(s, p, o[, src])`` rows."""
    if "src" not in triples.columns:
        triples = triples.withColumn("src", F.lit(src))
    return TripleGraph({(src, "*"): triples.select("s", "p", "o", "src")}, triples.sparkSession)


#: One line of N-Triples: identifiers in angle brackets, literals quoted with an optional language tag or type.
N_TRIPLE = r'^\s*<([^>]*)>\s+<([^>]*)>\s+(?:<([^>]*)>|"((?:[^"\\]|\\.)*+)"(?:@[A-Za-z0-9-]+|\^\^<[^>]*>)?)\s*\.\s*$'


def read_triples(spark: SparkSession, path: str, kind: str = "nt", src: str = "given") -> TripleGraph:
    """Reads ``nt`` (N-Triples; lines that are none are passed over), ``csv`` or ``json`` with columns s, p, o, or
    ``parquet``."""
    if kind == "nt":
        lines = spark.read.text(path).where(F.col("value").rlike(N_TRIPLE))
        get = lambda i: F.regexp_extract("value", N_TRIPLE, i)
        target = F.when(F.col("value").rlike(r"^\s*<[^>]*>\s+<[^>]*>\s+<"), get(3)).otherwise(literal(get(4)))
        rows = lines.select(get(1).alias("s"), get(2).alias("p"), target.alias("o"))
    elif kind == "csv":
        rows = spark.read.schema("s string, p string, o string").option("header", True).csv(path)
    elif kind == "json":
        rows = spark.read.schema("s string, p string, o string").json(path)
    elif kind == "parquet":
        rows = spark.read.parquet(path)
    else:
        raise ValueError(f"unknown kind {kind!r}")
    return from_triples(rows, src)


def construct(df: DataFrame, template: list[tuple[str, str, str]], src: str = "made") -> TripleGraph:
    """Triples from the rows of ``df``: each term of the template is ``?column`` or a constant."""
    term = lambda t: F.col(t[1:]) if t.startswith("?") else F.lit(t)
    made = F.array(*[F.struct(term(s).alias("s"), term(p).alias("p"), term(o).alias("o")) for s, p, o in template])
    return from_triples(df.select(F.inline(made)), src)


def write_layout(graph: TripleGraph, path: str, partitions: int = 32) -> None:
    """Adjacency on disk: one folder for each label and direction, rows sorted by node, so a lookup reads few row groups."""
    adj = graph.adjacency()
    adj.repartition(partitions, "p", "inv", F.pmod(F.xxhash64("node"), F.lit(4))).sortWithinPartitions("p", "inv", "node").write.partitionBy("p", "inv").option("parquet.bloom.filter.enabled#node", "true").mode("overwrite").parquet(path)


def write_buckets(graph: TripleGraph, name: str, buckets: int = 64) -> None:
    """Adjacency as a bucketed table: joins on ``node`` then move the frontier only."""
    graph.adjacency().write.bucketBy(buckets, "node").sortBy("node").mode("overwrite").saveAsTable(name)


def read_layout(spark: SparkSession, path: str, labels: Iterable[str] | None = None) -> DataFrame:
    out = spark.read.parquet(path).select("node", F.col("p").cast("string").alias("p"), F.col("inv").cast("boolean").alias("inv"), "nbr", "src")
    return out if labels is None else out.where(F.col("p").isin(sorted(labels)))
