"""Lookups: what asking for a node's document yields, and what it costs.

Every lookup gives ``edges()``, the adjacency rows that it can see, and ``cost(batch, matched)``, the requests and triples of
each expansion in a batch. For a client that keeps documents itself, ``rows()`` gives them with what each counts, and
``requests_for()`` the requests of one expansion. Literals are never looked up.
"""

from __future__ import annotations

from copy import copy
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.terms import jitter, jitter_of
from ..plans.automaton import Automaton
from ..sources.graph import TripleGraph

KEY = ["run", "node", "q"]


class Lookup:
    """Base: one request for each expansion, which returns the node's whole document."""

    #: Whether triples that a pattern brought count as transferred.
    pays_matches = False
    #: Whether whole documents travel, so that their sizes count.
    counts_documents = True

    def __init__(self, graph: TripleGraph):
        self.graph = graph
        #: What is stored once for all views of it, and the sources that this view is of (None: all).
        self.base: Lookup = self
        self.sources: frozenset[str] | None = None

    def among(self, *sources: str) -> Lookup:
        """A view: the same lookup over the triples of some sources. Who stores documents stores those of ``base``."""
        out = copy(self)
        out.graph, out.sources = self.graph.only(*sources), frozenset(sources)
        return out

    def visible(self, ends: DataFrame) -> DataFrame:
        """Of adjacency rows those that the lookup can see, with ``shown``: whether the document holds them."""
        return ends.where(self.shows()).withColumn("shown", F.lit(True))

    def shows(self) -> Column:
        """Whether a node's document holds an adjacency row."""
        return F.lit(True)

    def rows(self) -> DataFrame:
        """Visible adjacency rows of all labels, and ``shown``: whether the document holds them."""
        return self.visible(self.graph.adjacency())

    def requests_for(self, patterns: int) -> int:
        """Requests of one expansion out of a state with that many transitions."""
        return 1

    def edges(self, labels: set[str] | None) -> DataFrame:
        return self.graph.adjacency(labels)

    def documents(self) -> DataFrame:
        """Whole documents, for counting what a lookup transfers."""
        return self.edges(None)

    def sizes(self) -> DataFrame:
        """``(node, n_triples)`` of all documents."""
        return self.documents().groupBy("node").agg(F.count(F.lit(1)).alias("n_triples"))

    def cost(self, batch: DataFrame, matched: DataFrame, automaton: Automaton, sizes: DataFrame) -> DataFrame:
        """``(run, node, q, n_triples, requests)`` for each expansion in ``batch``; ``sizes`` as by :meth:`sizes`."""
        return batch.select(*KEY).join(sizes, "node", "left").select(*KEY, F.coalesce("n_triples", F.lit(0)).alias("n_triples"), F.lit(1).cast("long").alias("requests"))


class FullDocs(Lookup):
    """Ideal documents: all triples that mention the node."""


def kept_incoming(share: float) -> Column:
    """Whether an incoming triple is published, from a digest of the triple; ``share`` in 256ths. Columns: node, p, nbr."""
    return F.substring(F.md5(F.concat_ws("|", "nbr", "p", "node").cast("binary")), 1, 2) < f"{round(share * 256):02x}"


class PartialDocs(Lookup):
    """Documents that lack part of the incoming triples."""

    def __init__(self, graph: TripleGraph, keep_in: float = 0.5):
        super().__init__(graph)
        self.keep_in = keep_in

    def shows(self) -> Column:
        return F.lit(True) if self.keep_in >= 1 else ~F.col("inv") | kept_incoming(self.keep_in)

    def edges(self, labels: set[str] | None) -> DataFrame:
        return self.graph.adjacency(labels).where(self.shows())


def _asked(batch: DataFrame, automaton: Automaton) -> Column:
    """Number of patterns that an expansion asks for: one for each transition out of its state."""
    pairs = [x for q in range(automaton.size) for x in (F.lit(q), F.lit(len(automaton.outgoing(q))))]
    return F.element_at(F.create_map(*pairs), F.col("q")).cast("long")


class Endpoint(Lookup):
    """Pattern queries: only the wanted label and direction travel; one request for each pattern."""

    pays_matches, counts_documents = True, False

    def visible(self, ends: DataFrame) -> DataFrame:
        return ends.withColumn("shown", F.lit(False))

    def requests_for(self, patterns: int) -> int:
        return patterns

    def pattern(self, node: str, label: str, inv: bool) -> DataFrame:
        return self.graph.adjacency([label]).where((F.col("node") == node) & (F.col("inv") == inv))

    def cost(self, batch: DataFrame, matched: DataFrame, automaton: Automaton, sizes: DataFrame) -> DataFrame:
        got = matched.groupBy(*KEY).agg(F.count(F.lit(1)).alias("n_triples"))
        return batch.select(*KEY).join(got, KEY, "left").select(*KEY, F.coalesce("n_triples", F.lit(0)).alias("n_triples"), _asked(batch, automaton).alias("requests"))


class PatternPages(Endpoint):
    """Pattern queries answered in pages: a request for each page, one at least."""

    def __init__(self, graph: TripleGraph, page_size: int = 100):
        super().__init__(graph)
        self.page_size = page_size

    def requests_for(self, patterns: int) -> int:
        raise NotImplementedError("pages depend on what a pattern matches: use search.run_many")

    def pages(self, node: str, label: str, inv: bool) -> DataFrame:
        """``(page, nbr)`` of one pattern, in order of neighbour."""
        from pyspark.sql import Window

        rank = F.row_number().over(Window.partitionBy("node").orderBy("nbr")) - 1
        return self.pattern(node, label, inv).withColumn("page", F.floor(rank / self.page_size).cast("int")).select("page", "nbr")

    def cost(self, batch: DataFrame, matched: DataFrame, automaton: Automaton, sizes: DataFrame) -> DataFrame:
        by = matched.groupBy(*KEY, "t_rank").agg(F.count(F.lit(1)).alias("n"))
        got = by.groupBy(*KEY).agg(F.sum("n").alias("n_triples"), F.sum(F.greatest(F.ceil(F.col("n") / self.page_size), F.lit(1)) - 1).alias("more"))
        return batch.select(*KEY).join(got, KEY, "left").select(*KEY, F.coalesce("n_triples", F.lit(0)).alias("n_triples"), (_asked(batch, automaton) + F.coalesce("more", F.lit(0))).alias("requests"))


class Combined(Lookup):
    """A document and an endpoint asked together; both answers are used. ``count="pair"`` takes the two as one request,
    ``"each"`` counts the document and every pattern. Triples are counted from both: the document's, and what the patterns match."""

    pays_matches = True

    def __init__(self, docs: Lookup, endpoint: Endpoint, count: str = "pair"):
        super().__init__(docs.graph)
        self.docs, self.endpoint, self.count = docs, endpoint, count

    def edges(self, labels: set[str] | None) -> DataFrame:
        return self.docs.edges(labels).unionByName(self.endpoint.edges(labels)).dropDuplicates(["node", "p", "inv", "nbr"])

    def documents(self) -> DataFrame:
        return self.docs.documents()

    def among(self, *sources: str) -> Lookup:
        out = super().among(*sources)
        out.docs, out.endpoint = self.docs.among(*sources), self.endpoint.among(*sources)
        return out

    def visible(self, ends: DataFrame) -> DataFrame:
        return ends.withColumn("shown", self.docs.shows())

    def requests_for(self, patterns: int) -> int:
        return 1 if self.count == "pair" else 1 + patterns

    def cost(self, batch: DataFrame, matched: DataFrame, automaton: Automaton, sizes: DataFrame) -> DataFrame:
        got = matched.groupBy(*KEY).agg(F.count(F.lit(1)).alias("m_"))
        out = super().cost(batch, matched, automaton, sizes).join(got, KEY, "left")
        out = out.select(*KEY, (F.col("n_triples") + F.coalesce("m_", F.lit(0))).alias("n_triples"), "requests")
        return out if self.count == "pair" else out.withColumn("requests", F.col("requests") + _asked(batch, automaton))


class MultiSource(Lookup):
    """A node's triples live with several publishers; every one is asked."""

    def __init__(self, graph: TripleGraph, sources: list[str] | None = None):
        super().__init__(graph if sources is None else graph.only(*sources))
        self.asked = len(sources) if sources is not None else len({src for src, _ in graph.parts})

    def requests_for(self, patterns: int) -> int:
        return self.asked

    def cost(self, batch: DataFrame, matched: DataFrame, automaton: Automaton, sizes: DataFrame) -> DataFrame:
        return super().cost(batch, matched, automaton, sizes).withColumn("requests", F.lit(self.asked).cast("long"))


@dataclass(frozen=True)
class Latency:
    """Seconds that a lookup takes: the mean, spread evenly by ``spread`` around it, fixed by node and seed."""

    mean: float = 1.0
    spread: float = 0.5
    seed: int = 0

    def seconds(self) -> Column:
        return F.lit(self.mean) * (1 + self.spread * (2 * jitter("node", seed=self.seed) - 1))

    def of(self, node: str) -> float:
        """:meth:`seconds` of one node, without Spark."""
        return self.mean * (1 + self.spread * (2 * jitter_of(node, self.seed) - 1))
