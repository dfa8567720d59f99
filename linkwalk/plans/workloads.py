"""The experiment workloads on the given tables."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from ..operators.product import reach
from ..sources.graph import TripleGraph, from_testdata
from .twins import reach_sql


@dataclass(frozen=True)
class Workload:
    """One path query: its expression, start, sources and a cap on answer lengths for the SQL twin."""

    id: str
    key: str
    expr: str
    start: str
    sources: tuple[str, ...]
    cap: int
    in_grid: bool = False

    def graph(self, spark: SparkSession, sf_dir: str) -> TripleGraph:
        return from_testdata(spark, sf_dir, self.sources)

    def exact(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        return reach(self.graph(spark, sf_dir), self.expr, self.start)

    def sql(self) -> str:
        return reach_sql(self.expr, self.sources, self.start, self.cap)


_COLLAB = "((^placed_by/(contains/^contains)*/placed_by)|same_as|^same_as)*"
WORKLOADS: dict[str, Workload] = {
    w.key: w
    for w in (
        Workload("W1", "reach_coorder", "(^contains/contains)*", "part:0", ("supply",), 8, True),
        Workload("W1L", "reach_coorder_names", "(^contains/contains)*/label", "part:0", ("supply", "catalog"), 9, True),
        Workload("W2", "reach_orders", "(^contains/contains)*/^contains", "part:0", ("supply",), 9, True),
        Workload("W2D", "reach_order_dates", "(^contains/contains)*/^contains/dated", "part:0", ("supply", "sales"), 10),
        Workload("W3", "region_trade", "^in_region/^in_nation/(^placed_by|^filled_by)", "region:3", ("geo", "sales", "supply"), 6),
        Workload("W3S", "region_trade_star", "^in_region/^in_nation/(^placed_by|^filled_by)/(contains/^contains)*", "region:3", ("geo", "sales", "supply"), 8, True),
        Workload("W4", "collab_multi_source", _COLLAB, "user:8", ("sales", "supply", "clicks"), 14, True),
        Workload("W5", "coorder_fixed", "^contains/contains", "part:0", ("supply",), 3, True),
        Workload("W6", "coorder_names_fixed", "^contains/contains/label", "part:0", ("supply", "catalog"), 4, True),
        Workload("W7", "customer_reach", "(^placed_by/contains/^contains/placed_by)*", "customer:0", ("sales", "supply"), 16, True),
        Workload("W7N", "customer_reach_names", "(^placed_by/contains/^contains/placed_by)*/name", "customer:0", ("sales", "supply"), 17),
        Workload("W8", "topic_reach", "(^actor/about/^about/actor)*", "user:8", ("clicks",), 12, True),
        Workload("W9", "event_chain", "followed_by*", "event:0", ("clicks",), 400, True),
        Workload("W9D", "dialog_chain", "next*", "turn:0-0", ("dialog",), 20),
        Workload("W10", "page_hosts", "(anchors/^anchors)*/on_host", "page:0", ("web",), 21, True),
        Workload("W11", "multi_star_optional", "(^supplies/supplies)*/^supplies/in_nation/(^in_nation/in_nation)*/in_region?", "part:0", ("supply", "geo"), 10, True),
        Workload("W12", "plus_closure", "(^contains/contains)+", "part:0", ("supply",), 8),
        Workload("W12N", "negated_set", "^contains/!(contains|^contains)", "part:0", ("supply", "sales"), 8),
        Workload("W13", "copy_langs", "(copy_of|^copy_of)*/in_lang", "doc:170", ("corpus",), 8),
        Workload("W13Q", "quote_langs", "^quotes/in_lang", "item:11", ("corpus",), 8),
        Workload("W14", "similar_clusters", "near+/cluster", "vec:0", ("vectors",), 14),
        Workload("W14N", "similar_reach", "near+", "vec:0", ("vectors",), 14),
    )
}
#: The eleven that stand for the experiment's query set.
GRID = [w for w in WORKLOADS.values() if w.in_grid and w.key != "reach_coorder_names"]
