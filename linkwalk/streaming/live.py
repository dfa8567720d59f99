"""Streams: triples that arrive over time, and rates of answers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.tables import drop, keep
from ..functions.terms import named
from ..operators.product import succeed
from ..plans.automaton import compile_path
from ..plans.expr import PathExpr

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """Event rows from a folder of Parquet files, as a stream."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def event_triples(events: DataFrame) -> DataFrame:
    """``(ts, s, p, o)`` of arriving events: who acted, and about what."""
    event = named("event", "event_id")
    rows = F.array(
        F.struct(event.alias("s"), F.lit("actor").alias("p"), named("user", "user_id").alias("o")),
        F.struct(event.alias("s"), F.lit("about").alias("p"), F.concat(F.lit("topic:"), F.get_json_object("props", "$.k")).alias("o")),
    )
    return events.select(F.col("ts").cast("timestamp").alias("ts"), F.inline(rows)).where("o is not null")


def distinct_triples(triples: DataFrame, lateness: str = "1 hour") -> DataFrame:
    """Drops repeats of a triple that arrive within the watermark; its state does not outgrow the lateness."""
    return triples.withWatermark("ts", lateness).dropDuplicatesWithinWatermark(["s", "p", "o"])


class LiveReach:
    """A reach set kept current while triples arrive. Triples are only added, so the set only grows: a new edge matters where
    it leaves a product node that is reached, and then search goes on from there over all edges so far."""

    def __init__(self, spark: SparkSession, expr: str | PathExpr, start: str):
        self.spark, self.automaton = spark, compile_path(expr)
        self.delta = self.automaton.delta(spark)
        self.adj = keep(spark.createDataFrame([], "node string, p string, inv boolean, nbr string"))
        self.seen = keep(spark.createDataFrame([(start, 0, 0)], "node string, q int, since int"))
        self.batches = 0

    def add(self, triples: DataFrame) -> None:
        """Takes a batch of ``(s, p, o)``; a batch that is given again changes nothing."""
        self.batches += 1
        labels = self.automaton.labels
        t = triples.select("s", "p", "o") if labels is None else triples.select("s", "p", "o").where(F.col("p").isin(sorted(labels)))
        ends = F.array(F.struct(F.col("s").alias("node"), F.lit(False).alias("inv"), F.col("o").alias("nbr")), F.struct(F.col("o").alias("node"), F.lit(True).alias("inv"), F.col("s").alias("nbr")))
        fresh = keep(t.distinct().select("p", F.inline(ends)).select("node", "p", "inv", "nbr").join(self.adj, ["node", "p", "inv", "nbr"], "left_anti"))
        whole = keep(self.adj.unionByName(fresh))
        drop(self.adj)
        self.adj = whole
        front = keep(self._new(self.seen.select("node", "q"), fresh))
        while not front.isEmpty():
            grown = keep(self.seen.unionByName(front.withColumn("since", F.lit(self.batches))))
            drop(self.seen)
            self.seen = grown
            front = keep(self._new(front, self.adj))

    def _new(self, front: DataFrame, adj: DataFrame) -> DataFrame:
        ahead = succeed(front, self.automaton, self.delta, adj).select(F.col("nbr").alias("node"), F.col("q2").alias("q")).distinct()
        return ahead.join(self.seen.select("node", "q"), ["node", "q"], "left_anti")

    def answers(self) -> DataFrame:
        """``(node, since)``: answers and the batch that first reached each."""
        return self.seen.where(F.col("q").isin(sorted(self.automaton.finals))).groupBy("node").agg(F.min("since").alias("since"))


def maintain_reach(triples: DataFrame, expr: str | PathExpr, start: str, checkpoint: str) -> LiveReach:
    """Runs a stream of triples through a :class:`LiveReach` until what is there now is read."""
    live = LiveReach(triples.sparkSession, expr, start)
    query = triples.writeStream.foreachBatch(lambda batch, _: live.add(batch)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return live


def answer_rate(trace: DataFrame, ts: str = "ts", width: str = "1 hour", slide: str | None = None, lateness: str = "10 minutes", by: str | None = None) -> DataFrame:
    """Rows per window, tumbling or sliding; on a stream rows later than the watermark are left out."""
    rows = trace.withWatermark(ts, lateness)
    window = F.window(ts, width, slide) if slide else F.window(ts, width)
    return rows.groupBy(window.alias("w"), *([by] if by else [])).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *([by] if by else []), "n")


def session_rate(trace: DataFrame, key: str, ts: str = "ts", gap: str = "30 minutes", lateness: str = "10 minutes") -> DataFrame:
    """Rows per session of a key: a session ends after a pause of ``gap``."""
    rows = trace.withWatermark(ts, lateness).groupBy(F.session_window(ts, gap).alias("w"), key).agg(F.count(F.lit(1)).alias("n"))
    return rows.select(key, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")
