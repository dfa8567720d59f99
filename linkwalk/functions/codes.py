"""Node codes: names as longs for large graphs, with a dictionary back to names; and names that are longs without one."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .tables import keep
from .terms import kind_of

KIND_BITS = 8

#: Kinds whose names of the form ``kind:number`` are one long: the kind's place above, the number in the lower bits.
NUMBERED = ("order", "part", "supplier", "customer", "nation", "region", "event", "user", "page", "doc", "item", "vec", "cluster", "quality")
_PLACES = {kind: i for i, kind in enumerate(NUMBERED)}
NUMBER_BITS = 55


def number_in(kind: str, key: str) -> Column:
    """The long of ``kind:key`` for a key column of a whole-number type; null for keys that have none."""
    n = F.col(key).cast("long")
    return F.when(n.between(0, (1 << NUMBER_BITS) - 1), n.bitwiseOR(F.lit(_PLACES[kind] << NUMBER_BITS)))


def number(node: str) -> Column:
    """The long of a name; null where it has none."""
    kind, digits = F.substring_index(node, ":", 1), F.substring_index(node, ":", -1)
    place = F.lit(None).cast("long")
    for known, i in reversed(_PLACES.items()):
        place = F.when(kind == known, F.lit(i).cast("long")).otherwise(place)
    # Only what a name gives back in full. Nothing else is cast: a cast that fails takes some 20 microseconds, also where it is tried.
    n = F.when(F.col(node).rlike(rf"^(?:{'|'.join(NUMBERED)}):(?:0|[1-9][0-9]{{0,16}})\z"), digits.cast("long"))
    return F.when(n < 1 << NUMBER_BITS, F.shiftleft(place, NUMBER_BITS).bitwiseOR(n))


def number_of(name: str) -> int | None:
    """:func:`number` of one name, without Spark."""
    kind, _, digits = name.partition(":")
    if kind not in _PLACES or not (digits.isascii() and digits.isdigit()) or len(digits) > 17 or (digits[0] == "0" and digits != "0"):
        return None
    n = int(digits)
    return None if n >> NUMBER_BITS else _PLACES[kind] << NUMBER_BITS | n


def name_of(code: int) -> str:
    return f"{NUMBERED[code >> NUMBER_BITS]}:{code & (1 << NUMBER_BITS) - 1}"


def in_name_order(codes: np.ndarray) -> np.ndarray:
    """Longs in the order of the names that they stand for: kinds as text up to the colon, then numbers as text, which is by their
    digits from the left, and the shorter first."""
    kinds, n = codes >> NUMBER_BITS, codes & (1 << NUMBER_BITS) - 1
    place = np.argsort(np.argsort(np.array([f"{kind}:" for kind in NUMBERED])))[kinds]
    tens = 10 ** np.arange(18, dtype=np.int64)
    digits = np.maximum(np.searchsorted(tens, n, "right"), 1)
    return codes[np.lexsort((digits, n * tens[17 - digits], place))]


def build_dictionary(adjacency: DataFrame, buckets: int = 64) -> DataFrame:
    """``(node, code)``: the kind's number in the top bits (at most 127 kinds), below it a gapless number within the kind.

    Numbers come from hash buckets and prefix sums over (kind, bucket), so no task numbers all nodes of a common kind.
    """
    nodes = adjacency.select("node").distinct().withColumn("kind", kind_of("node")).withColumn("b", F.pmod(F.xxhash64("node"), F.lit(buckets)))
    nodes = keep(nodes)
    kinds = sorted(r["kind"] for r in nodes.select("kind").distinct().limit(1 << (KIND_BITS - 1)).collect())
    if len(kinds) >= 1 << (KIND_BITS - 1):
        raise ValueError("too many kinds of node")
    number = F.element_at(F.create_map(*[x for i, k in enumerate(kinds) for x in (F.lit(k), F.lit(i).cast("long"))]), F.col("kind"))
    sums = nodes.groupBy("kind", "b").agg(F.count(F.lit(1)).alias("n"))
    prior = Window.partitionBy("kind").orderBy("b").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.withColumn("base", F.coalesce(F.sum("n").over(prior), F.lit(0))).drop("n")
    rank = F.col("base") + F.row_number().over(Window.partitionBy("kind", "b").orderBy("node")) - 1
    return nodes.join(sums, ["kind", "b"]).select("node", F.shiftleft(number, 64 - KIND_BITS - 1).bitwiseOR(rank).alias("code"))


def encode(adjacency: DataFrame, dictionary: DataFrame) -> DataFrame:
    """Adjacency with codes for both ends."""
    near = dictionary.select(F.col("node").alias("nbr"), F.col("code").alias("nbr_code"))
    return adjacency.join(dictionary, "node").join(near, "nbr").select(F.col("code").alias("node"), "p", "inv", F.col("nbr_code").alias("nbr"), "src")
