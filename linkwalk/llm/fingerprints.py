"""Order MinHash fingerprints. Built-in functions only.

A text is read as units: its words, where those of more than ``LONG`` code points (scripts without blanks, encoded data) give
all their overlapping runs of ``GRAM`` code points instead, so that nothing depends on how far a place is from the last blank.
Its k-mers are runs of ``KMER`` units, numbered by occurrence, so that repeats count. Each of ``SKETCHES`` random orders picks
the k-mers at its two ends, the least and the greatest of *all* k-mers; their hashes, in text order, make one tuple hash.
Moved or replaced text changes the picks or their order, so agreement of tuples follows edit distance, not only set likeness.

K-mers are unfolded into rows and the picks are plain minima and maxima of numbers that hold a k-mer's rank above and its place
below, so the work for all orders is one pass of hash aggregation, next to the text, without a shuffle.
"""

from __future__ import annotations

from math import isqrt

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .spans import let
from .storage import with_uid

LONG, GRAM, KMER, SKETCHES = 16, 8, 2, 32
#: Bits for the place of a k-mer; of texts with more k-mers than that, places are kept to the nearest power of two.
PLACE = 24


def units(text: Column) -> Column:
    words = F.regexp_extract_all(text, F.lit(r"\S+"), F.lit(0))
    grams = lambda w: F.regexp_extract_all(w, F.lit(r"(?s)(?=(.{%d}))" % GRAM), F.lit(1))
    cut = lambda ws: F.flatten(F.transform(ws, lambda w: F.when(F.length(w) <= LONG, F.array(w)).otherwise(grams(w))))
    return let(words, lambda ws: F.when(F.forall(ws, lambda w: F.length(w) <= LONG), ws).otherwise(cut(ws)))


def placed(u: Column) -> Column:
    """Longs: a k-mer's hash above, its place below; sorting brings equal k-mers together in text order. No unit gives one."""
    n = F.greatest(F.size(u) - KMER + 1, F.lit(1))
    coarse = F.greatest(F.lit(0), F.ceil(F.log2(n + 1)).cast("int") - PLACE)
    place = lambda i: F.floor(i / F.pow(F.lit(2.0), coarse)).cast("long")
    near = lambda i: F.when(n < 1 << PLACE, i.cast("long")).otherwise(place(i))
    return F.transform(F.sequence(F.lit(1), n), lambda i: F.shiftleft(F.shiftrightunsigned(F.xxhash64(*[F.get(u, i - 1 + j) for j in range(KMER)]), PLACE + 1), PLACE).bitwiseOR(near(i)))


def _kmer(x: Column) -> Column:
    return F.shiftright(x, PLACE)


def numbered(s: Column) -> Column:
    """The same longs, sorted, with the hash of (k-mer, number of equal ones before it) above the place."""
    heads = F.filter(F.sequence(F.lit(0), F.size(s) - 1), lambda i: (i == 0) | (_kmer(F.get(s, i)) != _kmer(F.get(s, F.greatest(i - 1, F.lit(0))))))
    again = lambda x, o: F.shiftleft(F.shiftrightunsigned(F.xxhash64(_kmer(x), o), PLACE + 1), PLACE).bitwiseOR(x.bitwiseAND(F.lit((1 << PLACE) - 1)))
    runs = lambda h: F.flatten(F.transform(h, lambda a, j: F.transform(F.slice(s, a + 1, F.coalesce(F.get(h, j + 1), F.size(s)) - a), again)))
    # Without repeats every k-mer is occurrence 0 and no run need be cut out.
    return let(heads, lambda h: F.when(F.size(h) == F.size(s), F.transform(s, lambda x: again(x, F.lit(0)))).otherwise(runs(h)))


def sketched(texts: DataFrame, keys: list[str], text_col: str) -> DataFrame:
    """``keys`` and ``fp`` of each row: ``SKETCHES`` numbers of 8 hexadecimal digits, joined by commas. ``keys`` name a row; where
    the table is dealt out by some of them, nothing moves. Null counts as empty; texts without a unit share one fingerprint."""
    rows = texts.select(*keys, units(F.coalesce(F.col(text_col), F.lit(""))).alias("u_"))
    rows = rows.select(*keys, F.sort_array(placed(F.col("u_"))).alias("s_"))
    rows = rows.select(*keys, F.explode(numbered(F.col("s_"))).alias("x_"))
    kmer, at = _kmer(F.col("x_")), F.col("x_").bitwiseAND(F.lit((1 << PLACE) - 1))
    rank = lambda j: F.shiftleft(F.shiftright(F.xxhash64(kmer, F.lit(j)), PLACE), PLACE).bitwiseOR(at)
    ends = rows.groupBy(*keys).agg(*[f(rank(j)).alias(f"{name}{j}") for j in range(SKETCHES) for name, f in (("a", F.min), ("z", F.max))])

    def pick(j: int) -> Column:
        a, z = F.col(f"a{j}"), F.col(f"z{j}")
        where = lambda x: x.bitwiseAND(F.lit((1 << PLACE) - 1))
        h = F.when(where(a) <= where(z), F.xxhash64(F.lit(j), _kmer(a), _kmer(z))).otherwise(F.xxhash64(F.lit(j), _kmer(z), _kmer(a), F.lit(1)))
        return F.substring(F.lower(F.lpad(F.hex(h), 16, "0")), 1, 8)

    return ends.select(*keys, F.concat_ws(",", *[pick(j) for j in range(SKETCHES)]).alias("fp"))


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id, fingerprint)`` of every row. Null counts as empty; null and repeated ids are rows of their own; an empty table
    gives an empty one."""
    own = docs.select(F.col(f"`{id_col}`").alias("id"), F.col(f"`{text_col}`").alias("text"))
    return sketched(with_uid(own, "id", "text"), ["uid", "id"], "text").select(F.col("id").alias(id_col), F.col("fp").alias("fingerprint"))


def likeness(a: Column, b: Column) -> Column:
    """Share of equal tuples of two fingerprints."""
    both = F.zip_with(F.split(a, ","), F.split(b, ","), lambda x, y: (x == y).cast("int"))
    return F.aggregate(both, F.lit(0), lambda s, x: s + x) / F.lit(float(SKETCHES))


def in_ranges(rows: DataFrame, uid: str) -> DataFrame:
    """Rows with ``range_``, their place among ranges of about 2,000 rows (of a fifty-thousandth of the table, where that is more),
    and ``copy_``: each range also gets a copy of the first row of the range after it (the last: of the first of all), so no
    window need span the table. Only the ranges' bounds and first ids reach the driver."""
    n = rows.select(F.count(F.lit(1)).alias("n")).first()["n"]
    k = max(1, min(50_000, n // 2000))
    cuts = rows.agg(F.percentile_approx(uid, [i / k for i in range(1, k)], min(20 * k, 200_000)).alias("q")).first()["q"] if k > 1 else []
    cuts = sorted(set(cuts))
    # Bounds in two levels: about the square root of their number is looked at, twice.
    step = isqrt(len(cuts)) + 1
    lists = [cuts[i : i + step] for i in range(0, len(cuts), step)]
    below = lambda bounds: F.size(F.filter(bounds, lambda b: b < F.col(uid)))
    if lists:
        tops = below(F.array(*[F.lit(x[-1]) for x in lists]).cast("array<bigint>"))
        nested = F.array(*[F.array(*[F.lit(b) for b in x]).cast("array<bigint>") for x in lists])
        place = tops * step + F.coalesce(below(F.get(nested, tops)), F.lit(0))
    else:
        place = F.lit(0)
    firsts = [tuple(r) for r in rows.groupBy(place.alias("r")).agg(F.min(uid).alias("u")).orderBy("r").collect()]
    after = [(u, firsts[i - 1][0]) for i, (_, u) in enumerate(firsts)]
    seam = rows.sparkSession.createDataFrame(after, f"{uid} long, range_ int")
    own = rows.select("*", place.alias("range_"), F.lit(False).alias("copy_"))
    return own.unionByName(rows.join(F.broadcast(seam), uid).withColumn("copy_", F.lit(True)))


def edit_probe(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per document its fingerprint, that of its edited text (the last quarter replaced by the start of the next document's
    text), and the likeness of its own to that and to the next document's.

    Null counts as empty. "Next" follows the id; null ids come last, and rows of one id follow each other by text hash. A
    table of one row is its own next. An empty table gives an empty one.
    """
    own = docs.select(F.col(f"`{id_col}`").alias("id"), F.coalesce(F.col(f"`{text_col}`"), F.lit("")).alias("text"))
    rows = with_uid(own, "id", "text")
    # Texts move once, to their range; all that follows stays there.
    after = Window.partitionBy("range_").orderBy("copy_", "uid")
    led = in_ranges(rows, "uid").withColumn("next", F.lead("text").over(after))
    n = F.length("text")
    tail = F.floor(n / 4).cast("int")
    edited = F.concat(F.substr("text", F.lit(1), n - tail), F.substr("next", F.lit(1), tail))
    both = led.select("range_", "copy_", "uid", "id", n.cast("long").alias("n_chars"), F.col("text"), edited.alias("edited"))
    both = both.withColumn("edited_sha256", F.sha2(F.col("edited").cast("binary"), 256))
    pair = F.posexplode(F.array("text", "edited")).alias("kind", "probe")
    keys = ["range_", "copy_", "uid", "id", "n_chars", "edited_sha256", "kind"]
    fp = sketched(both.select(*keys[:-1], pair), keys, "probe")
    order = Window.partitionBy("range_").orderBy("copy_", "uid", "kind")
    out = fp.withColumns({"edited_fingerprint": F.lead("fp", 1).over(order), "next_fp": F.lead("fp", 2).over(order)}).where((F.col("kind") == 0) & ~F.col("copy_"))
    out = out.withColumnRenamed("fp", "fingerprint")
    return out.select(F.col("id").alias(id_col), "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", likeness(F.col("fingerprint"), F.col("edited_fingerprint")).alias("near_edited"), likeness(F.col("fingerprint"), F.col("next_fp")).alias("near_next"))
