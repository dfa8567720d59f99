"""Balanced label propagation: documents move towards their neighbours' shards under capacity quotas.

Neighbours are documents with equal texts. Large groups get their shards first, largest first, and are split only where no
shard holds them; the others start in order of group, within the room that is left. In each round a group's counts by shard are joined to its
members; members outside the shard with the most of their neighbours ask to move there, and each shard admits as many as it
has room for, by gain: the driver sees only counts by shard and gain class, and sets how many of each class go. Documents without
a neighbour cut no edge anywhere and are dealt last, so that all shards end within one document of each other.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .storage import cut, discard, with_uid

SHARDS = 24


def size_of(text: Column) -> Column:
    return F.coalesce(F.octet_length(text), F.lit(0)).cast("long") + 8


def _ranked(rows: DataFrame, keys: list[str], uid: str, n: int, name: str) -> DataFrame:
    """Gapless rank from 0 within ``keys``, by hash buckets and prefix sums: no window holds all rows of a key."""
    buckets = max(16, n // 20_000)
    tagged = rows.withColumn("bucket_", F.pmod(F.xxhash64(uid, F.lit(7)), F.lit(buckets)))
    sums = tagged.groupBy(*keys, "bucket_").agg(F.count(F.lit(1)).alias("n_"))
    prior = Window.partitionBy(*keys).orderBy("bucket_").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.withColumn("base_", F.coalesce(F.sum("n_").over(prior), F.lit(0))).drop("n_")
    inside = Window.partitionBy(*keys, "bucket_").orderBy(uid)
    return tagged.join(sums, [*keys, "bucket_"]).withColumn(name, (F.col("base_") + F.row_number().over(inside) - 1).cast("long")).drop("bucket_", "base_")


def reserve(sizes: list[tuple[str, int]], room: list[int]) -> list[tuple[str, int, int, int]]:
    """``(group, from, to, shard)`` for the given groups, largest first; ``room`` is lowered. A group goes whole to the fullest
    shard that holds it; one that no shard holds fills the emptiest shards, which is the least number of parts."""
    out = []
    for g, n in sorted(sizes, key=lambda x: (-x[1], x[0])):
        at = 0
        while at < n:
            fits = [s for s, r in enumerate(room) if r >= n - at]
            s = min(fits, key=lambda s: room[s]) if fits else max(range(len(room)), key=lambda s: room[s])
            take = min(n - at, room[s])
            out.append((g, at, at + take, s))
            room[s] -= take
            at += take
    return out


def _by_ends(rank: Column, ends: list[int]) -> Column:
    return F.size(F.filter(F.array(*[F.lit(e) for e in ends]), lambda e: e <= rank)).cast("int")


def place(linked: DataFrame, room: list[int], n: int) -> DataFrame:
    """``linked(uid, g, group_size)`` → ``(uid, g, shard)``; no shard gets more rows than its room.

    Groups of at least a twentieth of a shard are reserved their places by the driver; there are at most about twenty for each
    shard. The others propagate in the room that is left.
    """
    quota = max(room)
    large = linked.where(F.col("group_size") * 20 >= quota)
    sizes = [(r["g"], r["group_size"]) for r in large.select("g", "group_size").distinct().collect()]
    room = list(room)
    held = reserve(sizes, room)
    spark = linked.sparkSession
    places = F.broadcast(spark.createDataFrame(held, "g string, from_ long, to_ long, shard int"))
    ranked = _ranked(large.select("uid", "g"), ["g"], "uid", n, "rank_")
    fixed = ranked.join(places, "g").where("rank_ >= from_ and rank_ < to_").select("uid", "g", "shard")
    rest = linked.where(F.col("group_size") * 20 < quota).select("uid", "g")
    many = rest.count()
    return fixed.unionByName(propagate(rest, room, many)) if many else fixed


def propagate(linked: DataFrame, quotas: list[int], n: int, rounds: int = 24) -> DataFrame:
    """``linked(uid, g)`` of ``n`` rows → ``(uid, g, shard)``; no shard gets more rows than its quota."""
    shards, total = len(quotas), sum(quotas)
    # Rows start in order of group, dealt in proportion to the room: no start is overfull (n <= total), and few groups start cut.
    ends, before = [], 0
    for q in quotas:
        before += q
        ends.append(before * n // total)
    state = _ranked_range(linked, n).select("uid", "g", F.xxhash64("g").alias("sub"), _by_ends(F.col("rank_"), ends).alias("shard"))
    state = cut(state)
    for _ in range(rounds):
        load = {r["shard"]: r["n"] for r in state.groupBy("shard").agg(F.count(F.lit(1)).alias("n")).collect()}
        room = {s: quotas[s] - load.get(s, 0) for s in range(shards)}
        open_ = [s for s, r in room.items() if r > 0]
        if not open_:
            break
        votes = state.groupBy("sub", "shard").agg(F.count(F.lit(1)).alias("n"))
        pull = F.struct("n", F.xxhash64("sub", "shard").alias("tie"), F.col("shard").alias("to"))
        best = votes.groupBy("sub").agg(F.max(pull).alias("all"), F.max(F.when(F.col("shard").isin(open_), pull)).alias("open"))
        # Members leave for the best shard with room, unless the fullest one is their own.
        best = best.select("sub", F.col("all.to").alias("home"), F.col("open.to").alias("to"), F.col("open.n").alias("pull"))
        asked = state.join(best, "sub").withColumn("moves", (F.col("shard") != F.col("home")) & F.col("to").isNotNull() & (F.col("shard") != F.col("to")))
        asked = cut(asked.withColumn("gain", F.least(F.lit(40), F.floor(F.log2("pull") * 2)).cast("int")))
        wish = {(r["to"], r["gain"]): r["n"] for r in asked.where("moves").groupBy("to", "gain").agg(F.count(F.lit(1)).alias("n")).collect()}
        if not wish:
            discard(asked)
            break
        bars = []
        for s in open_:
            left = room[s]
            for gain in sorted((g for t, g in wish if t == s), reverse=True):
                bars.append((s, gain, min(wish[s, gain], left)))
                left -= bars[-1][2]
        bar = F.create_map(*[x for s, g, most in bars for x in (F.lit(s * 100 + g), F.lit(most))])
        movers = _ranked(asked.where("moves").select("uid", "to", "gain"), ["to", "gain"], "uid", sum(wish.values()), "rank_")
        admitted = movers.where(F.col("rank_") < F.element_at(bar, F.col("to") * 100 + F.col("gain"))).select("uid", F.col("to").alias("goes"))
        asked_all, asked = asked, asked.join(admitted, "uid", "left")
        after = cut(asked.select("uid", "g", "sub", F.coalesce("goes", "shard").alias("shard")))
        discard(asked_all)
        discard(state)
        state = after
    return state.select("uid", "g", "shard")


def shard_documents(docs: DataFrame, shards: int = SHARDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, size, text_crc32, law, shard, slot, grown_shard, group_size)`` under the law ``rows``.

    Counts of shards differ by one at most. A null text has size 8 and the checksum of the empty text, and no neighbour; an
    empty text is a text like any other. Rows with null or repeated ids are documents of their own. An empty table gives an
    empty one.
    """
    own = docs.select(F.col(f"`{id_col}`").alias("id"), F.col(f"`{text_col}`").alias("text"))
    source = with_uid(own, "id", "text")
    text = F.col("text")
    rows = cut(source.select("uid", "id", size_of(text).alias("size"), F.crc32(F.coalesce(text, F.lit("")).cast("binary")).alias("text_crc32"), F.when(text.isNotNull(), F.md5(text.cast("binary"))).alias("g")))
    n = rows.count()
    groups = rows.where("g is not null").groupBy("g").agg(F.count(F.lit(1)).alias("group_size")).where("group_size > 1")
    linked = cut(rows.join(groups, "g").select("uid", "g", "group_size"))
    quota = n // shards
    placed = cut(place(linked, [quota + (s < n % shards) for s in range(shards)], n))
    load = {r["shard"]: r["n"] for r in placed.groupBy("shard").agg(F.count(F.lit(1)).alias("n")).collect()}
    extra = sorted(range(shards), key=lambda s: (-load.get(s, 0), s))[: n % shards]
    need = [quota + (s in extra) - load.get(s, 0) for s in range(shards)]
    ends, total = [], 0
    for x in need:
        total += x
        ends.append(total)
    free = rows.select("uid").join(placed.select("uid"), "uid", "left_anti").withColumn("one_", F.lit(0))
    free = _ranked(free, ["one_"], "uid", n, "rank_")
    every = placed.select("uid", "shard").unionByName(free.select("uid", _by_ends(F.col("rank_"), ends).alias("shard")))
    slotted = _ranked(every, ["shard"], "uid", n, "slot")
    out = rows.join(slotted, "uid").join(linked.select("uid", "group_size"), "uid", "left")
    return out.select(F.col("id").alias(id_col), "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), F.coalesce("group_size", F.lit(1)).alias("group_size"))


def _ranked_range(linked: DataFrame, each: int) -> DataFrame:
    """Global rank in order of (g, uid), from counts by the first digits of g."""
    tagged = linked.withColumn("head_", F.substring("g", 1, 3))
    sums = tagged.groupBy("head_", "g").agg(F.count(F.lit(1)).alias("n_"))
    heads = sums.groupBy("head_").agg(F.sum("n_").alias("m_"))
    before = heads.withColumn("base_", F.coalesce(F.sum("m_").over(Window.orderBy("head_").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("m_")
    inner = Window.partitionBy("head_").orderBy("g").rowsBetween(Window.unboundedPreceding, -1)
    groups = sums.join(before, "head_").withColumn("at_", F.col("base_") + F.coalesce(F.sum("n_").over(inner), F.lit(0))).select("g", "at_")
    ranked = _ranked(linked, ["g"], "uid", each, "in_")
    return ranked.join(groups, "g").withColumn("rank_", F.col("at_") + F.col("in_"))
