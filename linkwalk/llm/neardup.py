"""MinHash near-duplicates: banded candidates, sequential Bayesian pruning on signature batches, exact verification.

1. One pass gives each text its distinct five-word shingles (as 64-bit hashes), a signature and band keys. Texts with equal
   word sequences become one *representative*; only representatives go on.
2. Members of a band bucket are first tried against the bucket's least representative (a star, linear in the bucket).
   Survivors of the Bayesian test are verified on full shingle sets, and verified links give components.
3. Buckets that still hold several components are dealt out in bounded cells, in which only pairs of different components
   are compared, the most frequent component never with itself. In every cell, signatures are compared in batches, and the
   sequential test prunes pairs as in 2. Survivors of small buckets are joined to their shingle sets and verified there. Cells
   of buckets above ``HOT`` members hold the sets, so survivors are verified in place, each member against those that no link
   found so far joins to it; only a spanning forest of links leaves the cell, so that a large group of copies never turns into
   a list of pairs. No pair between different components is skipped, and no cell outgrows a task.

The Bayesian test follows sequential pruning under a uniform prior: after each batch of ``BATCH`` hash agreements, a pair
is dropped once the posterior chance that its similarity reaches the threshold falls below ``miss``.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import connected_components
from .storage import cut, discard, names_out, with_uid
from .words import LOWER, Hasher, chunks, find_words, kept_by_worker, mix, texts

BANDS, ROWS, BATCH = 25, 5, 25
HASHES = BANDS * ROWS
#: Members above which a bucket is hot, and shingles and members that one side of a cell of a hot bucket holds.
HOT, ROOM, SIDE = 64, 150_000, 1024


def _hashers() -> tuple[Hasher, Hasher, np.ndarray, np.ndarray]:
    return kept_by_worker("neardup", _made)


def _made() -> tuple[Hasher, Hasher, np.ndarray, np.ndarray]:
    r = np.random.default_rng(8)
    return Hasher(81), Hasher(82), r.integers(0, 1 << 31, HASHES, dtype=np.uint32) * np.uint32(2) + np.uint32(1), r.integers(0, 1 << 32, HASHES, dtype=np.uint64).astype(np.uint32)


def shingle_sets(column, width: int) -> Iterator[tuple[int, int, int, np.ndarray]]:
    """For each row: two 64-bit hashes of its word sequence, and its sorted distinct shingle hashes."""
    one, two, *_ = _hashers()
    flat, offsets = texts(column)
    for lo, hi in chunks(offsets):
        b = LOWER[flat[offsets[lo] : offsets[hi]]]
        starts, ends, first = find_words(b, offsets[lo : hi + 1] - offsets[lo])
        h = one.words(b, starts, ends)
        sums, again = one.prefix(h), two.prefix(h)
        n = len(h)
        at = np.arange(max(0, n - width + 1))
        grams = one.run(sums, at, at + width)
        whole, other = one.run(sums, first[:-1], first[1:]), two.run(again, first[:-1], first[1:])
        for d in range(hi - lo):
            a, z = int(first[d]), int(first[d + 1])
            if z - a >= width:
                own = np.unique(grams[a : z - width + 1])
            else:
                own = whole[d : d + 1] if z > a else whole[:0]
            yield lo + d, int(whole[d].view(np.int64)), int(other[d].view(np.int64)), own


def signature(own: np.ndarray) -> np.ndarray:
    """Minima of ``HASHES`` affine maps of the shingle hashes modulo 2**32."""
    *_, a, c = _hashers()
    h = (own >> np.uint64(32)).astype(np.uint32) ^ own.astype(np.uint32)
    out = np.full(HASHES, 0xFFFFFFFF, np.uint32)
    for lo in range(0, len(h), 2048):
        np.minimum(out, (h[None, lo : lo + 2048] * a[:, None] + c[:, None]).min(axis=1), out=out)
    return out


def band_keys(sig: np.ndarray) -> np.ndarray:
    key = np.arange(1, BANDS + 1, dtype=np.uint64)
    for col in sig.reshape(BANDS, ROWS).T:
        key = mix(key ^ (col.astype(np.uint64) + (key << np.uint64(7))))
    return key.view(np.int64)


def sketch(docs: DataFrame, id_col: str, text_col: str, width: int) -> DataFrame:
    """``(uid, k1, k2, n_shingles, sig, bands)``; texts without words have no bands."""
    schema = pa.schema([("uid", pa.int64()), ("k1", pa.int64()), ("k2", pa.int64()), ("n_shingles", pa.int64()), ("sig", pa.binary()), ("bands", pa.list_(pa.int64()))])

    def run(batches):
        for batch in batches:
            k1, k2, n, sigs, bands = [], [], [], [], []
            for _, x, y, own in shingle_sets(batch.column(1), width):
                k1.append(x)
                k2.append(y)
                n.append(len(own))
                sig = signature(own) if len(own) else None
                sigs.append(None if sig is None else sig.tobytes())
                bands.append(None if sig is None else band_keys(sig))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(k1, pa.int64()), pa.array(k2, pa.int64()), pa.array(n, pa.int64()), pa.array(sigs, pa.binary()), pa.array(bands, pa.list_(pa.int64()))], schema=schema)

    return docs.select(F.col(id_col).alias("uid"), F.col(text_col).alias("text")).mapInArrow(run, "uid long, k1 long, k2 long, n_shingles long, sig binary, bands array<long>")


def needed_matches(threshold: float, miss: float) -> tuple[int, ...]:
    """After 1, 2, ... batches: the fewest agreements with which a pair goes on."""
    s = (np.arange(4000) + 0.5) / 4000
    out = []
    for n in range(BATCH, HASHES + 1, BATCH):
        for m in range(n + 1):
            logs = m * np.log(s) + (n - m) * np.log1p(-s)
            p = np.exp(logs - logs.max())
            if p[s >= threshold].sum() / p.sum() >= miss:
                out.append(m)
                break
    return tuple(out)


def _survive(a: np.ndarray, b: np.ndarray, needed: tuple[int, ...]) -> np.ndarray:
    """Rows of ``a`` and ``b`` (signatures side by side) that no batch prunes."""
    alive, got = np.arange(len(a)), np.zeros(len(a), np.int32)
    for k, least in enumerate(needed):
        part = slice(k * BATCH, (k + 1) * BATCH)
        got = got + (a[alive, part] == b[alive, part]).sum(axis=1)
        keep = got >= least
        alive, got = alive[keep], got[keep]
    return alive


def _sigs(column) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.uint32).reshape(-1, HASHES)


def prune(pairs: DataFrame, reps: DataFrame, threshold: float, miss: float) -> DataFrame:
    """Pairs ``(a, b)`` that the sequential test lets pass."""
    needed = needed_matches(threshold, miss)

    def run(batches):
        for batch in batches:
            for lo in range(0, batch.num_rows, 4096):
                part = batch.slice(lo, 4096)
                alive = _survive(_sigs(part.column(2)), _sigs(part.column(3)), needed)
                yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(alive)), part.column(1).take(pa.array(alive))], names=["a", "b"])

    of = lambda x: reps.select(F.col("rid").alias(x), F.col("sig").alias(f"sig_{x}"))
    return pairs.join(of("a"), "a").join(of("b"), "b").select("a", "b", "sig_a", "sig_b").mapInArrow(run, "a long, b long")


def _sets(wanted: DataFrame, docs: DataFrame, text_col: str, width: int) -> DataFrame:
    """``(rid, own)``: full shingle sets of the representatives ``wanted(rid, uid)``, made anew from their texts."""
    schema = pa.schema([("rid", pa.int64()), ("own", pa.binary())])

    def sets(batches):
        for batch in batches:
            own = [x[3].tobytes() for x in shingle_sets(batch.column(1), width)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(own, pa.binary())], schema=schema)

    return docs.select("uid", F.col(text_col).alias("text")).join(wanted, "uid").select("rid", "text").mapInArrow(sets, "rid long, own binary")


def verify(pairs: DataFrame, reps: DataFrame, docs: DataFrame, text_col: str, width: int, percent: int) -> DataFrame:
    """Pairs ``(a, b)`` of representatives whose full shingle sets reach the similarity; sets are made only for the
    representatives that occur in ``pairs``."""
    wanted = pairs.select(F.explode(F.array("a", "b")).alias("rid")).distinct().join(reps.select("rid", "uid"), "rid")

    def run(batches):
        for batch in batches:
            keep = []
            for i, (x, y) in enumerate(zip(batch.column(2), batch.column(3), strict=True)):
                a, b = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                if 100 * min(len(a), len(b)) >= percent * max(len(a), len(b)):
                    common = len(a) + len(b) - len(np.union1d(a, b))
                    if 100 * common >= percent * (len(a) + len(b) - common):
                        keep.append(i)
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(keep, pa.int64())), batch.column(1).take(pa.array(keep, pa.int64()))], names=["a", "b"])

    sets_table = cut(_sets(wanted, docs, text_col, width))
    of = lambda x: sets_table.select(F.col("rid").alias(x), F.col("own").alias(f"own_{x}"))
    links = cut(pairs.join(of("a"), "a").join(of("b"), "b").select("a", "b", "own_a", "own_b").mapInArrow(run, "a long, b long"))
    discard(sets_table)
    return links


def _stars(buckets: DataFrame) -> DataFrame:
    heads = buckets.groupBy("band").agg(F.min("rid").alias("a"), F.count(F.lit(1)).alias("n")).where("n > 1").select("band", "a")
    return buckets.join(heads, "band").where("rid <> a").select("a", F.col("rid").alias("b")).distinct()


def _open_buckets(buckets: DataFrame, labels: DataFrame) -> DataFrame:
    """``(band, rid, comp, main, n, k, k2)``: members of the buckets that hold several components; ``main`` is the most
    frequent one, ``k`` and ``k2`` the numbers of cells that all members and the others need to stay near ``ROOM`` and ``SIDE``."""
    named = buckets.join(labels, buckets["rid"] == labels["node"], "left").select("band", "rid", "size", F.coalesce("component", "rid").alias("comp"))
    sizes = named.groupBy("band", "comp").agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("size"))
    open_ = sizes.groupBy("band").agg(F.sum("n").alias("n"), F.sum("size").alias("size"), F.max(F.struct("n", "comp", "size")).alias("most"), F.count(F.lit(1)).alias("kinds")).where("kinds > 1")
    cells = lambda c, n: F.when(F.col("n") > HOT, F.greatest(F.ceil(c / ROOM), F.ceil(n / SIDE))).otherwise(1).cast("int")
    rest = cells(F.col("size") - F.col("most.size"), F.col("n") - F.col("most.n"))
    open_ = open_.select("band", "n", F.col("most.comp").alias("main"), cells(F.col("size"), F.col("n")).alias("k"), rest.alias("k2"))
    return named.drop("size").join(open_, "band")


def _dealt(members: DataFrame) -> DataFrame:
    """Members dealt to cells: every member that is not of the main component meets every member in exactly one cell."""
    rows = members.withColumn("other", F.col("comp") != F.col("main"))
    right = rows.select("band", F.explode(F.sequence(F.lit(0), F.col("k2") - 1)).alias("i"), F.pmod(F.xxhash64("rid"), "k").cast("int").alias("j"), "rid", "comp", "other", F.lit(False).alias("left"))
    left = rows.where("other").select("band", F.pmod(F.xxhash64("rid", F.lit(1)), "k2").cast("int").alias("i"), F.explode(F.sequence(F.lit(0), F.col("k") - 1)).alias("j"), "rid", "comp", "other", F.lit(True).alias("left"))
    return left.unionByName(right).withColumn("cell", F.xxhash64("band", "i", "j"))


def _runs(compare):
    """Reads batches sorted by (cell, band) and calls ``compare`` on each cell as a table."""

    def run(batches):
        held = []
        for batch in batches:
            if not batch.num_rows:
                continue
            ids, bands = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            edges = [0, *(np.flatnonzero((ids[1:] != ids[:-1]) | (bands[1:] != bands[:-1])) + 1).tolist(), len(ids)]
            for lo, hi in zip(edges, edges[1:], strict=False):
                part = batch.slice(lo, hi - lo)
                if held and (held[0].column(0)[0], held[0].column(1)[0]) != (part.column(0)[0], part.column(1)[0]):
                    yield from compare(pa.Table.from_batches(held))
                    held = []
                held.append(part)
        if held:
            yield from compare(pa.Table.from_batches(held))

    return run


def common_counts(one: np.ndarray, others: list[np.ndarray]) -> np.ndarray:
    """Sizes of the intersections of one sorted set with each of the others."""
    flat = np.concatenate(others)
    at = np.minimum(np.searchsorted(one, flat), len(one) - 1)
    return np.bincount(np.repeat(np.arange(len(others)), [len(v) for v in others])[one[at] == flat], minlength=len(others))


def forest(sets: list[np.ndarray], comp: np.ndarray, x: np.ndarray, y: np.ndarray, needed: tuple[int, ...], percent: int) -> list[tuple[int, int]]:
    """Links between members ``x`` and ``y`` that join their components ``comp``, found by the sequential test on signatures and
    verified on full sets: a spanning forest of all links between different components."""
    sigs = np.stack([signature(v) for v in sets])
    size = np.array([len(v) for v in sets])
    label, out = comp.copy(), []
    for i in x.tolist():
        js = y[label[y] != label[i]]
        js = js[100 * np.minimum(size[js], size[i]) >= percent * np.maximum(size[js], size[i])]
        js = js[_survive(np.broadcast_to(sigs[i], (len(js), HASHES)), sigs[js], needed)]
        if not len(js):
            continue
        common = common_counts(sets[i], [sets[j] for j in js])
        for j in js[100 * common >= percent * (size[i] + size[js] - common)].tolist():
            if label[j] != label[i]:
                out.append((i, j))
                label[label == label[j]] = label[i]
    return out


def _hot_links(members: DataFrame, reps: DataFrame, docs: DataFrame, text_col: str, width: int, percent: int, threshold: float, miss: float) -> DataFrame:
    """Links ``(a, b)`` between different components in large buckets: a spanning forest of those in each cell."""
    needed = needed_matches(threshold, miss)
    wanted = members.select("rid").distinct().join(reps.select("rid", "uid"), "rid")
    cells = _dealt(members).join(_sets(wanted, docs, text_col, width), "rid").select("cell", "band", "rid", "comp", "left", "own")
    cells = cells.repartition("cell").sortWithinPartitions("cell", "band")

    def compare(cell: pa.Table):
        rid, comp, left = (cell.column(c).to_numpy() for c in ("rid", "comp", "left"))
        x, y = np.flatnonzero(left), np.flatnonzero(~left)
        if len(x) and len(y):
            own = [np.frombuffer(v, np.uint64) for v in cell.column("own").to_pylist()]
            out = [(int(rid[i]), int(rid[j])) for i, j in forest(own, comp, x, y, needed, percent)]
            if out:
                yield pa.RecordBatch.from_arrays([pa.array([min(e) for e in out]), pa.array([max(e) for e in out])], names=["a", "b"])

    return cells.mapInArrow(_runs(compare), "a long, b long")


def _cells(members: DataFrame, reps: DataFrame, threshold: float, miss: float) -> DataFrame:
    """Pairs of different components that share a small bucket and survive pruning."""
    needed = needed_matches(threshold, miss)
    cells = _dealt(members).join(reps.select("rid", "sig"), "rid").select("cell", "band", "rid", "comp", "other", "left", "sig")
    cells = cells.repartition("cell").sortWithinPartitions("cell", "band")
    names = ["a", "b"]

    def compare(cell: pa.Table):
        rid, comp, other, left = (cell.column(c).to_numpy() for c in ("rid", "comp", "other", "left"))
        x, y = np.flatnonzero(left), np.flatnonzero(~left)
        if not len(x) or not len(y):
            return
        sig, band = _sigs(cell.column("sig")), cell.column("band")[0].as_py()
        keys = np.stack([band_keys(s) for s in sig])
        mine = int(np.flatnonzero((keys == band).any(axis=0))[0])
        for lo in range(0, len(x), 64):
            p, q = np.meshgrid(x[lo : lo + 64], y, indexing="ij")
            p, q = p.ravel(), q.ravel()
            ok = (comp[p] != comp[q]) & (~other[q] | (rid[p] < rid[q]))
            p, q = p[ok], q[ok]
            # A pair belongs to the first bucket that it shares.
            for t in range(mine):
                ok = keys[p, t] != keys[q, t]
                p, q = p[ok], q[ok]
            alive = _survive(sig[p], sig[q], needed)
            p, q = rid[p[alive]], rid[q[alive]]
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(p, q)), pa.array(np.maximum(p, q))], names=names)

    return cells.mapInArrow(_runs(compare), "a long, b long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, percent: int = 80, miss: float = 1e-5) -> DataFrame:
    """Input columns plus ``n_shingles``, ``component_id`` (least id reachable over links) and ``kept``.

    Two documents are linked when 100 * |A and B| >= percent * |A or B| for their sets of ``width``-word shingles (ASCII
    lower case); a shorter text has its whole word sequence as its one shingle. Null, empty and white-space texts have no
    shingle and no link, not even with each other. Rows with null or repeated ids are rows of their own; a component's id is
    the least non-null id in it (null if it has none), and ``kept`` marks its first row. An empty table gives an empty one. Input
    columns with the name of an added one come back with ``_in`` appended.
    ``miss`` is the posterior bound under which a candidate is dropped; the bands miss a pair at 0.85 with chance 4e-7, at
    0.80 with chance 5e-5.
    """
    threshold = percent / 100
    given = docs.columns
    own = docs.select(*[F.col(f"`{c}`").alias(f"in_{i}") for i, c in enumerate(given)])
    id_at, text_at = f"in_{given.index(id_col)}", f"in_{given.index(text_col)}"
    source = with_uid(own, id_at, text_at)
    base = cut(sketch(source, "uid", text_at, width))
    reps = base.where("bands is not null").groupBy("k1", "k2").agg(F.min("uid").alias("uid"), F.first("sig").alias("sig"), F.first("bands").alias("bands"), F.first("n_shingles").alias("size"))
    reps = cut(reps.withColumn("rid", F.col("uid")))
    buckets = cut(reps.select("rid", "size", F.explode("bands").alias("band")))
    stars = cut(_stars(buckets))
    tried = cut(prune(stars, reps, threshold, miss))
    links = verify(tried, reps, source, text_at, width, percent)
    labels = cut(connected_components(links.select(F.col("a").alias("u"), F.col("b").alias("v"))))
    members = cut(_open_buckets(buckets, labels))
    for table in (buckets, stars):
        discard(table)
    hot = cut(_hot_links(members.where(F.col("n") > HOT), reps, source, text_at, width, percent, threshold, miss))
    more = cut(_cells(members.where(F.col("n") <= HOT), reps, threshold, miss).join(tried, ["a", "b"], "left_anti"))
    rest = verify(more, reps, source, text_at, width, percent)
    if not (hot.isEmpty() and rest.isEmpty()):
        every = links.unionByName(rest).unionByName(hot)
        discard(labels)
        labels = cut(connected_components(every.select(F.col("a").alias("u"), F.col("b").alias("v"))))
    for table in (tried, members, hot, more, links, rest):
        discard(table)
    least = reps.select("k1", "k2", "rid").join(labels, F.col("rid") == F.col("node"), "left").select("k1", "k2", F.coalesce("component", "rid").alias("head"))
    members = base.select("uid", "k1", "k2", "n_shingles").join(least, ["k1", "k2"], "left")
    # uid sorts as the id does, so the component's least uid is the row of its least id.
    members = members.select("uid", "n_shingles", F.when(F.col("n_shingles") > 0, F.col("head")).otherwise(F.col("uid")).alias("head"))
    ids = source.select(F.col("uid").alias("head"), F.col(id_at).alias("component_id"))
    members = members.join(ids, "head").select("uid", "n_shingles", "component_id", (F.col("uid") == F.col("head")).alias("kept"))
    out = source.join(members, "uid")
    names = names_out(given, ["n_shingles", "component_id", "kept"])
    return out.select(*[F.col(f"in_{i}").alias(c) for i, c in enumerate(names)], "n_shingles", "component_id", "kept")


def miss_chance(similarity: float) -> float:
    """Chance that no band brings a pair of this similarity together."""
    return math.exp(BANDS * math.log1p(-(similarity**ROWS)))
