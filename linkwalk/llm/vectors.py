"""Embedding near-duplicates on a robust-pruned flat graph.

1. Vectors of one label are spread over *overlapping* cluster shards: each goes to the centres nearest to it. Centres come
   from k-means on a bounded sample; every vector is indexed. A shard that outgrows ``CAP`` is cut into slices, and each
   pair of slices becomes a unit of work, so no task holds more than two slices.
2. In each unit every vector gets its nearest candidates, and robust pruning keeps those that no kept one lies closer to by
   the factor ``ALPHA``; places left free go to the nearest pruned ones, without which a dense group around one centre becomes
   a star that search cannot walk. Reverse edges are added and pruned again. Adjacency lists of all units are united by vector.
3. Each unit searches its part of the united graph: every vector is a query, and starts at the unit's medoids, never at its
   own node; a beam walks towards it, then the search expands through every node in range until nothing new is in range.
4. Pairs found are verified in double precision. A pair that shares several shards counts in the least of them, so counts
   add up without listing pairs. Each unit sends a spanning forest of its links, from which components follow.
5. Recall is audited against brute force for a bounded sample of queries, as the lower of the share of links found and the mean
   share over queries; while it is below the target, beam and overlap double and the search runs again. Where the widest
   search falls short too, all rows of a label are compared exactly, in pairs of slices, and the log says so.

Equal vectors of a label are one node with a multiplicity.
"""

from __future__ import annotations

import logging

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import connected_components
from .storage import cut, with_uid

CAP, DEGREE, CANDIDATES, ALPHA, BEAM, OVERLAP = 1024, 16, 48, 1.2, 48, 4
SAMPLE, CENTRES, AUDIT = 40_000, 16_384, 200
#: The widest search; what falls short with it is compared exactly.
MOST_OVERLAP = 24
log = logging.getLogger(__name__)


def robust_prune(x: np.ndarray, own: np.ndarray, cand: np.ndarray, degree: int = DEGREE, alpha: float = ALPHA) -> np.ndarray:
    """For each row of ``cand`` (node numbers, -1 for none, repeats allowed), at most ``degree`` neighbours, -1 filled: first
    those that robust pruning keeps, then the nearest of the others."""
    n, _ = cand.shape
    out = np.full((n, degree), -1, np.int64)
    for lo in range(0, n, 256):
        c = cand[lo : lo + 256]
        rows = np.arange(len(c))
        d = 2 - 2 * np.einsum("ij,ikj->ik", x[own[lo : lo + 256]], x[c])
        order = np.argsort(c, axis=1, kind="stable")
        again = np.zeros(c.shape, bool)
        again[:, 1:] = np.diff(np.take_along_axis(c, order, 1), axis=1) == 0
        np.put_along_axis(again, order, again.copy(), 1)
        d[(c < 0) | (c == own[lo : lo + 256, None]) | again] = np.inf
        rest = d.copy()
        for k in range(degree):
            best = d.argmin(axis=1)
            live = np.isfinite(d[rows, best])
            if not live.any():
                break
            pick = np.where(live, c[rows, best], -1)
            out[lo : lo + len(c), k] = pick
            far = 2 - 2 * np.einsum("ij,ikj->ik", x[np.maximum(pick, 0)], x[c])
            d[live] = np.where((alpha * np.maximum(far, 0) <= d)[live], np.inf, d[live])
            d[rows[live], best[live]] = rest[rows[live], best[live]] = np.inf
        for k in range(degree):
            best = rest.argmin(axis=1)
            free = (out[lo : lo + len(c), k] < 0) & np.isfinite(rest[rows, best])
            out[lo + rows[free], k] = c[rows[free], best[free]]
            rest[rows[free], best[free]] = np.inf
    return out


def build(x: np.ndarray) -> np.ndarray:
    """Adjacency (node by degree, -1 filled) of the pruned graph over unit vectors ``x``."""
    n = len(x)
    k = min(CANDIDATES, n - 1)
    if k <= 0:
        return np.full((n, DEGREE), -1, np.int64)
    near = np.empty((n, k), np.int64)
    for lo in range(0, n, 512):
        s = x[lo : lo + 512] @ x.T
        s[np.arange(len(s)), np.arange(lo, lo + len(s))] = -np.inf
        near[lo : lo + 512] = np.argpartition(-s, k - 1, axis=1)[:, :k]
    r = np.random.default_rng(n)
    # A few far nodes keep the graph in one piece, as a search path needs.
    far = r.integers(0, n, (n, 4))
    first = robust_prune(x, np.arange(n), np.concatenate([near, far], 1))
    src = np.repeat(np.arange(n), DEGREE)
    dst = first.ravel()
    src, dst = src[dst >= 0], dst[dst >= 0]
    order = np.lexsort((src, dst))
    src, dst = src[order], dst[order]
    rank = np.arange(len(dst)) - np.searchsorted(dst, dst)
    back = np.full((n, 2 * DEGREE), -1, np.int64)
    ok = rank < 2 * DEGREE
    back[dst[ok], rank[ok]] = src[ok]
    return robust_prune(x, np.arange(n), np.concatenate([first, back], 1))


def medoids(x: np.ndarray, parts: int = 8) -> np.ndarray:
    """The medoid of all vectors, and those of ``parts`` parts of them: where searches start."""
    centres = np.vstack([x.mean(axis=0), k_means(x, min(parts, len(x)), 3)])
    return np.unique((x @ centres.T).argmax(axis=0))


def search(x: np.ndarray, graph: np.ndarray, starts: np.ndarray, least: float, beam: int, slack: float = 0.05) -> np.ndarray:
    """Square matrix of pairs (query, node) found with cosine >= ``least``; every node is a query, from ``starts`` on."""
    starts = starts[:beam]
    n = len(x)
    found = np.zeros((n, n), bool)
    for lo in range(0, n, 256):
        q = np.arange(lo, min(n, lo + 256))
        rows = np.arange(len(q))
        seen = np.zeros((len(q), n), bool)
        ids = np.full((len(q), beam), -1, np.int64)
        sims, open_ = np.full((len(q), beam), -np.inf), np.zeros((len(q), beam), bool)
        k = len(starts)
        ids[:, :k], sims[:, :k], open_[:, :k] = starts, x[q] @ x[starts].T, True
        seen[:, starts] = True
        while True:
            best = np.where(open_, sims, -np.inf).argmax(axis=1)
            live = open_[rows, best]
            if not live.any():
                break
            open_[rows, best] = False
            near = np.where(live[:, None], graph[ids[rows, best]], -1)
            new = (near >= 0) & ~seen[rows[:, None], np.maximum(near, 0)]
            seen[np.repeat(rows, near.shape[1])[new.ravel()], near[new]] = True
            s = np.where(new, np.einsum("ij,ikj->ik", x[q], x[np.maximum(near, 0)]), -np.inf)
            sims, ids, open_ = np.hstack([sims, s]), np.hstack([ids, near]), np.hstack([open_, new])
            keep = np.argpartition(-sims, beam - 1, axis=1)[:, :beam]
            sims, ids, open_ = (np.take_along_axis(a, keep, 1) for a in (sims, ids, open_))
        # Expansion: every node within a little less than the range passes the search on.
        at, k = np.nonzero(sims >= least - slack)
        hit = np.zeros((len(q), n), bool)
        hit[at, ids[at, k]] = True
        known = hit.copy()
        front = hit.copy()
        while front.any():
            a, b = np.nonzero(front)
            near = graph[b]
            a = np.repeat(a, near.shape[1])[near.ravel() >= 0]
            b = near[near >= 0]
            reach = np.zeros((len(q), n), bool)
            reach[a, b] = True
            reach &= ~known
            known |= reach
            a, b = np.nonzero(reach)
            front = np.zeros((len(q), n), bool)
            for part in range(0, len(a), 65_536):
                aa, bb = a[part : part + 65_536], b[part : part + 65_536]
                ok = np.einsum("ij,ij->i", x[q[aa]], x[bb]) >= least - slack
                front[aa[ok], bb[ok]] = True
            hit |= front
        a, b = np.nonzero(hit)
        for part in range(0, len(a), 65_536):
            aa, bb = a[part : part + 65_536], b[part : part + 65_536]
            ok = np.einsum("ij,ij->i", x[q[aa]], x[bb]) >= least
            found[q[aa[ok]], bb[ok]] = True
    np.fill_diagonal(found, False)
    return found | found.T


def k_means(x: np.ndarray, k: int, rounds: int = 8) -> np.ndarray:
    r = np.random.default_rng(10)
    centres = x[r.choice(len(x), k, replace=False)]
    for _ in range(rounds):
        own = np.concatenate([(x[lo : lo + 2048] @ centres.T).argmax(axis=1) for lo in range(0, len(x), 2048)])
        total = np.zeros_like(centres)
        np.add.at(total, own, x)
        size = np.linalg.norm(total, axis=1)
        centres = np.where(size[:, None] > 0, total / np.maximum(size, 1e-300)[:, None], centres)
    return centres


def _matrix(column) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.float64).reshape(len(column), -1)


def _nodes(vectors: DataFrame, label_col: str, vector_col: str) -> DataFrame:
    """``(uid, label, x)``: double vectors of length one; those that can link only."""

    def run(batches):
        for batch in batches:
            keep, out = [], []
            for i, v in enumerate(batch.column(2)):
                values = v.values
                if values is None or values.null_count or not len(values):
                    continue
                x = values.to_numpy(zero_copy_only=False).astype(np.float64)
                top = np.abs(x).max()
                if np.isfinite(top) and top > 0:
                    x = x / top
                    keep.append(i)
                    out.append((x / np.linalg.norm(x)).tobytes())
            at = pa.array(keep, pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0).take(at), batch.column(1).take(at), pa.array(out, pa.binary())], names=["uid", "label", "x"])

    rows = vectors.where(F.col(label_col).isNotNull() & F.col(vector_col).isNotNull()).select("uid", F.col(label_col).cast("string").alias("label"), F.col(vector_col).alias("v"))
    return rows.mapInArrow(run, "uid long, label string, x binary")


def _centres(reps: DataFrame, overlap: int) -> dict[tuple[str, int], np.ndarray]:
    """Centres by (label, width of the vectors) from a sample: as many as keep a shard, with ``overlap`` shards for each vector,
    to about three quarters of ``CAP``; at most ``CENTRES``. The sample holds four vectors for each centre, ``SAMPLE`` at least."""
    held = reps.groupBy("label", F.octet_length("x").alias("w")).agg(F.count(F.lit(1)).alias("n")).collect()
    total = sum(r["n"] for r in held)
    sample = max(SAMPLE, 4 * min(CENTRES, round(total * overlap / (0.75 * CAP))))
    bar = min(1.0, sample / max(1, total))
    lot = F.pmod(F.xxhash64("rid", F.lit(10)), F.lit(1_000_000)) / 1_000_000.0
    got = reps.where(lot < bar).select("label", "x").limit(2 * sample).toArrow()
    by: dict[tuple[str, int], list[bytes]] = {}
    for label, x in zip(got["label"].to_pylist(), got["x"].to_pylist(), strict=True):
        by.setdefault((label, len(x)), []).append(x)
    out = {}
    for r in held:
        own = by.get((r["label"], r["w"]), [])
        x = np.frombuffer(b"".join(sorted(own)), np.float64).reshape(len(own), -1) if own else np.ones((1, r["w"] // 8))
        k = max(1, min(len(x), round(r["n"] * overlap / (0.75 * CAP)), max(1, CENTRES * r["n"] // max(1, total))))
        out[r["label"], r["w"]] = k_means(x, k)
    return out


def _spread(reps: DataFrame, centres: dict, overlap: int) -> DataFrame:
    """``(rid, x, n, shards array, shard)``: one row for each shard that a vector belongs to."""
    base, numbers = 0, {}
    for key, c in centres.items():
        numbers[key] = base
        base += len(c)

    def run(batches):
        for batch in batches:
            out = []
            for label, x in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                c = centres[label, len(x)]
                s = c @ np.frombuffer(x, np.float64)
                k = min(overlap, len(s))
                out.append(sorted((np.argpartition(-s, k - 1)[:k] + numbers[label, len(x)]).tolist()))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), batch.column(3), pa.array(out, pa.list_(pa.int32()))], names=["rid", "x", "n", "shards"])

    return reps.select("rid", "label", "x", "n").mapInArrow(run, "rid long, x binary, n long, shards array<int>").withColumn("shard", F.explode("shards"))


def _units(spread: DataFrame) -> DataFrame:
    """Adds ``slice`` and ``unit``: pairs of slices of each shard; a shard within ``CAP`` is one unit."""
    sizes = spread.groupBy("shard").agg(F.count(F.lit(1)).alias("m")).select("shard", F.ceil(F.col("m") / CAP).cast("int").alias("k"))
    own = spread.join(sizes, "shard").withColumn("slice", F.pmod(F.xxhash64("rid", "shard"), "k").cast("int"))
    pair = F.transform(F.sequence(F.lit(0), F.col("k") - 1), lambda j: F.least(j, F.col("slice")) * F.col("k") + F.greatest(j, F.col("slice")))
    return own.withColumn("unit", F.explode(pair))


def _graph(units: DataFrame) -> DataFrame:
    """``(rid, near)``: united adjacency lists over all units."""

    def run(table: pa.Table) -> pa.Table:
        x, rid = _matrix(table["x"]), table["rid"].to_numpy()
        graph = build(x)
        near = [rid[row[row >= 0]].tolist() for row in graph]
        return pa.table({"rid": pa.array(rid), "near": pa.array(near, pa.list_(pa.int64()))})

    made = units.select("shard", "unit", "rid", "x").groupBy("shard", "unit").applyInArrow(run, "rid long, near array<long>")
    return made.groupBy("rid").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("near")))).alias("near"))


def _links(units: DataFrame, graph: DataFrame | None, least: float, beam: int) -> DataFrame:
    """``(rid, links, root)`` by unit: verified links counted here, and an edge to the root of the unit's forest.
    Without a graph all pairs of a unit are compared."""
    exact = graph is None

    def walked(table: pa.Table, x: np.ndarray, rid: np.ndarray) -> np.ndarray:
        order = np.argsort(rid)
        near = table["near"].combine_chunks()
        lengths = np.diff(np.asarray(near.offsets))
        row, to = np.repeat(np.arange(len(rid)), lengths), near.flatten().to_numpy()
        at = np.minimum(np.searchsorted(rid[order], to), len(rid) - 1)
        inside = rid[order][at] == to
        row, at = row[inside], order[at[inside]]
        counts = np.bincount(row, minlength=len(rid))
        adjacency = np.full((len(rid), max(1, int(counts.max(initial=0)))), -1, np.int64)
        adjacency[row, np.arange(len(row)) - np.repeat(np.cumsum(counts) - counts, counts)] = at
        return search(x, adjacency, medoids(x), least, beam)

    def compared(x: np.ndarray) -> np.ndarray:
        found = np.vstack([x[lo : lo + 256] @ x.T >= least for lo in range(0, len(x), 256)])
        np.fill_diagonal(found, False)
        return found | found.T

    def run(table: pa.Table) -> pa.Table:
        x, rid, n = _matrix(table["x"]), table["rid"].to_numpy(), table["n"].to_numpy()
        found = compared(x) if exact else walked(table, x, rid)
        # Roots: repeated least label over links; every label is a node of this unit.
        root = np.arange(len(rid))
        a, b = np.nonzero(found)
        while True:
            low = root.copy()
            np.minimum.at(low, a, root[b])
            low = low[low]
            if (low == root).all():
                break
            root = low
        # A pair belongs to the least shard that both share, and to the unit of its slices.
        shard = table["shard"][0].as_py()
        lists = table["shards"].combine_chunks().to_pylist()
        lower = {s: np.zeros(len(rid), bool) for held in lists for s in held if s < shard}
        for i, held in enumerate(lists):
            for s in held:
                if s < shard:
                    lower[s][i] = True
        ours = np.ones(len(a), bool)
        for member in lower.values():
            ours &= ~(member[a] & member[b])
        slices = table["slice"].to_numpy()
        if len(np.unique(slices)) > 1:
            ours &= slices[a] != slices[b]
        links = np.bincount(a[ours], n[b[ours]], len(rid)).astype(np.int64)
        return pa.table({"rid": rid, "links": links, "root": rid[root]})

    columns = ["shard", "unit", "slice", "k", "shards", "rid", "x", "n"]
    rows = units.select(columns) if exact else units.join(graph, "rid").select(*columns, "near")
    return rows.groupBy("shard", "unit").applyInArrow(run, "rid long, links long, root long")


def audit_recall(reps: DataFrame, counts: DataFrame, least: float, queries: int = AUDIT) -> float:
    """For a bounded sample of query vectors against all rows: links found over links that are there, or the mean of that over
    queries that have links, whichever is lower. The first follows dense groups, the second the many small ones."""
    some = reps.orderBy(F.xxhash64("rid", F.lit(12)), "rid").limit(queries).select("rid", "label", "x", "n").toArrow()
    if not some.num_rows:
        return 1.0
    rid, label, x = some["rid"].to_numpy(), some["label"].to_pylist(), some["x"].to_pylist()

    def run(batches):
        for batch in batches:
            total = np.zeros(len(rid), np.int64)
            labels, xs = np.array(batch.column(1).to_pylist(), object), batch.column(2).to_pylist()
            n, own = batch.column(3).to_numpy(), batch.column(0).to_numpy()
            widths = np.array([len(v) for v in xs])
            for i, q in enumerate(x):
                at = np.flatnonzero((labels == label[i]) & (widths == len(q)) & (own != rid[i]))
                if len(at):
                    s = np.frombuffer(b"".join(xs[j] for j in at), np.float64).reshape(len(at), -1) @ np.frombuffer(q, np.float64)
                    total[i] += n[at[s >= least]].sum()
            yield pa.RecordBatch.from_arrays([pa.array(rid), pa.array(total)], names=["rid", "t"])

    there = reps.select("rid", "label", "x", "n").mapInArrow(run, "rid long, t long").groupBy("rid").agg(F.sum("t").alias("t"))
    share = F.least(F.coalesce("links", F.lit(0)), F.col("t"))
    got = there.where("t > 0").join(counts, "rid", "left").agg(F.sum("t").alias("t"), F.sum(share).alias("l"), F.avg(share / F.col("t")).alias("each")).first()
    return 1.0 if not got["t"] else min(got["l"] / got["t"], got["each"])


def near_vectors(vectors: DataFrame, id_col: str = "vec_id", label_col: str = "label", vector_col: str = "embedding", least: float = 0.93, target: float = 0.995) -> DataFrame:
    """``(vec_id, n_links, component_id, kept)`` for every row.

    Rows link when labels are equal and not null, vectors have one width, and the cosine in double precision is at least
    ``least``. Vectors that are null, empty, zero or hold null or non-finite components link with nothing. Rows with null or
    repeated ids are rows of their own; a component's id is the id of its first row, nulls last. An empty table gives an
    empty one. The audited recall is logged. Repeated ids are told apart by vector only in the order of rows. Where the graph
    search falls short of ``target`` at its widest, all pairs of a label are compared; if the audit fails even then, this raises.
    """
    own = vectors.select(F.col(f"`{id_col}`").alias("id"), F.col(f"`{label_col}`").alias("label_"), F.col(f"`{vector_col}`").alias("v"))
    source = with_uid(own, "id", "v")
    nodes = cut(_nodes(source, "label_", "v"))
    # Equal directions are one node: the copies' own links are counted from the multiplicity.
    reps = cut(nodes.groupBy("label", "x").agg(F.min("uid").alias("rid"), F.count(F.lit(1)).alias("n")))
    overlap, beam = OVERLAP, BEAM
    while True:
        exact = overlap > MOST_OVERLAP
        centres = {k: c[:1] for k, c in _centres(reps, 1).items()} if exact else _centres(reps, overlap)
        units = cut(_units(_spread(reps, centres, 1 if exact else overlap)))
        links = cut(_links(units, None if exact else cut(_graph(units)), least, beam))
        counts = links.groupBy("rid").agg(F.sum("links").alias("links"))
        recall = audit_recall(reps, counts, least)
        (log.warning if exact else log.info)("near_vectors: audited recall %.4f (%s)", recall, "all pairs" if exact else f"overlap {overlap}, beam {beam}")
        if recall >= target:
            break
        if exact:
            raise RuntimeError(f"audited recall {recall} is below {target} with all pairs compared")
        # The widest search comes once, then all pairs.
        overlap, beam = min(2 * overlap, MOST_OVERLAP) if overlap < MOST_OVERLAP else 2 * overlap, 2 * beam
    labels = connected_components(links.where("rid <> root").select(F.col("rid").alias("u"), F.col("root").alias("v")))
    per = reps.join(counts, "rid", "left").join(labels.withColumnRenamed("node", "rid"), "rid", "left")
    per = per.select("label", "x", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("component", "rid").alias("head"))
    members = nodes.join(per, ["label", "x"]).select("uid", "n_links", "head")
    ids = source.select(F.col("uid").alias("head"), F.col("id").alias("component_id"))
    every = source.select("uid", "id").join(members, "uid", "left").withColumn("head", F.coalesce("head", "uid")).join(ids, "head")
    return every.select(F.col("id").alias(id_col), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), "component_id", (F.col("uid") == F.col("head")).alias("kept"))
