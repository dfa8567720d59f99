"""Toxicity by cumulative-link ordinal regression on sparse text features.

Features of a text are its lower-case letter runs (whole, and their first four and five bytes), counted. The model gives
severity grades 0..3: P(grade > k) = sigmoid(w . x - theta_k) with one weight vector for all ordered thresholds; the expected
severity is the sum of these chances.

Features that mark toxic documents and features that mark clean ones both go into the fit.

Labels may be grades 0..3; those are used as they are. Labels that say only toxic or not are graded first: 0 for a clean document;
for a toxic one 1, 2 or 3 by how many of its words mark toxic documents (fewer than 3, fewer than 6, more). Which words do
is learnt from the other half of the sample, so no document takes part in its own grade.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import cut, names_out
from .words import LOWER, Hasher, chunks, kept_by_worker, texts

LETTERS = np.zeros(256, bool)
LETTERS[65:91] = LETTERS[97:123] = LETTERS[128:] = True
STEPS = (3, 6)


def _hasher() -> Hasher:
    return kept_by_worker("toxicity", lambda: Hasher(11))


def features(column):
    """Yields (first row, rows, row of each feature, 64-bit feature) for chunks of rows; one feature for each word and kind."""
    flat, offsets = texts(column)
    for lo, hi in chunks(offsets):
        b = LOWER[flat[offsets[lo] : offsets[hi]]]
        own = offsets[lo : hi + 1] - offsets[lo]
        inside = LETTERS[b]
        before, after = np.zeros(len(b), bool), np.zeros(len(b), bool)
        before[1:], after[:-1] = inside[:-1], inside[1:]
        before[own[:-1][own[:-1] < len(b)]] = False
        after[own[1:][own[1:] > 0] - 1] = False
        starts, ends = np.flatnonzero(inside & ~before), np.flatnonzero(inside & ~after) + 1
        row = np.searchsorted(own, starts, "right") - 1
        kinds = [_hasher().words(b, starts, ends)]
        for n, salt in ((4, 0x5851F42D4C957F2D), (5, 0x14057B7EF767814F)):
            long_ = ends - starts > n
            h = np.zeros(len(starts), np.uint64)
            h[long_] = _hasher().words(b, starts[long_], starts[long_] + n) ^ np.uint64(salt)
            kinds.append(h)
        yield lo, hi - lo, row, np.stack(kinds)


@dataclass
class Model:
    """Weights by feature hash (sorted), thresholds, and how it was fitted."""

    keys: np.ndarray = field(default_factory=lambda: np.zeros(0, np.uint64))
    weights: np.ndarray = field(default_factory=lambda: np.zeros(0))
    thresholds: np.ndarray = field(default_factory=lambda: np.array([4.0, 6.0, 8.0]))
    rows: int = 0

    def severity(self, score: np.ndarray) -> np.ndarray:
        return (1 / (1 + np.exp(np.clip(self.thresholds[None, :] - score[:, None], -40, 40)))).sum(axis=1)


def _lookup(keys: np.ndarray, h: np.ndarray, seen: np.ndarray) -> np.ndarray:
    """Place of each feature in ``keys`` or -1; ``seen`` marks the low bits of the keys and spares most searches."""
    out = np.full(h.shape, -1, np.int64)
    if len(keys):
        hit = np.flatnonzero(seen[(h & np.uint64(len(seen) - 1)).astype(np.int64)])
        at = np.minimum(np.searchsorted(keys, h[hit]), len(keys) - 1)
        out[hit] = np.where(keys[at] == h[hit], at, -1)
    return out


def _marks(keys: np.ndarray) -> np.ndarray:
    seen = np.zeros(1 << 20, bool)
    seen[(keys & np.uint64(len(seen) - 1)).astype(np.int64)] = True
    return seen


def _sparse(column, keys: np.ndarray, seen: np.ndarray, marked: np.ndarray | None = None, half: np.ndarray | None = None):
    """(row, key place, count) of the known features, and the words per row with one that ``marked`` (half by key) names for
    the row's ``half``."""
    rows, places, words = [], [], np.zeros(len(column), np.int64)
    for lo, n, row, kinds in features(column):
        at = np.stack([_lookup(keys, h, seen) for h in kinds])
        for one in at:
            hit = one >= 0
            rows.append(row[hit] + lo)
            places.append(one[hit])
        if marked is not None:
            hit = (at >= 0) & marked[half[row + lo][None, :], np.maximum(at, 0)]
            words[lo : lo + n] += np.bincount(row[hit.any(axis=0)], minlength=n)
    if not rows:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64), words
    key, count = np.unique(np.concatenate(rows) * (len(keys) + 1) + np.concatenate(places), return_counts=True)
    return key // (len(keys) + 1), key % (len(keys) + 1), count, words


def loss_and_slopes(row, place, x, grade: np.ndarray, weight: np.ndarray, w: np.ndarray, raw: np.ndarray, ridge: float):
    """Weighted negative log-likelihood of the grades plus ridge, and its slopes by weights and by raw thresholds (the first
    threshold, and logarithms of the gaps)."""
    n, top, at = len(grade), len(raw), np.arange(len(grade))
    theta = np.cumsum(np.concatenate([raw[:1], np.exp(raw[1:])]))
    score = np.bincount(row, w[place] * x, n)
    p = np.hstack([np.ones((n, 1)), 1 / (1 + np.exp(-np.clip(score[:, None] - theta, -30, 30))), np.zeros((n, 1))])
    slope = p * (1 - p)
    mass = np.maximum(p[at, grade] - p[at, grade + 1], 1e-9)
    d_score = -weight * (slope[at, grade] - slope[at, grade + 1]) / mass / n
    d_theta = np.array([(weight * (np.where(grade == k + 1, slope[:, k + 1], 0) - np.where(grade == k, slope[:, k + 1], 0)) / mass).sum() / n for k in range(top)])
    tail = np.cumsum(d_theta[::-1])[::-1]
    loss = -(weight * np.log(mass)).sum() / n + ridge / 2 * (w * w).sum()
    return loss, np.bincount(place, d_score[row] * x, len(w)) + ridge * w, np.concatenate([tail[:1], tail[1:] * np.exp(raw[1:])])


def fit_ordinal(row, place, count, grade: np.ndarray, n_features: int, steps: int = 400, ridge: float = 2e-3) -> tuple[np.ndarray, np.ndarray]:
    """Weights and thresholds of the cumulative-link model by full-batch Adam; gaps between thresholds stay positive."""
    x, n = np.log1p(count), len(grade)
    w, raw = np.zeros(n_features), np.array([1.0, 0.5, 0.5])
    state = [np.zeros(n_features), np.zeros(n_features), np.zeros(3), np.zeros(3)]
    weight = np.where(grade > 0, n / (2 * max(1, (grade > 0).sum())), n / (2 * max(1, (grade == 0).sum())))
    for t in range(1, steps + 1):
        _, d_w, d_raw = loss_and_slopes(row, place, x, grade, weight, w, raw, ridge)
        for value, grad, a, b in ((w, d_w, state[0], state[1]), (raw, d_raw, state[2], state[3])):
            a += 0.1 * (grad - a)
            b += 0.01 * (grad * grad - b)
            value -= 0.1 * (a / (1 - 0.9**t)) / (np.sqrt(b / (1 - 0.99**t)) + 1e-8)
    return w, np.cumsum(np.concatenate([raw[:1], np.exp(raw[1:])]))


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", most_rows: int = 10_000, most_features: int = 8192) -> Model:
    """Fits on at most ``most_rows`` labelled documents of each class (grade 0, and above), those with the least id hashes, and at
    most ``most_features`` features, those that tell the classes apart most; no more of them speak for clean text than for toxic.
    Of contradictory labels the highest counts; grades above 3 count as 3; labels without id, value or document are passed over.
    Without both classes the model finds nothing toxic."""
    clean = labels.where(F.col(id_col).isNotNull() & F.col(label_col).isNotNull()).groupBy(F.col(id_col).alias("id")).agg(F.greatest(F.lit(0), F.least(F.lit(3), F.max(F.col(label_col).cast("int")))).alias("y"))
    part = lambda toxic: clean.where((F.col("y") > 0) == toxic).orderBy(F.xxhash64("id"), "id").limit(most_rows)
    chosen = part(False).unionByName(part(True)).withColumn("half", F.pmod(F.xxhash64("id", F.lit(5)), F.lit(2)).cast("int"))
    sample = cut(docs.select(F.col(f"`{id_col}`").alias("id"), F.col(f"`{text_col}`").alias("text")).join(F.broadcast(chosen), "id").select("y", "half", "text"))
    sizes = {(r["y"], r["half"]): r["n"] for r in sample.groupBy("y", "half").agg(F.count(F.lit(1)).alias("n")).collect()}
    graded = any(y > 1 for y, _ in sizes)
    n = {(t, h): sum(m for (y, g), m in sizes.items() if (y > 0) == t and g == h) for t in (True, False) for h in (0, 1)}
    n0, n1 = n[False, 0] + n[False, 1], n[True, 0] + n[True, 1]
    if not n0 or not n1:
        return Model()
    names = ["a0", "a1", "b0", "b1"]  # toxic and clean documents by half

    def tally(found, hits):
        h, at = np.unique(np.concatenate(found), return_inverse=True)
        code = np.concatenate(hits)
        counts = [np.bincount(at, code == k, len(h)).astype(np.int64) for k in range(4)]
        return pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), *map(pa.array, counts)], names=["h", *names])

    def spread(batches):
        for batch in batches:
            kind = np.where(batch.column(0).to_numpy() > 0, 0, 2) + batch.column(1).to_numpy()
            found, hits = [], []
            for lo, _, row, kinds in features(batch.column(2)):
                for h in kinds:
                    # Document frequency: each feature once for each row.
                    order = np.lexsort((row, h))
                    hh, rr = h[order], row[order]
                    head = np.ones(len(hh), bool)
                    head[1:] = (hh[1:] != hh[:-1]) | (rr[1:] != rr[:-1])
                    head &= hh != 0
                    found.append(hh[head])
                    hits.append(kind[rr[head] + lo])
                # Partial counts leave early, so that a worker never holds the features of a whole batch.
                if sum(map(len, found)) > 1 << 19:
                    yield tally(found, hits)
                    found, hits = [], []
            if found:
                yield tally(found, hits)

    seen_in = sample.mapInArrow(spread, "h long, " + ", ".join(f"{c} long" for c in names)).groupBy("h").agg(*[F.sum(c).alias(c) for c in names])
    odds_of = lambda a, b, na, nb: F.log((a + 0.1) / max(1, na)) - F.log((b + 0.1) / max(1, nb))
    a, b = F.col("a0") + F.col("a1"), F.col("b0") + F.col("b1")
    odds = odds_of(a, b, n1, n0)
    other = [(F.col(f"a{1 - h}") >= 3) & (odds_of(F.col(f"a{1 - h}"), F.col(f"b{1 - h}"), n[True, 1 - h], n[False, 1 - h]) > 2.5) for h in (0, 1)]
    rated = cut(seen_in.where((a >= 3) & (odds > 2.5) | (b >= 10) & (odds < -1)).select("h", odds.alias("odds"), F.when(odds > 0, odds * F.sqrt(a)).otherwise(-odds * F.sqrt(b)).alias("strength"), other[0].alias("m0"), other[1].alias("m1")))
    take = lambda side, k: rated.where(side).orderBy(F.desc("strength"), "h").limit(k).collect()
    top = take(F.col("odds") > 0, most_features)
    top += take(F.col("odds") < 0, min(most_features - len(top), len(top)))
    top.sort(key=lambda r: np.int64(r["h"]).view(np.uint64))
    keys = np.array([r["h"] for r in top], np.int64).view(np.uint64)
    if not len(keys):
        return Model(rows=n0 + n1)
    seen, marked = _marks(keys), np.array([[r[c] for r in top] for c in ("m0", "m1")])

    def gather(batches):
        for batch in batches:
            row, place, count, words = _sparse(batch.column(2), keys, seen, marked, batch.column(1).to_numpy())
            edge = np.searchsorted(row, np.arange(batch.num_rows + 1))
            lists = lambda v: pa.ListArray.from_arrays(pa.array(edge, pa.int32()), pa.array(v, pa.int32()))  # noqa: E731, B023
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(words), lists(place), lists(count)], names=["y", "words", "place", "count"])

    got = sample.mapInArrow(gather, "y int, words long, place array<int>, count array<int>").toArrow()
    y, words = got["y"].to_numpy(), got["words"].to_numpy()
    grade = y if graded else np.where(y > 0, 1 + (words[:, None] >= np.array(STEPS)).sum(axis=1), 0)
    lists = got["place"].combine_chunks()
    place, count = lists.flatten().to_numpy(), got["count"].combine_chunks().flatten().to_numpy()
    row = np.repeat(np.arange(len(y)), np.diff(np.asarray(lists.offsets)))
    w, theta = fit_ordinal(row, place, count, grade, len(keys))
    return Model(keys, w, theta, n0 + n1)


def score(docs: DataFrame, model: Model, text_col: str = "text", cut_at: float = 0.5, digest: str | None = None) -> DataFrame:
    """Input columns plus ``severity`` (expected grade), ``grade`` (nearest) and ``toxic`` (severity >= cut_at). Null and
    empty texts have no feature and the least severity. Rows are handled one by one. ``digest`` names the one input column
    to return; input columns with the name of an added one come back with ``_in`` appended."""
    given = docs.columns
    own = docs.select(*[F.col(f"`{c}`").alias(f"in_{i}") for i, c in enumerate(given)])
    text_at = given.index(text_col)
    keep = [i for i, c in enumerate(given) if digest is None or c == digest]
    own = own.select(*[f"in_{i}" for i in keep], F.col(f"in_{text_at}").alias("text_"))
    seen = _marks(model.keys)

    def run(batches):
        for batch in batches:
            column = batch.column(batch.num_columns - 1)
            row, place, count, _ = _sparse(column, model.keys, seen)
            total = np.bincount(row, model.weights[place] * np.log1p(count), len(column)) if len(row) else np.zeros(len(column))
            value = np.round(model.severity(total), 6)
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(value), pa.array(np.rint(value).astype(np.int32)), pa.array(value >= cut_at)], names=[*batch.schema.names[:-1], "severity", "grade", "toxic"])

    kinds = ", ".join(f"{c} {t}" for c, t in own.dtypes[:-1])
    out = own.mapInArrow(run, f"{kinds}, severity double, grade int, toxic boolean")
    names = names_out(given, ["severity", "grade", "toxic"])
    return out.select(*[F.col(f"in_{i}").alias(names[i]) for i in keep], "severity", "grade", "toxic")
