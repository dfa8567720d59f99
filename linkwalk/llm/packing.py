"""Best-fit packing of token sequences by the configuration linear program over the length histogram.

A configuration is a multiset of lengths that fits one sequence. Multiplicative weights give each length a price; in each
round the priciest configurations that the counts allow, found by knapsack dynamic programming over the capacity, are used a
little, in whole numbers, and prices of the lengths that lag behind grow. Rounds end when every token is placed, so the plan is
the rounded program and nothing else. Prices scaled by the best configuration's are a dual solution, which bounds from below
what any packing needs. The histogram has at most one row for each length, whatever the size of the corpus.
"""

from __future__ import annotations

import base64
import json
import re
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .bpe import Encoder
from .storage import cut
from .words import kept_by_worker

CAPACITY = 1024
#: Rounds between two looks at the dual bound.
LOOK = 8
LONG_GAP = re.compile(r"\s{5000}|[^\W\d_]{20000}|[^\w\s]{20000}|\d{20000}")


def _encoder(ranks: str, pattern: str, special: dict[str, int]):
    import tiktoken

    with open(ranks, "rb") as f:
        table = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
    fast = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=table, special_tokens=special)
    marks = re.compile("|".join(re.escape(x) for x in sorted(special, key=len, reverse=True)) or "(?!)")
    slow: list = []

    def encode(text: str) -> list[int]:
        if len(text) > 5000 and LONG_GAP.search(text):
            # Very long runs go through the vectorised encoder, whose time stays near linear on them.
            if not slow:
                slow.append(Encoder(ranks))
            out, at = [], 0
            for m in marks.finditer(text):
                out += [*slow[0].ids(text[at : m.start()]), special[m[0]]]
                at = m.end()
            return out + slow[0].ids(text[at:])
        return fast.encode(text, allowed_special=set(special), disallowed_special=())

    return encode


def special_tokens(tokenizer: str) -> dict[str, int]:
    """The special tokens that a tokenizer's JSON file names; read by the driver."""
    with open(tokenizer, encoding="utf-8") as f:
        return {x["content"]: x["id"] for x in json.load(f)["added_tokens"]}


def pieces(docs: DataFrame, ranks: str, pattern: str, special: dict[str, int] | None = None, id_col: str = "doc_id", text_col: str = "text", end_id: int = 2, capacity: int = CAPACITY) -> DataFrame:
    """``(doc_id, piece, start, length, ids_crc32)``: each document's ids and ``end_id``; one longer than ``capacity`` is cut
    so that all pieces but the first are full. ``special`` maps strings that are one token to their ids. Null counts as empty,
    which is one piece of one id. Rows with null or repeated ids are documents of their own; an empty table gives an empty one."""
    schema = pa.schema([("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64())])
    special = special or {}

    def run(batches):
        encode = kept_by_worker(f"packing:{ranks}:{sorted(special)}", lambda: _encoder(ranks, pattern, special))
        for batch in batches:
            out = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = np.array([*encode(text.as_py() or ""), end_id], "<u4")
                head = (len(ids) - 1) % capacity + 1
                for k, at in enumerate([0, *range(head, len(ids), capacity)]):
                    part = ids[at : head if k == 0 else at + capacity]
                    out.append((doc, k, at, len(part), zlib.crc32(part.tobytes())))
            yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in out], f.type) for i, f in enumerate(schema)], schema=schema)

    return docs.select(F.col(f"`{id_col}`").cast("long").alias("doc_id"), F.col(f"`{text_col}`").alias("text")).mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long")


def price(weights: np.ndarray, lengths: np.ndarray, most: np.ndarray, capacity: int) -> np.ndarray:
    """For each length the configuration of most weight that holds it, as a row of counts by length; none holds more than
    ``most`` copies of a length. One knapsack over 0..capacity, with copies in powers of two, prices all of them."""
    items: list[tuple[int, int]] = []
    for k, (length, n) in enumerate(zip(lengths.tolist(), most.tolist(), strict=True)):
        n, copies = min(n, capacity // length), 1
        while n > 0:
            items.append((k, min(copies, n)))
            n -= copies
            copies *= 2
    best, took = np.zeros(capacity + 1), np.zeros((len(items), capacity + 1), bool)
    for i, (k, copies) in enumerate(items):
        size = int(lengths[k]) * copies
        value = best[: capacity + 1 - size] + weights[k] * copies
        took[i, size:] = value > best[size:] + 1e-12
        best[size:] = np.maximum(best[size:], value)
    out, room = np.zeros((len(lengths), len(lengths)), np.int64), capacity - lengths
    for i in range(len(items) - 1, -1, -1):
        k, copies = items[i]
        hit = took[i, room]
        out[hit, k] += copies
        room = room - hit * (int(lengths[k]) * copies)
    out[np.arange(len(lengths)), np.arange(len(lengths))] += 1
    return np.minimum(out, most)


def dual_bound(weights: np.ndarray, lengths: np.ndarray, counts: np.ndarray, capacity: int) -> float:
    """Sequences that the program needs at least: the pieces' worth over that of the best configuration within the counts."""
    worth = np.zeros(capacity + 1)
    for length, n, w in zip(lengths.tolist(), counts.tolist(), weights.tolist(), strict=True):
        n, copies = min(n, capacity // length), 1
        while n > 0:
            k = min(copies, n)
            worth[length * k :] = np.maximum(worth[length * k :], worth[: capacity + 1 - length * k] + k * w)
            n -= copies
            copies *= 2
    return float((weights * counts).sum() / worth[capacity])


def cover(lengths: np.ndarray, counts: np.ndarray, capacity: int, step: float = 0.25, lean: float = 2.0, rate: float = 0.02) -> tuple[list[tuple[list[int], int]], float]:
    """``(configurations with their whole use, the best dual bound met)``, by multiplicative weights.

    Each round prices a configuration for every length that is left, within what is left, and uses those that are full up to
    a tolerance, by at most ``step`` of a length's count; uses are whole, so they are rounded as they are made. Then prices of
    lengths that lag behind grow. The tolerance doubles when no configuration meets it. Prices start above proportion for long
    pieces (``lean``), so that short ones last as filling.
    """
    left, out, rounds = counts.copy(), [], 0
    weights, slack = lengths / capacity * (1 + lean * lengths / capacity), 0.001
    # Dual solutions known beforehand: for a threshold, pieces that leave less than it count 1, shorter ones than it nothing,
    # the others their share of a sequence.
    near = lengths[lengths * 2 <= capacity]
    share = lambda t: np.where(lengths > capacity - t, 1.0, np.where(lengths < t, 0.0, lengths / capacity))
    bound = max(float((counts * share(t)).sum()) for t in [0, *near.tolist(), capacity // 2])
    while left.any():
        if rounds % LOOK == 0:
            bound = max(bound, dual_bound(weights, lengths, counts, capacity))
        rounds += 1
        live = np.flatnonzero(left > 0)
        configurations = price(weights[live], lengths[live], left[live], capacity)
        waste = 1 - configurations @ lengths[live] / capacity
        used = False
        for j in np.flatnonzero(waste <= slack)[::-1]:
            held = np.flatnonzero(configurations[j])
            k, m = live[held], configurations[j, held]
            n = min(int((left[k] // m).min()), max(1, int(step * (counts[k] / m).min())))
            if n > 0:
                left[k] -= n * m
                out.append((np.repeat(lengths[k], m).tolist(), n))
                used = True
        if not used:
            slack = max(2 * slack, float(waste.min()) + 1e-12)
        share = left[live] / counts[live]
        weights[live] *= np.exp(rate * (share - share.mean()))
    return out, bound


def best_fit(lengths: np.ndarray, counts: np.ndarray, capacity: int) -> list[tuple[list[int], int]]:
    """The plain rule to compare with: best fit, longest first, on a histogram. Bins of equal content are one class with a count."""
    classes: dict[int, dict[tuple[tuple[int, int], ...], int]] = {}
    free = np.zeros(capacity + 1, bool)

    def put(room, content, n):
        classes.setdefault(room, {})
        classes[room][content] = classes[room].get(content, 0) + n
        free[room] = True

    for length, count in sorted(zip(lengths.tolist(), counts.tolist(), strict=True), reverse=True):
        while count:
            fits = np.flatnonzero(free[length:])
            if not len(fits):
                each = min(capacity // length, count)
                bins = count // each
                put(capacity - each * length, ((length, each),), bins)
                count -= bins * each
                continue
            room = int(fits[0]) + length
            content, bins = classes[room].popitem()
            each = min(room // length, count)
            n = min(bins, count // each)
            if bins > n:
                classes[room][content] = bins - n
            free[room] = bool(classes[room])
            put(room - each * length, (*content, (length, each)), n)
            count -= n * each
    return [([x for x, k in content for _ in range(k)], n) for held in classes.values() for content, n in held.items()]


def _arrays(histogram: dict[int, int]) -> tuple[np.ndarray, np.ndarray]:
    keep = sorted(x for x, n in histogram.items() if n > 0)
    return np.array(keep, np.int64), np.array([histogram[x] for x in keep], np.int64)


def plan(histogram: dict[int, int], capacity: int = CAPACITY) -> list[tuple[list[int], int]]:
    """``(lengths in one sequence, number of such sequences)`` that place the whole histogram."""
    lengths, counts = _arrays(histogram)
    return cover(lengths, counts, capacity)[0] if len(lengths) else []


def report(histogram: dict[int, int], capacity: int = CAPACITY) -> dict[str, int]:
    """``pieces``, ``sequences`` of the plan, ``at_least`` (what the dual bound says that any packing needs), and
    ``best_fit`` (what the plain rule needs)."""
    lengths, counts = _arrays(histogram)
    if not len(lengths):
        return {"pieces": 0, "sequences": 0, "at_least": 0, "best_fit": 0}
    out, bound = cover(lengths, counts, capacity)
    used = lambda plan: sum(n for _, n in plan)
    return {"pieces": int(counts.sum()), "sequences": used(out), "at_least": int(np.ceil(bound - 1e-6)), "best_fit": used(best_fit(lengths, counts, capacity))}


def pack(parts: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """``parts`` with a ``length`` of 1..capacity → the same rows plus ``sequence_id`` and ``offset``.

    The k-th piece of a length goes where the plan puts the k-th of that length. Pieces are numbered within a length by
    buckets and prefix sums, so no task sorts all pieces of a common length. Ties are numbered in any order; an empty
    table gives an empty one.
    """
    parts = cut(parts)
    histogram = {r["length"]: r["n"] for r in parts.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}
    total = sum(histogram.values())
    at: dict[int, list[tuple[int, int, int]]] = {}
    used: dict[int, int] = {}
    base = 0
    for content, n in plan(histogram, capacity):
        offset = 0
        for length in content:
            k = used.get(length, 0)
            at.setdefault(length, []).append((k, base, offset))
            used[length] = k + n
            offset += length
        base += n
    table = np.array([(length << 44 | k, k, b, o) for length in sorted(at) for k, b, o in at[length]] or [(0, 0, 0, 0)], np.int64)
    buckets = max(16, total // 20_000)
    tagged = parts.withColumn("bucket_", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(buckets)))
    sums = tagged.groupBy("length", "bucket_").agg(F.count(F.lit(1)).alias("n_"))
    prior = Window.partitionBy("length").orderBy("bucket_").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.withColumn("base_", F.coalesce(F.sum("n_").over(prior), F.lit(0))).drop("n_")
    inside = Window.partitionBy("length", "bucket_").orderBy("doc_id", "piece")
    ranked = tagged.join(sums, ["length", "bucket_"]).withColumn("rank_", F.col("base_") + F.row_number().over(inside) - 1)
    names = parts.columns

    def run(batches):
        for batch in batches:
            columns = dict(zip(batch.schema.names, batch.columns, strict=True))
            length, rank = columns["length"].to_numpy(), columns["rank_"].to_numpy()
            row = table[np.searchsorted(table[:, 0], length << 44 | rank, "right") - 1]
            yield pa.RecordBatch.from_arrays([*(columns[c] for c in names), pa.array(row[:, 2] + rank - row[:, 1]), pa.array(row[:, 3])], names=[*names, "sequence_id", "offset"])

    kinds = ", ".join(f"{c} {t}" for c, t in parts.dtypes)
    return ranked.select(*names, "rank_").mapInArrow(run, f"{kinds}, sequence_id long, offset long")
