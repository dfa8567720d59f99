"""Repeated passages by relative Lempel-Ziv parsing against all text that comes earlier.

The reference is every document, in order of id, cut into *blocks*: a block is a maximal run of ``span``-word windows that
share their minimiser (the least-hashed ``GRAM``-word gram in the window). Equal windows have equal minimisers at the same
offset, so they always meet under one index key, though only about one gram in nine is indexed.

* Index: per block its minimiser, a hash of all its words, its place. An Arrow batch sends only its first block of each
  content; later ones are factors already. Under each key the earliest block of each content is the reference.
* Factors: a block equal to an earlier one is copied whole. Where a key holds different contents, blocks match only in
  part: the windows at these factor boundaries are hashed and looked up one by one in the same way.
* Parse: each document joins its matches greedily, left to right, into the longest factors that keep the alignment to one
  reference place. All factors have ``span`` words or more; what no factor covers is literal text.

Minimiser plus content hash give 128-bit keys. Reference places always lie earlier (smaller id, or same id, earlier word).
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .storage import cut, names_out, release, with_uid
from .words import Hasher, chunks, find_words, kept_by_worker, mix, texts

GRAM = 5
BLOCK = "key long, content long, uid long, start int, n int, ref_uid long, ref_start int, send boolean"
_BLOCK = pa.schema([(c, {"long": pa.int64(), "int": pa.int32(), "boolean": pa.bool_()}[t]) for c, t in (x.split() for x in BLOCK.split(", "))])


def _hashers() -> tuple[Hasher, Hasher]:
    return kept_by_worker("substring", lambda: (Hasher(41), Hasher(42)))


def _hashed(flat: np.ndarray, offsets: np.ndarray, lo: int, hi: int):
    """Words of rows lo..hi: first word of each row, and prefix sums under two functions."""
    one, two = _hashers()
    b = flat[offsets[lo] : offsets[hi]]
    starts, ends, first = find_words(b, offsets[lo : hi + 1] - offsets[lo])
    h = one.words(b, starts, ends)
    return first, one.prefix(h), two.prefix(mix(h ^ np.uint64(0x9E3779B97F4A7C15)))


def _local(key, content, uid, start, n, shift=None) -> pa.RecordBatch:
    """Keeps one sender for each (key, content): the earliest; later ones point to it and stay home. Equal places of
    repeated rows cannot occur, for ``uid`` is unique."""
    order = np.lexsort((start, uid, content, key))
    key, content, uid, start, n = (x[order] for x in (key, content, uid, start, n))
    head = np.ones(len(key), bool)
    head[1:] = (key[1:] != key[:-1]) | (content[1:] != content[:-1])
    at = np.maximum.accumulate(np.where(head, np.arange(len(key)), 0)) if len(key) else np.zeros(0, np.int64)
    mask = head
    return pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(content.view(np.int64)), pa.array(uid), pa.array(start.astype(np.int32)), pa.array(n.astype(np.int32)), pa.array(uid[at], mask=mask), pa.array(start[at].astype(np.int32), mask=mask), pa.array(head)], schema=_BLOCK)


def _blocks(span: int):
    reach = span - GRAM + 1

    def run(batches):
        for batch in batches:
            ids = batch.column(0).to_numpy()
            flat, offsets = texts(batch.column(1))
            parts = []
            for lo, hi in chunks(offsets):
                first, sums, others = _hashed(flat, offsets, lo, hi)
                n = len(sums) - 1
                if n < span:
                    continue
                at = np.arange(n - GRAM + 1)
                grams = _hashers()[0].run(sums, at, at + GRAM)
                row = np.repeat(np.arange(lo, hi), np.diff(first))
                least = np.lib.stride_tricks.sliding_window_view(grams, reach).argmin(axis=1) + np.arange(n - span + 1)
                good = row[: n - span + 1] == row[span - 1 :]
                opens = good.copy()
                opens[1:] &= ~good[:-1] | (least[1:] != least[:-1]) | (row[1 : len(good)] != row[: len(good) - 1])
                w = np.flatnonzero(opens)
                stop = np.append(w[1:], len(good))
                # A block ends at the next block or at the last window of its row.
                stop = np.minimum(stop, first[row[w] - lo + 1] - span + 1)
                content = mix(_hashers()[1].run(others, w, stop + span - 1) ^ (least[w] - w).astype(np.uint64) ^ ((stop - w).astype(np.uint64) << np.uint64(32)))
                parts.append((grams[least[w]], content, ids[row[w]], w - first[row[w] - lo], stop - w))
            if parts:
                yield _local(*(np.concatenate(x) for x in zip(*parts, strict=True)))

    return run


def _windows(span: int):
    """Rows (uid, text, blocks): one record for each window of the given blocks."""

    def run(batches):
        for batch in batches:
            ids = batch.column(0).to_numpy()
            flat, offsets = texts(batch.column(1))
            lists = batch.column(2)
            flatter = lists.flatten()
            where = np.asarray(lists.offsets) - lists.offsets[0].as_py()
            key, start, n = (flatter.field(i).to_numpy(zero_copy_only=False) for i in range(3))
            parts = []
            for lo, hi in chunks(offsets):
                first, sums, others = _hashed(flat, offsets, lo, hi)
                a, z = where[lo], where[hi]
                row = np.repeat(np.arange(lo, hi), np.diff(where[lo : hi + 1]))
                k, s, m = key[a:z], start[a:z].astype(np.int64), n[a:z].astype(np.int64)
                step = np.arange(m.sum()) - np.repeat(np.cumsum(m) - m, m)
                w = np.repeat(s, m) + step
                g = np.repeat(first[row - lo], m) + w
                one, two = _hashers()
                parts.append((mix(one.run(sums, g, g + span) ^ np.repeat(k, m).view(np.uint64)), two.run(others, g, g + span), np.repeat(ids[row], m), w, np.ones(len(w), np.int64)))
            if parts:
                yield _local(*(np.concatenate(x) for x in zip(*parts, strict=True)))

    return run


def _earliest(rows: DataFrame, *keys: str) -> DataFrame:
    """Sent rows with the earliest place of their (key, content). A key holds one row for each content and Arrow batch at
    most, for batches have combined before the shuffle."""
    w = Window.partitionBy(*keys).orderBy("uid", "start")
    return rows.where("send").withColumn("ref_uid", F.first("uid").over(w)).withColumn("ref_start", F.first("start").over(w))


def matches(docs: DataFrame, text_col: str = "text", span: int = 20) -> DataFrame:
    """``docs`` has a unique long ``uid``. Returns ``(uid, start, n, ref_uid, ref_start)``: n consecutive windows from word
    ``start`` on that also start at word ``ref_start`` and on of ``ref_uid``, earlier."""
    source = docs.select("uid", F.col(text_col).alias("text"))
    found = cut(source.mapInArrow(_blocks(span), BLOCK))
    w = Window.partitionBy("key")
    sent = _earliest(found, "key", "content").withColumn("mixed", F.min("content").over(w) != F.max("content").over(w))
    sent = cut(sent.withColumn("later", (F.col("uid") != F.col("ref_uid")) | (F.col("start") != F.col("ref_start"))).where("mixed or later").drop("send", "content"))
    release(docs.sparkSession)
    out = ["uid", "start", "n", "ref_uid", "ref_start"]
    partly = sent.where("mixed and not later").groupBy("uid").agg(F.collect_list(F.struct("key", "start", "n")).alias("blocks"))
    single = cut(source.join(partly, "uid").select("uid", "text", "blocks").mapInArrow(_windows(span), BLOCK))
    release(docs.sparkSession)
    late = _earliest(single, "key", "content").where("uid <> ref_uid or start <> ref_start")
    return found.where("not send").select(out).unionByName(sent.where("later").select(out)).unionByName(single.where("not send").select(out)).unionByName(late.select(out))


def parse(start, n, ref_uid, ref_start, span: int) -> list[tuple[int, int, int, int]]:
    """Greedy factors ``(start, words, ref_uid, ref_start)`` of one document from its matches, in order of start."""
    order = np.lexsort((n, start))
    runs: list[list[int]] = []
    open_: dict[tuple[int, int], list[int]] = {}
    for i in order.tolist():
        s, m, u, r = int(start[i]), int(n[i]), int(ref_uid[i]), int(ref_start[i])
        held = open_.get((u, r - s))
        if held and s <= held[1]:
            held[1] = max(held[1], s + m)
        else:
            open_[u, r - s] = held = [s, s + m, u, r]
            runs.append(held)
    factors, reach, i = [], 0, 0
    while i < len(runs):
        # Of the runs that start at or before the first uncovered window, take the one that reaches furthest.
        at, best = max(reach, runs[i][0]), None
        while i < len(runs) and runs[i][0] <= at:
            if runs[i][1] > at and (best is None or runs[i][1] > best[1]):
                best = runs[i]
            i += 1
        if best is None:
            continue
        factors.append((at, best[1] - at + span - 1, best[2], best[3] + at - best[0]))
        reach = best[1]
        while i and runs[i - 1][1] > reach:
            i -= 1
    return factors


PARSED = "n_words long, n_removed long, kept_text string, kept_sha256 string, factors array<struct<start:long,words:long,ref_uid:long,ref_start:long>>"


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", span: int = 20, digest: bool = False) -> DataFrame:
    """Input columns plus ``n_words``, ``n_removed``, ``kept_text``, ``kept_sha256`` and ``factors`` (starts and lengths in
    words; neighbouring factors may overlap by up to span - 1 words; ``ref_uid`` is the id where ids are unique).

    A word goes when a window of ``span`` words covers it whose words also start earlier: in a smaller id, or earlier in the
    same document. Null and empty texts have no words. Rows whose ids are null or repeated are documents of their own, null
    ids last, repeated ones in an order by text hash. An empty table gives an empty one. ``digest`` leaves out the texts and
    the other input columns but the id. Input columns with the name of an added one come back with ``_in`` appended.
    """
    given = [id_col, text_col] if digest else docs.columns
    own = docs.select(*[F.col(f"`{c}`").alias(f"in_{i}") for i, c in enumerate(given)])
    id_at, text_at = f"in_{given.index(id_col)}", f"in_{given.index(text_col)}"
    source = with_uid(own, id_at, text_at)
    hits = matches(source, text_at, span).groupBy("uid").agg(*[F.collect_list(c).alias(c) for c in ("start", "n", "ref_uid", "ref_start")])
    names = [x for x in source.columns if not (digest and x == text_at)]

    def run(batches):
        for batch in batches:
            column = dict(zip(batch.schema.names, batch.columns, strict=True))
            flat, offsets = texts(column[text_at])
            raw, out = flat.tobytes(), []
            for lo, hi in chunks(offsets):
                base = int(offsets[lo])
                starts, ends, first = find_words(flat[base : offsets[hi]], offsets[lo : hi + 1] - base)
                for d in range(lo, hi):
                    a, z = int(first[d - lo]), int(first[d - lo + 1])
                    factors = []
                    if column["start"][d].is_valid:
                        get = lambda c: column[c][d].values.to_numpy()  # noqa: B023, E731
                        factors = parse(get("start"), get("n"), get("ref_uid"), get("ref_start"), span)
                    gone = np.zeros(z - a, bool)
                    for s, m, *_ in factors:
                        gone[s : s + m] = True
                    keep = np.flatnonzero(~gone) + a
                    kept = b" ".join([raw[base + x : base + y] for x, y in zip(starts[keep].tolist(), ends[keep].tolist(), strict=True)])
                    out.append((z - a, int(gone.sum()), None if digest else kept.decode(), hashlib.sha256(kept).hexdigest(), [dict(zip(("start", "words", "ref_uid", "ref_start"), f, strict=True)) for f in factors]))
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.list_(pa.struct([(c, pa.int64()) for c in ("start", "words", "ref_uid", "ref_start")]))]
            made = [pa.array([x[i] for x in out], k) for i, k in enumerate(kinds)]
            yield pa.RecordBatch.from_arrays([column[c] for c in names] + made, names=[*names, "n_words", "n_removed", "kept_text", "kept_sha256", "factors"])

    kinds = ", ".join(f"{c} {t}" for c, t in source.dtypes if c in names)
    out = source.join(hits, "uid", "left").mapInArrow(run, f"{kinds}, {PARSED}")
    named = names_out(given, ["n_words", "n_removed", "kept_text", "kept_sha256", "factors"])
    return out.select(*[F.col(f"in_{i}").alias(c) for i, c in enumerate(named) if f"in_{i}" in names], "n_words", "n_removed", "kept_text", "kept_sha256", "factors")
