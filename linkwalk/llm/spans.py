"""Pattern spans in code points, from built-in functions only.

``regexp_extract_all`` gives values but no places. Here every pattern is matched behind a lazy prefix that starts where the
last match ended, so the extracted pieces tile the text up to the last match, and running sums of their lengths are the
places. The anchor also ends the search at once after the last match, which keeps it linear. Sums are taken by doubling, and
parts of a text are read from an array of its blocks, so that a text with n matches costs n log n steps, whatever its length.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

BLOCK = 256
SPAN = "array<struct<kind:string,start:int,end:int,value:string,score:double>>"


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body(value)``, with the value computed once."""
    return F.element_at(F.transform(F.array(value), body), 1)


def running(values: Column, join: Callable[[Column, Column], Column]) -> Column:
    """Each element joined with all before it, for an associative ``join``: pass k joins elements 2**k apart, so an array of n
    elements is copied log2(n) times, not n times."""
    steps = F.transform(F.sequence(F.lit(0), F.ceil(F.log2(F.greatest(F.size(values), F.lit(1)))).cast("int")), lambda k: F.pow(F.lit(2.0), k).cast("int"))
    return F.aggregate(steps, values, lambda s, step: F.transform(s, lambda x, i: F.when(i >= step, join(F.get(s, i - step), x)).otherwise(x)))


def blocks(text: Column) -> Column:
    """The text cut into blocks of ``BLOCK`` code points, the last one shorter."""
    return F.regexp_extract_all(text, F.lit(r"(?s).{1,%d}" % BLOCK), F.lit(0))


def part(cut: Column, start: Column, end: Column) -> Column:
    """Code points ``start`` to ``end`` of the text behind :func:`blocks`; only the blocks that hold them are read. Places
    before or after the text are passed over."""
    a = F.greatest(start, F.lit(0))
    first, last = F.floor(a / BLOCK).cast("int"), F.floor((end - 1) / BLOCK).cast("int")
    held = F.array_join(F.slice(cut, first + 1, F.greatest(last - first + 1, F.lit(0))), "")
    return F.when(end > a, F.substr(held, a - first * BLOCK + 1, end - a)).otherwise("")


def none() -> Column:
    return F.array().cast(SPAN)


def find(text: Column, kind: str, pattern: str, gate: Column, keep: Callable[[Column], Column] | None = None) -> Column:
    """Leftmost non-overlapping matches of ``pattern`` that ``keep(value)`` confirms, as spans of score 1. ``gate`` must hold
    for every text with a match; it spares the others the search."""
    tiled = rf"(?s)\G(.*?)(?:{pattern})"

    def places(both: Column) -> Column:
        pieces, before = both["pieces"], both["before"]
        ends = running(F.transform(pieces, F.length), lambda a, b: a + b)
        return let(
            ends,
            lambda e: F.transform(
                pieces,
                lambda piece, i: F.struct(
                    F.lit(kind).alias("kind"),
                    (F.get(e, i) - F.length(piece) + F.length(F.get(before, i))).alias("start"),
                    F.get(e, i).alias("end"),
                    F.substr(piece, F.length(F.get(before, i)) + 1).alias("value"),
                    F.lit(1.0).alias("score"),
                ),
            ),
        )

    pieces = F.regexp_extract_all(text, F.lit(tiled), F.lit(0))
    found = let(pieces, lambda p: F.when(F.size(p) > 0, let(F.struct(p.alias("pieces"), F.regexp_extract_all(text, F.lit(tiled), F.lit(1)).alias("before")), places)))
    if keep:
        found = F.filter(found, lambda s: keep(s["value"]))
    return F.coalesce(F.when(gate, found), none())


def has(text: Column, *words: str) -> Column:
    """Whether the text holds one of ``words``."""
    out = F.lit(False)
    for w in words:
        out = out | F.contains(text, F.lit(w))
    return out


def listed(spans: Column) -> Column:
    """``kind:start:end`` of each, comma-joined, in the order given."""
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def by_start(spans: Column, kinds: list[str]) -> Column:
    """Sorted by start, then by the place of the kind in ``kinds``."""
    order = F.array(*map(F.lit, kinds))
    tagged = F.transform(spans, lambda s: F.struct(s["start"].alias("a"), F.array_position(order, s["kind"]).alias("b"), s.alias("s")))
    return F.transform(F.array_sort(tagged), lambda t: t["s"])


def count(spans: Column, kind: str) -> Column:
    return F.size(F.filter(spans, lambda s: s["kind"] == kind)).cast("long")
