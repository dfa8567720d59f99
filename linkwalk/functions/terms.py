"""Names of nodes. An identifier is ``kind:key``; a literal is its text behind one quotation mark."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

MARK = '"'


def named(kind: str, *parts: Column | str) -> Column:
    return F.concat(F.lit(f"{kind}:"), F.concat_ws("-", *[F.col(p).cast("string") if isinstance(p, str) else p.cast("string") for p in parts]))


def literal(value: Column | str) -> Column:
    return F.concat(F.lit(MARK), (F.col(value) if isinstance(value, str) else value).cast("string"))


def lit_date(value: Column | str) -> Column:
    return literal(F.date_format(value, "yyyy-MM-dd"))


def is_literal(node: Column | str) -> Column:
    return F.startswith(F.col(node) if isinstance(node, str) else node, F.lit(MARK))


def kind_of(node: Column | str) -> Column:
    node = F.col(node) if isinstance(node, str) else node
    return F.when(is_literal(node), F.lit("literal")).otherwise(F.split_part(node, F.lit(":"), F.lit(1)))


def value_of(node: Column | str) -> Column:
    """A literal's text, or an identifier's key."""
    node = F.col(node) if isinstance(node, str) else node
    return F.when(is_literal(node), F.substr(node, F.lit(2))).otherwise(F.regexp_replace(node, "^[^:]*:", ""))


def host_of(url: Column | str) -> Column:
    return F.parse_url(F.col(url) if isinstance(url, str) else url, F.lit("HOST"))


def jitter(*columns: str, seed: int = 0) -> Column:
    """A number in [0, 1) that depends on the columns and the seed alone."""
    return F.pmod(F.xxhash64(*columns, F.lit(seed)), F.lit(1 << 20)) / float(1 << 20)


_PRIMES = (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5)
_ALL = (1 << 64) - 1


def _turn(x: int, n: int) -> int:
    x &= _ALL
    return (x << n | x >> (64 - n)) & _ALL


def _mixed(x: int) -> int:
    x &= _ALL
    x = (x ^ x >> 33) * _PRIMES[1] & _ALL
    x = (x ^ x >> 29) * _PRIMES[2] & _ALL
    return x ^ x >> 32


def _xxhash64(data: bytes, seed: int) -> int:
    a, b, c, d, e = _PRIMES
    word = lambda i, n: int.from_bytes(data[i : i + n], "little")
    step = lambda acc, x: _turn(acc + x * b, 31) * a & _ALL
    at = 0
    if len(data) >= 32:
        lanes = [seed + a + b, seed + b, seed, seed - a]
        while at + 32 <= len(data):
            lanes = [step(x, word(at + 8 * i, 8)) for i, x in enumerate(lanes)]
            at += 32
        h = sum(_turn(x, n) for x, n in zip(lanes, (1, 7, 12, 18), strict=True))
        for x in lanes:
            h = (h ^ step(0, x)) * a + d
    else:
        h = seed + e
    h += len(data)
    while at + 8 <= len(data):
        h = _turn((h ^ step(0, word(at, 8))) & _ALL, 27) * a + d
        at += 8
    if at + 4 <= len(data):
        h = _turn((h ^ word(at, 4) * a) & _ALL, 23) * b + c
        at += 4
    for x in data[at:]:
        h = _turn((h ^ x * e) & _ALL, 11) * a
    return _mixed(h)


def hash_of(value: str | int) -> int:
    """``F.xxhash64`` of one string or long, without Spark."""
    h = _xxhash64(value.encode() if isinstance(value, str) else value.to_bytes(8, "little", signed=True), 42)
    return h - (1 << 64) if h >> 63 else h


def jitter_of(text: str, seed: int = 0) -> float:
    """:func:`jitter` of one string, without Spark."""
    wide = 4 if -(1 << 31) <= seed < 1 << 31 else 8
    return _xxhash64((seed & (1 << 8 * wide) - 1).to_bytes(wide, "little"), _xxhash64(text.encode(), 42)) % (1 << 20) / float(1 << 20)
