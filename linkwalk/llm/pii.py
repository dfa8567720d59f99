"""Personal data: patterns propose, checksums confirm, context words score. Built-in functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .spans import blocks, find, has, let, part, running
from .storage import names_out

BASE = ["email", "ip", "card", "phone"]
ADDED = ["iban"]
#: Whole words that raise the score of a span of the kind when they stand near it, and words that speak against it.
CONTEXT = {
    "email": ["mail", "email", "contact", "write"],
    "ip": ["ip", "host", "server", "address", "login"],
    "card": ["card", "visa", "credit", "payment", "mastercard"],
    "phone": ["phone", "call", "tel", "telephone", "mobile", "fax"],
    "iban": ["iban", "bank", "account", "konto"],
}
AGAINST = {
    "email": ["placeholder"],
    "ip": ["version", "release", "chapter", "section"],
    "card": ["isbn", "serial", "tracking", "barcode"],
    "phone": ["isbn", "serial", "tracking", "version"],
    "iban": ["serial", "checksum"],
}
#: Score of a confirmed span, what context adds or takes, and how many code points on each side count as near.
START, FOR, LESS, NEAR = 0.6, 0.35, 0.3, 40


def digits(value: Column) -> Column:
    return F.regexp_replace(value, "[^0-9]", "")


def luhn(number: Column) -> Column:
    """Whether a string of digits passes the Luhn check."""
    one = lambda c, i: F.when(i % 2 == 0, c.cast("int")).otherwise((c.cast("int") * 2) % 10 + F.floor(c.cast("int") / 5).cast("int"))
    each = F.transform(F.filter(F.split(F.reverse(number), ""), lambda c: c != ""), one)
    return F.aggregate(each, F.lit(0), lambda a, x: a + x) % 10 == 0


def mod97(code: Column) -> Column:
    """Whether an account code leaves 1 modulo 97 with its first four characters moved to the end."""
    moved = F.filter(F.split(F.concat(F.substring(code, 5, 40), F.substring(code, 1, 4)), ""), lambda c: c != "")
    value = lambda c: F.when(c.between("0", "9"), F.ascii(c) - 48).otherwise(F.ascii(c) - 55)
    return F.aggregate(F.transform(moved, value), F.lit(0), lambda a, x: F.when(x < 10, a * 10 + x).otherwise(a * 100 + x) % 97) == 1


def _scored(found: Column, cut: Column, n: Column) -> Column:
    """Spans with scores: whole words within ``NEAR`` code points count; a word that the edge cuts, or touches, does not."""
    of = lambda words: F.create_map(*[x for k in BASE + ADDED for x in (F.lit(k), F.array(*map(F.lit, words[k])))])
    edge = lambda s: F.when(s["start"] > NEAR, F.regexp_replace(part(cut, s["start"] - NEAR, s["start"]), "^[A-Za-z]+", "")).otherwise(part(cut, F.lit(0), s["start"]))
    tail = lambda s: F.when(s["end"] + NEAR < n, F.regexp_replace(part(cut, s["end"], s["end"] + NEAR), r"[A-Za-z]+\z", "")).otherwise(part(cut, s["end"], n))

    def one(s: Column) -> Column:
        words = F.transform(F.regexp_extract_all(F.concat_ws(" ", edge(s), tail(s)), F.lit("[A-Za-z]+"), F.lit(0)), F.lower)
        near = lambda w, table: F.arrays_overlap(w, F.element_at(of(table), s["kind"])).cast("int")
        score = let(words, lambda w: F.round(START + FOR * near(w, CONTEXT) - LESS * near(w, AGAINST), 2))
        return F.struct(s["kind"].alias("kind"), s["start"].alias("start"), s["end"].alias("end"), s["value"].alias("value"), score.alias("score"))

    return F.transform(found, one)


def pii_spans(text: Column) -> Column:
    """All spans of a text, kind by kind in the order of ``BASE + ADDED``, each kind by start; null counts as empty.

    The patterns are written so that no text makes them backtrack over long runs: repeats are possessive where nothing can
    follow them, and a run that failed is not tried again from its middle.
    """
    t = F.coalesce(text, F.lit(""))
    parts = lambda v: F.forall(F.split(v, r"\."), lambda p: F.length(F.ltrim(p, F.lit("0"))) <= 3) & F.forall(F.split(v, r"\."), lambda p: F.substring(F.concat(F.lit("00"), p), -3, 3).cast("int") <= 255)
    email = r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"
    every = F.concat(
        find(t, "email", email, has(t, "@")),
        find(t, "ip", r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++", t.rlike(r"[0-9]\.[0-9]++\.[0-9]++\.[0-9]"), parts),
        find(t, "card", r"[0-9](?:[\x20-]?[0-9])++", t.rlike(r"[0-9](?:[\x20-]?[0-9]){12}"), lambda v: F.length(digits(v)).between(13, 19) & luhn(digits(v))),
        find(t, "phone", r"\+[0-9][\x20().0-9-]+[0-9]", has(t, "+"), lambda v: F.length(digits(v)).between(9, 15)),
        find(t, "iban", r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}[A-Z0-9]{11,30}+(?![A-Za-z0-9])", t.rlike(r"[A-Z]{2}[0-9]{2}[A-Z0-9]{11}"), mod97),
    )
    return let(every, lambda e: F.when(F.size(e) > 0, let(blocks(t), lambda cut: let(F.length(t), lambda n: _scored(e, cut, n)))).otherwise(e))


def find_pii(docs: DataFrame, text_col: str = "text", name: str = "pii") -> DataFrame:
    """Input columns plus ``name``: an array of (kind, start, end, value, score); places in code points, end exclusive.

    Null and empty texts have no span; rows are handled one by one, so nulls elsewhere, ties, repeated rows and an empty
    table need no rule. An input column called ``name`` comes back with ``_in`` appended.
    """
    out = names_out(docs.columns, [name])
    return docs.select(*[F.col(f"`{c}`").alias(o) for c, o in zip(docs.columns, out, strict=True)], pii_spans(F.col(f"`{text_col}`")).alias(name))


def redact(text: Column, spans: Column, least: float = 0.5) -> Column:
    """The text with every span of at least that score replaced by its kind in angle brackets; of spans that overlap, the
    one that starts first (then the longer) stands, and what it covers goes with it. A span that context speaks against,
    with no word for it, scores below ``least`` and stays."""
    order = F.transform(F.filter(spans, lambda s: s["score"] >= least), lambda s: F.struct(s["start"].alias("start"), (-s["end"]).alias("back"), s["end"].alias("end"), s["kind"].alias("kind")))

    def masked(c: Column, cut: Column, reach: Column) -> Column:
        # ``reach`` is how far spans have covered the text; what lies before it is written or gone.
        before = lambda i: F.coalesce(F.get(reach, i - 1), F.lit(0))
        fresh = F.transform(c, lambda s, i: F.when(s["start"] >= before(i), F.concat(part(cut, before(i), s["start"]), F.lit("<"), F.upper(s["kind"]), F.lit(">"))).otherwise(""))
        return F.concat(F.array_join(fresh, ""), part(cut, F.array_max(reach), F.length(text)))

    joined = lambda c: let(blocks(text), lambda cut: let(running(F.transform(c, lambda s: s["end"]), lambda a, b: F.greatest(a, b)), lambda reach: masked(c, cut, reach)))
    return let(F.array_sort(order), lambda c: F.when(F.size(c) > 0, joined(c)).otherwise(text))
