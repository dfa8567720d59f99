"""SQL twins of the span queries, for DuckDB: its expressions find leftmost non-overlapping matches too, and a lazy prefix
before each match gives the places."""

from __future__ import annotations

from .pii import AGAINST, CONTEXT


def _found(kinds: dict[str, tuple[str, str]]) -> str:
    """``f(doc_id, kind, k, a, b, v)``: confirmed spans; each kind has a pattern and a condition on the value v."""
    raw = " UNION ALL ".join(f"SELECT doc_id, '{kind}' AS kind, {k} AS k, regexp_extract_all(t, '(?s)(.*?)({pattern})', 0) AS w, regexp_extract_all(t, '(?s)(.*?)({pattern})', 1) AS p FROM d" for k, (kind, (pattern, _)) in enumerate(kinds.items()))
    keep = " OR ".join(f"(kind = '{kind}' AND {condition})" for kind, (_, condition) in kinds.items())
    return f"""d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
r AS ({raw}),
u AS (SELECT doc_id, kind, k, i, length(w[i]) AS n, length(p[i]) AS h, substr(w[i], length(p[i]) + 1) AS v FROM (SELECT *, unnest(range(1, len(w) + 1)) AS i FROM r)),
s AS (SELECT *, sum(n) OVER (PARTITION BY doc_id, kind ORDER BY i) AS e FROM u),
f AS (SELECT doc_id, kind, k, (e - n + h)::BIGINT AS a, e::BIGINT AS b, v FROM s WHERE {keep})"""


def _listed(kinds: dict[str, tuple[str, str]], base: list[str], order: str, score: str = "") -> str:
    counts = ", ".join(f"count(*) FILTER (WHERE kind = '{k}') AS n_{k}" for k in base)
    names = ", ".join(f"'{k}'" for k in base)
    one = "kind || ':' || a || ':' || b"
    more, scores = (", string_agg(score, ',' ORDER BY " + order + ") AS scores", ", coalesce(scores, '') AS scores") if score else ("", "")
    rated = f", f AS (SELECT *, ({score})::VARCHAR AS score FROM {_NEAR})" if score else ""
    return f"""WITH {_found(kinds).replace("f AS (", "f0 AS (") if score else _found(kinds)}{rated},
g AS (SELECT doc_id, {counts}{more}, string_agg({one}, ',' ORDER BY {order}) AS every, string_agg({one}, ',' ORDER BY {order}) FILTER (WHERE kind IN ({names})) AS base FROM f GROUP BY doc_id)
SELECT d.doc_id, {', '.join(f'coalesce(n_{k}, 0)::BIGINT AS n_{k}' for k in base)}, sha256(coalesce(base, '')) AS base_sha256, coalesce(every, '') AS spans{scores} FROM d LEFT JOIN g USING (doc_id)"""


#: Spans with the whole words near them.
_NEAR = """(SELECT f0.*, list_transform(regexp_extract_all(CASE WHEN a > 40 THEN regexp_replace(substr(t, a - 39, 40), '^[A-Za-z]+', '') ELSE substr(t, 1, a) END || ' ' || CASE WHEN b + 40 < length(t) THEN regexp_replace(substr(t, b + 1, 40), '[A-Za-z]+$', '') ELSE substr(t, b + 1) END, '[A-Za-z]+'), lambda x: lower(x)) AS near FROM f0 JOIN d USING (doc_id))"""


def _score(start: int, up: int, down: int, plus: dict[str, list[str]], minus: dict[str, list[str]]) -> str:
    case = lambda t: "CASE kind " + " ".join(f"WHEN '{k}' THEN list_has_any(near, {w})" for k, w in t.items()) + " END::INTEGER"
    return f"{start} + {up} * {case(plus)} - {down} * {case(minus)}"


_DIGITS = "regexp_replace(v, '[^0-9]', '', 'g')"
_LUHN = f"list_sum(list_transform(range(1, length({_DIGITS}) + 1), lambda i: CASE WHEN i % 2 = 1 THEN reverse({_DIGITS})[i]::INT ELSE (reverse({_DIGITS})[i]::INT * 2) % 10 + reverse({_DIGITS})[i]::INT // 5 END)) % 10 = 0"
_MOVED = "(substr(v, 5) || substr(v, 1, 4))"
_MOD97 = f"list_reduce(list_prepend(0, list_transform(range(1, length({_MOVED}) + 1), lambda i: CASE WHEN ascii({_MOVED}[i]) < 58 THEN ascii({_MOVED}[i]) - 48 ELSE ascii({_MOVED}[i]) - 55 END)), lambda x, y: CASE WHEN y < 10 THEN (x * 10 + y) % 97 ELSE (x * 100 + y) % 97 END) = 1"

PII_SQL = _listed(
    {
        "email": (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+", "true"),
        "ip": (r"[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+", r"len(list_filter(string_split(v, '.'), lambda x: length(ltrim(x, '0')) > 3 OR (length(ltrim(x, '0')) = 3 AND ltrim(x, '0') > '255'))) = 0"),
        "card": (r"[0-9](?:[\x20-]?[0-9])+", f"length({_DIGITS}) BETWEEN 13 AND 19 AND {_LUHN}"),
        "phone": (r"\+[0-9][\x20().0-9-]+[0-9]", f"length({_DIGITS}) BETWEEN 9 AND 15"),
        "iban": ("[A-Za-z0-9]+", f"regexp_full_match(v, '[A-Z][A-Z][0-9][0-9][A-Z0-9]{{11,30}}') AND {_MOD97}"),
    },
    ["email", "ip", "card", "phone"],
    "k, a",
    _score(60, 35, 30, CONTEXT, AGAINST),
)


def _any_case(words: list[str]) -> str:
    spelled = ["".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in w) for w in words]
    return "(?:" + "|".join(spelled) + ")"


_HEAD = _any_case(["password", "passwd", "secret", "token", "api_?key"]) + r"""["'']?\x20*[:=]\x20*["'']?"""
SECRETS_SQL = _listed(
    {
        "assign": (_HEAD + r"[A-Za-z0-9+/_.=-]+", f"length(regexp_extract(v, '^{_HEAD}([A-Za-z0-9+/_.=-]+)$', 1)) >= 6"),
        "access": (r"AKIA[A-Z0-9]+", "length(v) >= 20"),
        "hex": (r"[0-9a-f]+", "length(v) >= 24"),
        "pem": (r"-----BEGIN [A-Z ]{0,40}PRIVATE KEY-----", "true"),
        "jwt": (r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}", "true"),
    },
    ["assign", "access", "hex"],
    "a, k",
)
