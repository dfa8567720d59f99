"""SQL twins of graph queries, for DuckDB over the same tables."""

from __future__ import annotations

from collections.abc import Iterable

from .automaton import INF, Automaton, compile_path, heuristic

#: The triples of each (source, label), as SQL over the given tables.
TRIPLES: dict[tuple[str, str], str] = {
    ("supply", "contains"): "SELECT 'order:' || l_orderkey AS s, 'part:' || l_partkey AS o FROM lineitem",
    ("supply", "filled_by"): "SELECT 'order:' || l_orderkey AS s, 'supplier:' || l_suppkey AS o FROM lineitem",
    ("supply", "supplies"): "SELECT 'supplier:' || l_suppkey AS s, 'part:' || l_partkey AS o FROM lineitem",
    ("sales", "placed_by"): "SELECT 'order:' || o_orderkey AS s, 'customer:' || o_custkey AS o FROM orders",
    ("sales", "dated"): "SELECT 'order:' || o_orderkey AS s, '\"' || strftime(o_orderdate, '%Y-%m-%d') AS o FROM orders",
    ("sales", "status"): "SELECT 'order:' || o_orderkey AS s, '\"' || o_orderstatus AS o FROM orders",
    ("sales", "name"): "SELECT 'customer:' || c_custkey AS s, '\"' || c_name AS o FROM customer",
    ("geo", "in_nation"): "SELECT 'customer:' || c_custkey AS s, 'nation:' || c_nationkey AS o FROM customer UNION ALL SELECT 'supplier:' || s_suppkey, 'nation:' || s_nationkey FROM supplier",
    ("geo", "in_region"): "SELECT 'nation:' || n_nationkey AS s, 'region:' || r_regionkey AS o FROM nation JOIN region ON n_regionkey = r_regionkey",
    ("geo", "name"): "SELECT 'nation:' || n_nationkey AS s, '\"' || n_name AS o FROM nation UNION ALL SELECT 'region:' || r_regionkey, '\"' || r_name FROM region UNION ALL SELECT 'supplier:' || s_suppkey, '\"' || s_name FROM supplier",
    ("catalog", "label"): "SELECT 'part:' || p_partkey AS s, '\"' || p_name AS o FROM part",
    ("catalog", "brand"): "SELECT 'part:' || p_partkey AS s, '\"' || p_brand AS o FROM part",
    ("catalog", "kind"): "SELECT 'part:' || p_partkey AS s, '\"' || p_type AS o FROM part",
    ("clicks", "actor"): "SELECT 'event:' || event_id AS s, 'user:' || user_id AS o FROM events",
    ("clicks", "about"): "SELECT 'event:' || event_id AS s, 'topic:' || json_extract_string(props, '$.k') AS o FROM events",
    ("clicks", "followed_by"): "SELECT s, o FROM (SELECT 'event:' || event_id AS s, 'event:' || lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS o FROM events) WHERE o IS NOT NULL",
    ("clicks", "same_as"): "SELECT DISTINCT 'user:' || user_id AS s, 'customer:' || c_custkey AS o FROM events JOIN customer ON user_id = c_custkey",
    ("web", "on_host"): "SELECT 'page:' || page_id AS s, 'host:' || regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS o FROM pages",
    ("web", "anchors"): "SELECT 'page:' || page_id AS s, 'ref:' || unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS o FROM pages",
    ("web", "links_to"): "SELECT s, 'url:' || host || href AS o FROM (SELECT 'page:' || page_id AS s, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages)",
    ("corpus", "in_lang"): "SELECT 'doc:' || doc_id AS s, 'lang:' || lang AS o FROM documents",
    ("corpus", "from_source"): "SELECT 'doc:' || doc_id AS s, 'source:' || source AS o FROM documents",
    ("corpus", "copy_of"): "SELECT 'doc:' || doc_id AS s, 'doc:' || first AS o FROM (SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS first FROM documents) WHERE doc_id <> first",
    ("corpus", "quotes"): "SELECT 'doc:' || doc_id AS s, 'item:' || item_id AS o FROM documents d JOIN benchmark b ON contains(d.text, b.text)",
    ("corpus", "rated"): "SELECT 'doc:' || doc_id AS s, 'quality:' || quality AS o FROM labels",
    ("dialog", "next"): "SELECT s, o FROM (SELECT 'turn:' || conv_id || '-' || turn AS s, 'turn:' || conv_id || '-' || lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS o FROM conversations) WHERE o IS NOT NULL",
    ("vectors", "cluster"): "SELECT 'vec:' || vec_id AS s, 'cluster:' || label AS o FROM embeddings",
    ("vectors", "near"): "SELECT 'vec:' || a AS s, 'vec:' || b AS o FROM (SELECT a.vec_id AS a, b.vec_id AS b, row_number() OVER (PARTITION BY a.vec_id ORDER BY list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) DESC, b.vec_id) AS r FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) WHERE r <= 3",
}


def triples_sql(sources: Iterable[str], labels: Iterable[str] | None = None) -> str:
    """A query of ``(s, p, o)`` with each triple once, over the given sources."""
    wanted = None if labels is None else set(labels)
    parts = [f"SELECT s, '{p}' AS p, o FROM ({sql})" for (src, p), sql in TRIPLES.items() if src in sources and (wanted is None or p in wanted)]
    return "SELECT DISTINCT s, p, o FROM (" + " UNION ALL ".join(parts or ["SELECT '' AS s, '' AS p, '' AS o WHERE false"]) + ") WHERE s IS NOT NULL AND o IS NOT NULL"


def delta_sql(a: Automaton) -> str:
    rows = []
    for q in range(a.size):
        for rank, (s, t) in enumerate(a.outgoing(q)):
            names = [s.label] if s.label else sorted(s.excluded)
            listed = "[" + ", ".join(f"'{x}'" for x in names) + "]"
            rows.append(f"({q}, {listed}, {str(s.inv).lower()}, {str(s.label is None).lower()}, {t}, {rank})")
    return "SELECT * FROM (VALUES " + ", ".join(rows or ["(NULL, [''], NULL, NULL, NULL, NULL)"]) + ") AS t(q, names, inv, negated, q2, t_rank)"


def walk_ctes(expr: str, sources: Iterable[str], start_sql: str, cap: int, partial: float | None = None) -> str:
    """Common table expressions down to ``walk(seed, node, q, d)``: product nodes with every length up to ``cap``."""
    a = compile_path(expr)
    dropped = "" if partial is None else f" WHERE NOT inv OR substr(md5(s || '|' || p || '|' || o), 1, 2) < '{round(partial * 256):02x}'"
    return f"""t AS MATERIALIZED ({triples_sql(sources, a.labels)}),
adj AS MATERIALIZED (SELECT node, p, inv, nbr FROM (SELECT s AS node, p, false AS inv, o AS nbr, s, o FROM t UNION ALL SELECT o, p, true, s, s, o FROM t){dropped}),
delta AS ({delta_sql(a)}),
edge AS MATERIALIZED (SELECT node, q, nbr, q2, p, adj.inv AS inv, t_rank FROM adj JOIN delta ON adj.inv = delta.inv AND list_contains(names, p) <> negated),
walk(seed, node, q, d) AS (SELECT seed, seed, 0, 0 FROM ({start_sql}) UNION SELECT seed, nbr, q2, d + 1 FROM walk JOIN edge USING (node, q) WHERE d < {cap})"""


def reach_sql(expr: str, sources: Iterable[str], start: str, cap: int, partial: float | None = None) -> str:
    """``(node, length)`` of all answers from ``start``; ``cap`` is at least the largest length there."""
    finals = sorted(compile_path(expr).finals)
    where = f"q IN ({', '.join(map(str, finals))})" if finals else "false"
    return f"WITH RECURSIVE {walk_ctes(expr, sources, f'''SELECT '{start}' AS seed''', cap, partial)}\nSELECT node, min(d)::INTEGER AS length FROM walk WHERE {where} GROUP BY node"


def pairs_sql(expr: str, sources: Iterable[str], start_sql: str, cap: int) -> str:
    """``(seed, node, length)`` for the starts that a query gives."""
    finals = ", ".join(map(str, sorted(compile_path(expr).finals)))
    return f"WITH RECURSIVE {walk_ctes(expr, sources, start_sql, cap)}\nSELECT seed, node, min(d)::INTEGER AS length FROM walk WHERE q IN ({finals}) GROUP BY seed, node"


def _state_ctes(expr: str, sources: Iterable[str], start: str, strategy: str, k: int, guide: str, tie: str, most: int) -> str:
    """Common table expressions of a search over whole documents, down to ``st``: the state after every round, as rows. A step
    picks the next ``k`` open rows and merges what they lead to, until ``most`` lookups are ``done``. A row of ``hop`` without
    neighbour stands for the picked node itself."""
    a = compile_path(expr)
    h = heuristic(a, guide) if strategy == "astar" else dict.fromkeys(range(a.size), 0.0)
    dead = heuristic(a, "pathmax")
    guides = ", ".join(f"({q}, {float(h[q])}::DOUBLE)" for q in range(a.size) if h[q] < INF and dead[q] < INF)
    best = strategy == "astar"
    order = f"g + h, {'h, ' if tie == 'low_h' else ''}seq {'DESC' if tie == 'lifo' else 'ASC'}" if best else f"seq {'DESC' if strategy == 'dfs' else 'ASC'}"
    ctes = walk_ctes(expr, sources, f"SELECT '{start}' AS seed", 0).rsplit("walk(seed", 1)[0]
    route = f"{{'g': {'g + 1' if best else '0'}, 't': {'-' if strategy == 'dfs' else ''}place, 'v': via, 'n': s.node, 'q': s.q, 'l': g + 1}}"
    better = "r IS NOT NULL AND (old_seq IS NULL" + (" OR r.l < old_g)" if best else ")")
    return f"""{ctes}
guide(q, h) AS (VALUES {guides}),
hop AS MATERIALIZED (
  SELECT node, q, nbr, q2, min({{'a': t_rank, 'b': p, 'c': inv}}) AS via FROM edge GROUP BY node, q, nbr, q2
  UNION ALL SELECT DISTINCT node, q, NULL, NULL, NULL FROM edge),
st(round, done, node, q, g, seq, open, pos, paid) AS (
  SELECT 0, 0::BIGINT, '{start}', 0, 0::DOUBLE, {{'r': 0, 't': 0::BIGINT, 'v': {{'a': 0, 'b': '', 'c': false}}, 'n': '', 'q': 0}}, true, NULL::BIGINT, NULL::DOUBLE
  UNION ALL
  SELECT round + 1, done + picked, node, q, CASE WHEN {better} THEN r.l ELSE old_g END,
    coalesce(old_seq, {{'r': round + 1, 't': r.t, 'v': r.v, 'n': node, 'q': q}}),
    CASE WHEN {better} THEN q IN (SELECT q FROM guide) AND NOT starts_with(node, '"') ELSE old_open AND pos IS NULL END,
    pos, CASE WHEN pos IS NOT NULL THEN old_g END
  FROM (
    SELECT round, done, picked, coalesce(nbr, s.node) AS node, coalesce(q2, s.q) AS q, max(g) FILTER (nbr IS NULL) AS old_g, max(seq) FILTER (nbr IS NULL) AS old_seq,
      bool_or(open) FILTER (nbr IS NULL) AS old_open, max(place) FILTER (nbr IS NULL AND place <= room) AS pos, min({route}) FILTER (nbr IS NOT NULL) AS r
    FROM (
      SELECT *, count(*) FILTER (place <= room) OVER () AS picked
      FROM (SELECT st.*, least({k}, {most} - done) AS room, CASE WHEN open THEN row_number() OVER (PARTITION BY open ORDER BY {order}) END AS place FROM st LEFT JOIN guide USING (q) WHERE round < {most} AND done < {most})) AS s
      LEFT JOIN hop ON hop.node = s.node AND hop.q = s.q AND place <= room
    GROUP BY ALL))"""


def _stack_ctes(expr: str, sources: Iterable[str], start: str) -> str:
    """Common table expressions of a whole depth-first search, one lookup after the other, down to the one row of ``st``: numbers of
    product nodes on the stack, one bit for each that was met, and what was looked up and met so far, in order. In ``ids`` those that
    are never looked up are negative."""
    a = compile_path(expr)
    dead = heuristic(a, "pathmax")
    live = ", ".join(str(q) for q in range(a.size) if dead[q] < INF) or "NULL"
    ctes = walk_ctes(expr, sources, f"SELECT '{start}' AS seed", 0).rsplit("walk(seed", 1)[0]
    return f"""{ctes}
hop AS MATERIALIZED (SELECT node, q, nbr, q2, min({{'a': t_rank, 'b': p, 'c': inv}}) AS via FROM edge GROUP BY node, q, nbr, q2),
met AS MATERIALIZED (
  SELECT node, q, q IN ({live}) AND NOT starts_with(node, '"') AS live, row_number() OVER (ORDER BY node, q) AS id
  FROM (SELECT node, q FROM hop UNION SELECT nbr, q2 FROM hop UNION SELECT '{start}', 0)),
way AS MATERIALIZED (SELECT a.id AS here, list(CASE WHEN b.live THEN b.id ELSE -b.id END ORDER BY via, b.node, b.q) AS ids FROM hop JOIN met a USING (node, q) JOIN met b ON b.node = nbr AND b.q = q2 GROUP BY a.id),
st(one, stack, seen, looked, born) USING KEY (one) AS (
  SELECT 1, CASE WHEN live THEN [{{'id': id, 'g': 0}}] ELSE [] END, set_bit(bitstring('0', (SELECT count(*) + 1 FROM met)::INTEGER), id::INTEGER, 1),
    []::STRUCT(id BIGINT, g INTEGER)[], [{{'id': id, 'g': 0, 'n': 0}}]
  FROM met WHERE node = '{start}' AND q = 0
  UNION ALL
  SELECT 1, stack[:-2] || [{{'id': x, 'g': top.g + 1}} FOR x IN kids IF x > 0], CASE WHEN len(kids) = 0 THEN seen ELSE seen | marks END,
    list_append(looked, top), born || [{{'id': abs(x), 'g': top.g + 1, 'n': len(looked) + 1}} FOR x IN kids]
  FROM (
    SELECT *, list_aggregate([set_bit(seen & ~seen, abs(x)::INTEGER, 1) FOR x IN kids], 'bit_or') AS marks
    FROM (
      SELECT stack, seen, looked, born, top, coalesce([x FOR x IN ids IF get_bit(seen, abs(x)::INTEGER) = 0], []) AS kids
      FROM (SELECT *, stack[-1] AS top FROM st WHERE len(stack) > 0) LEFT JOIN way ON here = top.id)))"""


def whole_order_sql(expr: str, sources: Iterable[str], start: str) -> str:
    """``(req, node, q, g)``: all lookups of depth-first search in order."""
    return f"""WITH RECURSIVE {_stack_ctes(expr, sources, start)}
SELECT req::INTEGER AS req, node, q::INTEGER AS q, x.g::DOUBLE AS g FROM (SELECT unnest(looked) AS x, generate_subscripts(looked, 1) AS req FROM st) JOIN met ON id = x.id"""


def whole_emission_sql(expr: str, sources: Iterable[str], start: str) -> str:
    """``(rank, node, length, req_at_emit)``: all answers of depth-first search, after the lookup that first met them."""
    finals = ", ".join(map(str, sorted(compile_path(expr).finals)))
    return f"""WITH RECURSIVE {_stack_ctes(expr, sources, start)},
goal AS (SELECT node, x, place FROM (SELECT unnest(born) AS x, generate_subscripts(born, 1) AS place FROM st) JOIN met ON id = x.id WHERE q IN ({finals}) QUALIFY row_number() OVER (PARTITION BY node ORDER BY place) = 1)
SELECT row_number() OVER (ORDER BY place)::INTEGER AS rank, node, x.g::DOUBLE AS length, x.n::BIGINT AS req_at_emit FROM goal"""


def order_sql(expr: str, sources: Iterable[str], start: str, strategy: str, k: int = 1, guide: str = "pathmax", tie: str = "low_h", most: int = 300) -> str:
    """``(req, node, q, g)``: the first ``most`` lookups in order."""
    return f"""WITH RECURSIVE {_state_ctes(expr, sources, start, strategy, k, guide, tie, most)}
SELECT row_number() OVER (ORDER BY round, pos)::INTEGER AS req, node, q::INTEGER AS q, paid AS g FROM st WHERE pos IS NOT NULL"""


def emission_sql(expr: str, sources: Iterable[str], start: str, strategy: str, k: int = 1, guide: str = "pathmax", tie: str = "low_h", emit_rule: str = "early", most: int = 300) -> str:
    """``(rank, node, length, req_at_emit)``: the answers of the first ``most`` lookups. Blind search emits a goal after the batch
    that generated it; best-first search after the first one that leaves no open row of smaller f (or, on extraction, of none up to
    its length, unless it was looked up itself)."""
    a = compile_path(expr)
    finals = ", ".join(map(str, sorted(a.finals)))
    free = {"early": "st.g <= coalesce(least, 1e300)", "on_extract": "(st.g < coalesce(least, 1e300) OR looked <= st.round)"}[emit_rule] if strategy == "astar" else "true"
    major = "g" if strategy == "astar" else "abs(seq.t)"
    return f"""WITH RECURSIVE {_state_ctes(expr, sources, start, strategy, k, guide, tie, most)},
bound AS (SELECT round, min(g + h) FILTER (open) AS least FROM st LEFT JOIN guide USING (q) GROUP BY round),
once AS (SELECT node, q, min(round) FILTER (pos IS NOT NULL) AS looked FROM st GROUP BY node, q),
goal AS (SELECT st.node, st.q, min({{'r': st.round, 'd': st.done, 'g': st.g, 's': st.seq}}) AS e FROM st JOIN bound USING (round) JOIN once USING (node, q) WHERE st.q IN ({finals}) AND {free} GROUP BY st.node, st.q),
named AS (SELECT node, e.r AS r, e.d AS d, e.g AS g, e.s AS seq FROM goal),
first AS (SELECT node, r, d, g, seq, {major} AS major FROM named QUALIFY row_number() OVER (PARTITION BY node ORDER BY r, major, seq) = 1)
SELECT row_number() OVER (ORDER BY r, major, seq)::INTEGER AS rank, node, g::DOUBLE AS length, d::BIGINT AS req_at_emit FROM first"""
