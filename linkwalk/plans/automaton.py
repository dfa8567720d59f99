"""Automata of path expressions, and the guides for best-first search that they give."""

from __future__ import annotations

import heapq
from collections import defaultdict
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from .expr import Alt, Label, Opt, Other, PathExpr, Plus, Seq, Star, as_expr, nullable, push_inverse, simplify

INF = float("inf")


@dataclass(frozen=True)
class Symbol:
    """What a transition reads: one label, or any but the excluded ones, in one direction; ``test`` names a node test."""

    label: str | None
    inv: bool
    excluded: frozenset[str] | None = None
    test: str | None = None

    def key(self) -> tuple:
        return (self.inv, self.label is None, self.label or "", tuple(sorted(self.excluded or ())), self.test or "")


@dataclass(frozen=True)
class Automaton:
    """States are 0..size-1, the start is 0; there are no empty transitions."""

    size: int
    finals: frozenset[int]
    edges: frozenset[tuple[int, Symbol, int]]

    def outgoing(self, q: int) -> list[tuple[Symbol, int]]:
        """Transitions of a state in their fixed order: forward before reversed, then by label and target."""
        return sorted(((s, t) for a, s, t in self.edges if a == q), key=lambda x: (*x[0].key(), x[1]))

    @property
    def labels(self) -> set[str] | None:
        """All labels read; None when a negated set reads labels unknown beforehand."""
        names = {s.label for _, s, _ in self.edges}
        return None if None in names else {n for n in names if n}

    def delta(self, spark: SparkSession, costs: dict[str, float] | None = None) -> DataFrame:
        """Transitions as rows; a few dozen, whatever the data."""
        rows = []
        for q in range(self.size):
            for rank, (s, t) in enumerate(self.outgoing(q)):
                rows.append((q, s.label, s.inv, s.label is None, sorted(s.excluded or ()), s.test, t, rank, t in self.finals, float((costs or {}).get(s.label, 1.0))))
        return spark.createDataFrame(rows, "q int, label string, t_inv boolean, negated boolean, excluded array<string>, test string, q2 int, t_rank int, goal boolean, cost double")

    def states(self, spark: SparkSession) -> DataFrame:
        h, hat = state_distance(self), pathmax_distance(self)
        rows = [(q, q in self.finals, None if h[q] == INF else int(h[q]), None if hat[q] == INF else int(hat[q])) for q in range(self.size)]
        return spark.createDataFrame(rows, "q int, is_final boolean, h int, h_hat int")


def _positions(e: PathExpr) -> tuple[list[Symbol], set[int], set[int], set[tuple[int, int]]]:
    """Position automaton parts: symbols, first and last positions, and which may follow which."""
    symbols: list[Symbol] = []
    follows: set[tuple[int, int]] = set()

    def walk(x: PathExpr) -> tuple[set[int], set[int]]:
        if isinstance(x, (Label, Other)):
            symbols.append(Symbol(x.name, x.inv, None, x.test) if isinstance(x, Label) else Symbol(None, x.inv, x.excluded, x.test))
            return {len(symbols)}, {len(symbols)}
        if isinstance(x, Alt):
            (a, b), (c, d) = walk(x.left), walk(x.right)
            return a | c, b | d
        if isinstance(x, Seq):
            (a, b), (c, d) = walk(x.left), walk(x.right)
            follows.update((i, j) for i in b for j in c)
            return a | (c if nullable(x.left) else set()), d | (b if nullable(x.right) else set())
        if isinstance(x, (Star, Plus, Opt)):
            a, b = walk(x.of)
            if not isinstance(x, Opt):
                follows.update((i, j) for i in b for j in a)
            return a, b
        return set(), set()

    first, last = walk(e)
    return symbols, first, last, follows


def trim(a: Automaton) -> Automaton:
    """Drops states that no word reaches or that reach no final state; the start always stays."""
    def closure(seeds, pairs):
        seen, todo = set(seeds), list(seeds)
        while todo:
            q = todo.pop()
            for x, y in pairs:
                if x == q and y not in seen:
                    seen.add(y)
                    todo.append(y)
        return seen

    ahead = {(q, t) for q, _, t in a.edges}
    keep = closure({0}, ahead) & closure(set(a.finals), {(t, q) for q, t in ahead})
    names = {q: i for i, q in enumerate(sorted(keep | {0}))}
    return Automaton(len(names), frozenset(names[q] for q in a.finals if q in keep), frozenset((names[q], s, names[t]) for q, s, t in a.edges if q in keep and t in keep))


def reduce(a: Automaton) -> Automaton:
    """Trims, then merges states with the same future: the coarsest partition in which equal states agree on being final and
    on the (symbol, class) pairs that they reach."""
    a = trim(a)
    block = [int(q in a.finals) for q in range(a.size)]
    while True:
        signs = [(block[q], frozenset((s, block[t]) for x, s, t in a.edges if x == q)) for q in range(a.size)]
        numbers: dict = {}
        after = [numbers.setdefault(s, len(numbers)) for s in signs]
        if len(set(after)) == len(set(block)):
            break
        block = after
    return Automaton(len(set(after)), frozenset(after[q] for q in a.finals), frozenset((after[q], s, after[t]) for q, s, t in a.edges))


def compile_path(e: str | PathExpr, reduced: bool = True) -> Automaton:
    """The automaton that accepts the walks of ``e``."""
    e = simplify(push_inverse(simplify(as_expr(e))))
    symbols, first, last, follows = _positions(e)
    edges = {(0, symbols[j - 1], j) for j in first} | {(i, symbols[j - 1], j) for i, j in follows}
    a = Automaton(len(symbols) + 1, frozenset(last | ({0} if nullable(e) else set())), frozenset(edges))
    return reduce(a) if reduced else a


def accepts_empty(a: Automaton) -> bool:
    return 0 in a.finals


def accepts(a: Automaton, word: list[tuple[str, bool]]) -> bool:
    """Whether a word of (label, reversed) steps is in the language; node tests count as passed."""
    now = {0}
    for label, inv in word:
        now = {t for q, s, t in a.edges if q in now and s.inv == inv and (s.label == label if s.label else label not in s.excluded)}
    return bool(now & a.finals)


def state_distance(a: Automaton, costs: dict[str, float] | None = None) -> dict[int, float]:
    """Least cost from each state to a final one; infinite where there is no way. Any cost must not be negative."""
    back = defaultdict(list)
    for q, s, t in a.edges:
        cost = (costs or {}).get(s.label, 1.0)
        if cost < 0:
            raise ValueError("costs must not be negative")
        back[t].append((q, cost))
    out = dict.fromkeys(range(a.size), INF)
    heap = [(0.0, q) for q in a.finals]
    while heap:
        d, q = heapq.heappop(heap)
        if d < out[q]:
            out[q] = d
            for p, cost in back[q]:
                heapq.heappush(heap, (d + cost, p))
    return out


def pathmax_distance(a: Automaton, costs: dict[str, float] | None = None) -> dict[int, float]:
    """Least cost of one further step plus what then remains. It equals :func:`state_distance` off the final states; on a
    final state it tells how far the *next* answer is, which delays lookups of nodes that are answers already."""
    h = state_distance(a, costs)
    return {q: min(((costs or {}).get(s.label, 1.0) + h[t] for x, s, t in a.edges if x == q), default=INF) for q in range(a.size)}


def heuristic(a: Automaton, kind: str, costs: dict[str, float] | None = None) -> dict[int, float]:
    """``state``, ``pathmax`` or ``zero`` (uniform cost; states without a way to an answer still stay out)."""
    h = state_distance(a, costs)
    if kind == "state":
        return h
    hat = pathmax_distance(a, costs)
    if kind == "pathmax":
        return hat
    if kind == "zero":
        return {q: 0.0 if hat[q] < INF or h[q] < INF else INF for q in h}
    raise ValueError(f"unknown heuristic {kind!r}")
