"""Search by plain queues on in-memory graphs: the expected order of lookups and answers."""

import heapq

from linkwalk.plans.automaton import INF, accepts_empty, compile_path, heuristic


def neighbours(triples):
    out = {}
    for s, p, o in set(triples):
        out.setdefault(s, set()).add((p, False, o))
        out.setdefault(o, set()).add((p, True, s))
    return out


def reads(symbol, p, inv):
    return symbol.inv == inv and (symbol.label == p if symbol.label else p not in symbol.excluded)


def simulate(triples, expr, start, strategy, k=1, guide="pathmax", tie="low_h", most=10**9):
    """(expanded nodes, [(node, length, request)]) of one run. ``k`` None takes all open nodes, without an order among them."""
    flat, k = k is None, k or 10**9
    adj, a = neighbours(triples), compile_path(expr)
    h = heuristic(a, guide) if strategy == "astar" else dict.fromkeys(range(a.size), 0.0)
    dead = heuristic(a, "pathmax")
    counter = 0
    g, seq, open_, emitted, waiting = {(start, 0): 0}, {(start, 0): 0}, set(), {}, set()
    trace, answers = [], []

    def priority(n):
        if strategy == "bfs":
            return (seq[n],)
        if strategy == "dfs":
            return (-seq[n],)
        f = g[n] + h[n[1]]
        return (f, h[n[1]] if tie == "low_h" else 0, -seq[n] if tie == "lifo" else seq[n])

    def release():
        least = min((g[n] + h[n[1]] for n in open_), default=INF)
        for n in sorted((n for n in waiting if g[n] <= least), key=lambda n: (g[n], seq[n])):
            waiting.discard(n)
            emitted[n] = True
            answers.append((n[0], g[n], len(trace)))

    if accepts_empty(a):
        emitted[start, 0] = True
        answers.append((start, 0, 0))
    if a.outgoing(0) and not start.startswith('"'):
        open_.add((start, 0))
    while open_ and len(trace) < most:
        batch = heapq.nsmallest(min(k, most - len(trace), len(open_)), open_, key=priority)
        if flat:
            batch.sort()
        trace += [n[0] for n in batch]
        open_ -= set(batch)
        made = {}
        for pos, n in [(0, n) for n in batch] if flat else enumerate(batch, 1):
            for rank, (symbol, q2) in enumerate(a.outgoing(n[1])):
                for p, inv, o in adj.get(n[0], ()):
                    if reads(symbol, p, inv):
                        new = (o, q2)
                        turn = -pos if strategy == "dfs" else pos
                        route = (g[n] + 1 if strategy == "astar" else 0, turn, rank, p, inv, n, g[n] + 1, pos)
                        made[new] = min(made.get(new, route), route)
        for new, route in sorted(made.items(), key=lambda x: (*x[1][1:5], x[0])):
            fresh = new not in seq
            if fresh:
                counter += 1
                seq[new] = counter
            if fresh or strategy == "astar" and route[6] < g[new]:
                g[new] = route[6]
                if dead[new[1]] < INF and h[new[1]] < INF and not new[0].startswith('"'):
                    open_.add(new)
                if new[1] in a.finals and new not in emitted:
                    if strategy == "astar":
                        waiting.add(new)
                    elif fresh:
                        emitted[new] = True
                        answers.append((new[0], g[new], len(trace), route[7], seq[new]))
        if strategy == "astar":
            release()
        else:
            done = [x for x in answers if len(x) == 3]
            late = sorted((x for x in answers if len(x) == 5), key=lambda x: (x[3], x[4]))
            answers[:] = done + [x[:3] for x in late]
    out, names = [], set()
    for node, length, req in answers:
        if node not in names:
            names.add(node)
            out.append((node, length, req))
    return trace, out


def exact(triples, expr, start):
    """{node: least length} over the product."""
    adj, a = neighbours(triples), compile_path(expr)
    dist, layer, d = {(start, 0): 0}, [(start, 0)], 0
    while layer:
        d += 1
        after = []
        for n, q in layer:
            for symbol, q2 in a.outgoing(q):
                for p, inv, o in adj.get(n, ()):
                    if reads(symbol, p, inv) and (o, q2) not in dist:
                        dist[o, q2] = d
                        after.append((o, q2))
        layer = after
    out = {}
    for (n, q), x in dist.items():
        if q in a.finals:
            out[n] = min(x, out.get(n, x))
    return out


#: Four documents and five people.
G1 = [("P1", "c", "A"), ("P1", "c", "B"), ("P2", "c", "A"), ("P2", "c", "C"), ("P3", "c", "B"), ("P3", "c", "D"), ("P4", "c", "D"), ("P4", "c", "E")] + [(x, "name", f'"n{x}') for x in "ABCDE"]
#: Stack search takes a longer walk than needed.
G2 = [("P1", "c", "A"), ("P1", "c", "B"), ("P2", "c", "A"), ("P2", "c", "C"), ("P3", "c", "B"), ("P3", "c", "C")]
#: A self-loop, a repeat, parallel labels, shared literals.
G3 = [("x", "a", "x"), ("x", "a", "y"), ("x", "b", "y"), ("x", "n", '"t'), ("z", "n", '"t'), ("x", "a", "y")]
