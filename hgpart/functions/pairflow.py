"""Flow refinement of a pair of blocks inside one task."""

from __future__ import annotations

from .kernels import Local, State
from .maxflow import piercing_bipartition


def region(g: Local, part: list[int], side: int, border: list[int], most: int, depth: int, fixed: frozenset = frozenset()) -> list[int]:
    """Nodes of block ``side`` around ``border``, breadth first up to ``depth`` hops and ``most`` weight."""
    out, load, seen, layer = [], 0, set(border) | fixed, [v for v in border if v not in fixed]
    for hop in range(depth + 1):
        nxt = []
        for v in layer:
            if load + g.node_weight[v] > most:
                return out
            out.append(v)
            load += g.node_weight[v]
            if hop < depth:
                for e in g.nets[v]:
                    for u in g.pins[e]:
                        if part[u] == side and u not in seen:
                            seen.add(u)
                            nxt.append(u)
        layer = nxt
    return out


def refine_pair(g: Local, part: list[int], i: int, j: int, limit: list[int], alpha: float = 16.0, depth: int = 2, bulk: bool = True, fixed: frozenset = frozenset()) -> tuple[list[tuple[int, int, int]], int]:
    """(moves (node, from, to), expected gain) of a better cut between blocks i and j; no moves if none is found.

    Only what nets have in the two blocks counts, which is exact for connectivity. What lies outside the regions is contracted to
    a terminal on each side; ``fixed`` nodes always do.
    """
    nets = [e for e, vs in enumerate(g.pins) if (x := {part[v] for v in vs}) and i in x and j in x]
    if not nets:
        return [], 0
    border = [sorted({v for e in nets for v in g.pins[e] if part[v] == b}) for b in (i, j)]
    weight = [sum(w for v, w in enumerate(g.node_weight) if part[v] == b) for b in (i, j)]
    half, eps = (weight[0] + weight[1] + 1) // 2, max(0.0, min(limit[i], limit[j]) / max(1, (weight[0] + weight[1]) / 2) - 1)
    sides = [region(g, part, b, border[x], max(1, int((1 + alpha * eps) * half) - weight[1 - x]), depth, fixed) for x, b in enumerate((i, j))]
    # a side without a rest gives its last node to the terminal
    for x in (0, 1):
        if sides[x] and sum(g.node_weight[v] for v in sides[x]) == weight[x]:
            sides[x].pop()
    if not sides[0] and not sides[1]:
        return [], 0
    number = {v: n + 2 for n, v in enumerate(sides[0] + sides[1])}
    node_weight = [weight[0] - sum(g.node_weight[v] for v in sides[0]), weight[1] - sum(g.node_weight[v] for v in sides[1]), *(g.node_weight[v] for v in sides[0] + sides[1])]
    merged: dict[tuple[int, ...], int] = {}
    old = 0
    for e in {e for v in number for e in g.nets[v]} | set(nets):
        key = tuple(sorted({number.get(v, 0 if part[v] == i else 1) for v in g.pins[e] if part[v] in (i, j)}))
        if len(key) > 1:
            merged[key] = merged.get(key, 0) + g.net_weight[e]
    side_of = [0, 1, *([0] * len(sides[0])), *([1] * len(sides[1]))]
    for key, w in merged.items():
        if len({side_of[v] for v in key}) > 1:
            old += w
    distance = [0] * len(node_weight)
    for x in (0, 1):
        near = set(border[x])
        for v in sides[x]:
            distance[number[v]] = 0 if v in near else 1
    got = piercing_bipartition([list(key) for key in merged], list(merged.values()), node_weight, 0, 1, limit[i], limit[j], distance, bulk, stop_at=old)
    if got is None or got[1] > old:
        return [], 0
    side, value, _ = got
    moves = [(v, part[v], (i, j)[side[n]]) for v, n in number.items() if part[v] != (i, j)[side[n]]]
    before, after = max(weight[0] - limit[i], weight[1] - limit[j], 0), 0
    if value == old and before <= after and not moves:
        return [], 0
    return moves, old - value


def refine(g: Local, part: list[int], k: int, limit: list[int], rounds: int = 2, min_rel_gain: float = 1e-3, alpha: float = 16.0, depth: int = 2) -> list[int]:
    """All active adjacent pairs in turn; a block stays active while a pair of it improved. Ends when a round gains under a thousandth."""
    at = State(g, part, k)
    active = set(range(k))
    for _ in range(rounds):
        pairs = sorted({(a, b) for c in at.phi if len(c) > 1 for a in c for b in c if a < b and (a in active or b in active)})
        start, gained, nxt = g.km1(at.part), 0, set()
        for a, b in pairs:
            moves, expected = refine_pair(g, at.part, a, b, limit, alpha, depth)
            real = 0
            for v, _, t in moves:
                real += at.gain(v, t)
                at.move(v, t)
            if real < 0:
                for v, s, _ in reversed(moves):
                    at.move(v, s)
            elif real > 0:
                gained += real
                nxt |= {a, b}
        active = nxt
        if gained < min_rel_gain * max(1, start):
            break
    return at.part
