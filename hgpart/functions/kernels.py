"""Sequential searches on a hypergraph that fits one task: a region, a coarsest level, one run of a portfolio."""

from __future__ import annotations

import heapq
import itertools
import math
import random

import numpy as np


class Local:
    """A small hypergraph with nodes and nets numbered from 0; ``pins`` by net, ``nets`` by node."""

    def __init__(self, pins: list[list[int]], net_weight: list[int], node_weight: list[int]):
        self.pins, self.net_weight, self.node_weight = pins, net_weight, node_weight
        self.nets: list[list[int]] = [[] for _ in node_weight]
        for e, vs in enumerate(pins):
            for v in vs:
                self.nets[v].append(e)

    @classmethod
    def of(cls, net: np.ndarray, node: np.ndarray, net_ids: np.ndarray, net_weight: np.ndarray, node_ids: np.ndarray, node_weight: np.ndarray) -> Local:
        """From id arrays; ``net_ids`` and ``node_ids`` must be sorted."""
        pins: list[list[int]] = [[] for _ in net_ids]
        for e, v in zip(np.searchsorted(net_ids, net).tolist(), np.searchsorted(node_ids, node).tolist(), strict=True):
            pins[e].append(v)
        return cls(pins, net_weight.tolist(), node_weight.tolist())

    @property
    def n(self) -> int:
        return len(self.node_weight)

    def counts(self, part: list[int]) -> list[dict[int, int]]:
        out = []
        for vs in self.pins:
            c: dict[int, int] = {}
            for v in vs:
                c[part[v]] = c.get(part[v], 0) + 1
            out.append(c)
        return out

    def km1(self, part: list[int]) -> int:
        return sum(w * (len({part[v] for v in vs}) - 1) for vs, w in zip(self.pins, self.net_weight, strict=True) if vs)

    def cut(self, part: list[int]) -> int:
        return sum(w for vs, w in zip(self.pins, self.net_weight, strict=True) if len({part[v] for v in vs}) > 1)

    def weights(self, part: list[int], k: int) -> list[int]:
        out = [0] * k
        for v, b in enumerate(part):
            out[b] += self.node_weight[v]
        return out

    def part_of(self, keep: list[int]) -> Local:
        """The part on ``keep``, renumbered; nets under two pins are left out."""
        number = {v: i for i, v in enumerate(keep)}
        pins, weight = [], []
        for vs, w in zip(self.pins, self.net_weight, strict=True):
            inner = [number[v] for v in vs if v in number]
            if len(inner) > 1:
                pins.append(inner)
                weight.append(w)
        return Local(pins, weight, [self.node_weight[v] for v in keep])


class State:
    """A partition with counts, benefits and presences that moves keep up to date: what a move changes costs the pins of nets that cross 0, 1 or 2."""

    def __init__(self, g: Local, part: list[int], k: int, weight: list[int] | None = None, objective: str = "km1"):
        self.g, self.part, self.k, self.objective = g, list(part), k, objective
        self.weight = list(weight) if weight is not None else g.weights(self.part, k)
        self.phi = g.counts(self.part)
        self.total = [sum(g.net_weight[e] for e in es) for es in g.nets]
        self.alone = [0] * g.n
        self.present: list[dict[int, int]] = [{} for _ in range(g.n)]
        for vs, w, c in zip(g.pins, g.net_weight, self.phi, strict=True):
            for v in vs:
                if c[self.part[v]] == 1:
                    self.alone[v] += w
                x = self.present[v]
                for b in c:
                    x[b] = x.get(b, 0) + w

    def best(self, u: int, limit: list[int]) -> tuple[int, int] | None:
        """(gain, target) of the best move with room, preferring lighter targets."""
        own, c, weight, found = self.part[u], self.g.node_weight[u], self.weight, None
        base = self.alone[u] - self.total[u]
        cut = self.cut_gains(u) if self.objective != "km1" else None
        for t, w in self.present[u].items():
            if t != own and w and weight[t] + c <= limit[t]:
                x = (base + w if cut is None else self.gain(u, t, cut), -weight[t], -t)
                if found is None or x > found:
                    found = x
        return found and (found[0], -found[2])

    def cut_gains(self, u: int) -> dict[int, int]:
        """By block, the weight of u's nets with all their other pins there; for u's own block, that of the nets it would cut."""
        out: dict[int, int] = {}
        for e in self.g.nets[u]:
            for b, n in self.phi[e].items():
                if n == len(self.g.pins[e]) - (b != self.part[u]) and n + (b != self.part[u]) > 1:
                    out[b] = out.get(b, 0) + self.g.net_weight[e]
        return out

    def gain(self, u: int, t: int, cut: dict[int, int] | None = None) -> int:
        km1 = self.alone[u] - self.total[u] + self.present[u].get(t, 0)
        if self.objective == "km1":
            return km1
        cut = self.cut_gains(u) if cut is None else cut
        return cut.get(t, 0) - cut.get(self.part[u], 0) + (km1 if self.objective == "soed" else 0)

    def move(self, u: int, t: int, touched: set[int] | None = None) -> None:
        g, part, s = self.g, self.part, self.part[u]
        part[u] = t
        fresh = 0
        for e in g.nets[u]:
            w, c, vs = g.net_weight[e], self.phi[e], g.pins[e]
            left, now = c[s] - 1, c.get(t, 0) + 1
            if left:
                c[s] = left
            else:
                del c[s]
            c[t] = now
            if not left:
                for v in vs:
                    self.present[v][s] -= w
            elif left == 1:
                for v in vs:
                    if part[v] == s:
                        self.alone[v] += w
                        break
            if now == 1:
                fresh += w
                for v in vs:
                    x = self.present[v]
                    x[t] = x.get(t, 0) + w
            elif now == 2:
                for v in vs:
                    if part[v] == t and v != u:
                        self.alone[v] -= w
                        break
            if touched is not None and (left < 2 or now <= 2 or self.objective != "km1" and max(left + 1, now) >= len(vs) - 2):
                touched.update(vs)
        self.alone[u] = fresh
        c = g.node_weight[u]
        self.weight[s] -= c
        self.weight[t] += c


def fm_should_stop(steps: int, total: float, squares: float, alpha: float = 1.0, beta: float = 10.0) -> bool:
    """Under a normal model of gains an improvement is unlikely: steps * mean ** 2 > alpha * variance + beta, at a negative mean."""
    if steps < 2 or total >= 0:
        return False
    mean = total / steps
    variance = max(0.0, (squares - steps * mean * mean) / (steps - 1))
    return steps * mean * mean > alpha * variance + beta


def localized_fm(g: Local, part: list[int], k: int, limit: list[int], seeds: list[int], free: list[bool] | None = None, variant: str = "localized", max_steps: int | None = None, expand: bool = True, weight: list[int] | None = None, at: State | None = None, objective: str = "km1") -> tuple[list[tuple[int, int, int]], list[int]]:
    """One search: published moves (node, from, to) in order and the partition after them.

    The queue holds each node's best move (``all_moves``: one entry a target). Neighbours over nets that crossed join the search
    if ``free``. Moves stay pending until their sum is positive, or 0 with a smaller largest block; what is
    pending at the end is taken back. Every node moves once at most. ``weight`` are the blocks' weights where ``g`` is only a region;
    ``at`` is a state to go on with.
    """
    at = at or State(g, part, k, weight, objective)
    part, weight = at.part, at.weight
    done = [False] * g.n
    heap, published, pending = [], [], []
    beta = math.log(max(2, g.n)) + 5
    total = steps = squares = gained = 0
    top = max(weight)

    def push(u):
        if variant == "all_moves":
            for t in at.present[u]:
                if t != part[u] and weight[t] + g.node_weight[u] <= limit[t]:
                    heapq.heappush(heap, (-at.gain(u, t), u, t))
        elif (x := at.best(u, limit)) is not None:
            heapq.heappush(heap, (-x[0], u, x[1]))

    for u in seeds:
        if free is None or free[u]:
            push(u)
    while heap and (max_steps is None or steps < max_steps):
        score, u, t = heapq.heappop(heap)
        if done[u]:
            continue
        now = at.best(u, limit)
        if now is None:
            continue
        if now[0] < -score:
            heapq.heappush(heap, (-now[0], u, now[1]))
            continue
        gain, t = now
        own, near = part[u], set()
        at.move(u, t, near)
        done[u] = True
        pending.append((u, own, t))
        total += gain
        gained += gain
        squares += gain * gain
        steps += 1
        high = max(weight)
        if gained > 0 or gained == 0 and high < top:
            published += pending
            pending, gained, total, steps, squares, top = [], 0, 0, 0, 0, high
        elif fm_should_stop(steps, total, squares, 1.0, beta):
            break
        if expand:
            for v in sorted(near):
                if not done[v] and (free is None or free[v]):
                    push(v)
    for u, own, _ in reversed(pending):
        at.move(u, own)
    return published, at.part


def fm(g: Local, part: list[int], k: int, limit: list[int], rounds: int = 3, variant: str = "localized", seeds_per_search: int | None = None, seed: int = 0) -> list[int]:
    """Rounds of searches from all boundary nodes at once, or from ``seeds_per_search`` at a time."""
    rng, at = random.Random(seed), State(g, part, k)
    for _ in range(rounds):
        border = sorted({v for e, c in enumerate(at.phi) if len(c) > 1 for v in g.pins[e]})
        rng.shuffle(border)
        moved = False
        free = [True] * g.n
        step = seeds_per_search or max(1, len(border))
        for i in range(0, len(border), step):
            moves, _ = localized_fm(g, at.part, k, limit, border[i:i + step], free, variant, at=at)
            for u, _, _ in moves:
                free[u] = False
            moved |= bool(moves)
        if not moved:
            break
    return at.part


def fm2(g: Local, part: list[int], limit: list[int], rounds: int = 3, seed: int = 0) -> list[int]:
    return fm(g, part, 2, limit, rounds, seed=seed)


def label_propagation(g: Local, part: list[int], k: int, limit: list[int], rounds: int = 5, seed: int = 0) -> list[int]:
    at, rng, order = State(g, part, k), random.Random(seed), list(range(g.n))
    for _ in range(rounds):
        rng.shuffle(order)
        moved = 0
        for u in order:
            x = at.best(u, limit)
            if x and x[0] > 0:
                at.move(u, x[1])
                moved += 1
        if not moved:
            break
    return at.part


def rebalance(g: Local, part: list[int], k: int, limit: list[int]) -> list[int]:
    """Move nodes out of blocks over their limit, least loss first, to blocks with room; nodes without a net go anywhere."""
    weight = g.weights(part, k)
    if all(w <= x for w, x in zip(weight, limit, strict=True)):
        return list(part)
    at = State(g, part, k)
    for b in range(k):
        if at.weight[b] <= limit[b]:
            continue
        order = []
        for u in range(g.n):
            if at.part[u] == b:
                order.append((-max((at.gain(u, t) for t in at.present[u] if t != b), default=0), u))
        for _, u in sorted(order):
            if at.weight[b] <= limit[b]:
                break
            room = [(at.gain(u, t), limit[t] - at.weight[t], -t) for t in range(k) if t != b and at.weight[t] + g.node_weight[u] <= limit[t]]
            if room:
                at.move(u, -max(room)[2])
    return at.part


# -- constructive bipartitions ------------------------------------------------------------------


def _far_pair(g: Local, rng: random.Random) -> tuple[int, int]:
    def farthest(s):
        seen, last, todo = {s}, s, [s]
        while todo:
            nxt = []
            for u in todo:
                for e in g.nets[u]:
                    for v in g.pins[e]:
                        if v not in seen:
                            seen.add(v)
                            nxt.append(v)
            if nxt:
                last = nxt[rng.randrange(len(nxt))]
            todo = nxt
        return last

    a = farthest(rng.randrange(g.n))
    return a, farthest(a)


def random_assign(g: Local, limit: list[int], seed: int) -> list[int]:
    rng = random.Random(seed)
    order = list(range(g.n))
    rng.shuffle(order)
    share = limit[0] / max(1, limit[0] + limit[1])
    part, load, total = [1] * g.n, 0, sum(g.node_weight)
    for u in order:
        if load + g.node_weight[u] <= min(limit[0], share * total + g.node_weight[u] / 2):
            part[u] = 0
            load += g.node_weight[u]
    return part


def bfs_grow(g: Local, limit: list[int], seed: int) -> list[int]:
    """Block 0 grows breadth first from one end until it has its share."""
    rng = random.Random(seed)
    part, load, total = [1] * g.n, 0, sum(g.node_weight)
    want = total * limit[0] / max(1, limit[0] + limit[1])
    todo, seen, at = [], set(), 0
    start, _ = _far_pair(g, rng)
    rest = list(range(g.n))
    rng.shuffle(rest)
    for s in [start, *rest]:
        if s not in seen:
            seen.add(s)
            todo.append(s)
        while at < len(todo):
            u = todo[at]
            at += 1
            if load + g.node_weight[u] > limit[0] or load >= want:
                return part
            part[u] = 0
            load += g.node_weight[u]
            for e in g.nets[u]:
                for v in g.pins[e]:
                    if v not in seen:
                        seen.add(v)
                        todo.append(v)
    return part


def greedy_grow(g: Local, limit: list[int], seed: int, schedule: str, gain: str) -> list[int]:
    """Two blocks grow from two far ends by priority queues over unassigned nodes.

    ``schedule``: ``global`` takes the better head of both queues, ``round_robin`` alternates, ``sequential`` fills
    block 0 first. ``gain``: ``fm`` weighs nets that joining would complete against nets it would cut, ``max_net``
    counts the weight of nets that already touch the block.
    """
    rng = random.Random(seed)
    total = sum(g.node_weight)
    want = [total * x / max(1, sum(limit)) for x in limit]
    part, load = [-1] * g.n, [0, 0]
    phi = [[0, 0] for _ in g.pins]
    heaps: list[list] = [[], []]
    tick = itertools.count()

    score = [[0] * g.n, [0] * g.n]

    def put(u, b):
        part[u] = b
        load[b] += g.node_weight[u]
        mine, other = score[b], score[1 - b]
        for e in g.nets[u]:
            phi[e][b] += 1
            if phi[e][b] == 1:
                w = g.net_weight[e]
                for v in g.pins[e]:
                    if part[v] < 0:
                        mine[v] += w
                        if gain == "fm":
                            # a net that only this side has would be cut; one that both have no longer pulls
                            other[v] -= w
                        heapq.heappush(heaps[b], (-mine[v], next(tick), v))

    def head(b):
        while heaps[b]:
            x, _, u = heaps[b][0]
            if part[u] >= 0:
                heapq.heappop(heaps[b])
            elif (now := score[b][u]) < -x:
                heapq.heapreplace(heaps[b], (-now, next(tick), u))
            else:
                return now, u
        return None

    a, z = _far_pair(g, rng)
    put(a, 0)
    if z != a:
        put(z, 1)
    rest = [u for u in range(g.n) if part[u] < 0]
    rng.shuffle(rest)
    turn = 0
    while True:
        while rest and part[rest[-1]] >= 0:
            rest.pop()
        if not rest:
            return part
        room = [load[b] < want[b] for b in (0, 1)]
        if schedule == "sequential":
            b = 0 if room[0] else 1
        elif schedule == "round_robin":
            b = turn if room[turn] else 1 - turn
            turn = 1 - turn
        else:
            heads = [(head(b) if room[b] else None) for b in (0, 1)]
            b = max((x[0], -i) for i, x in enumerate(heads) if x)[1] * -1 if any(heads) else int(load[0] * want[1] > load[1] * want[0])
        x = head(b)
        u = x[1] if x else rest[-1]
        if load[b] + g.node_weight[u] > limit[b] and load[1 - b] + g.node_weight[u] <= limit[1 - b]:
            b = 1 - b
        put(u, b)


def lp_assign(g: Local, limit: list[int], seed: int) -> list[int]:
    return label_propagation(g, random_assign(g, limit, seed), 2, limit, 5, seed)


TECHNIQUES = {
    "bfs": bfs_grow,
    **{f"{gain}_{schedule}": (lambda g, limit, seed, s=schedule, x=gain: greedy_grow(g, limit, seed, s, x)) for gain in ("fm", "max_net") for schedule in ("global", "round_robin", "sequential")},
    "random": random_assign,
    "label_propagation": lp_assign,
}


def candidate(g: Local, technique: str, limit: list[int], seed: int) -> tuple[int, float, list[int]]:
    """(km1, overload, bipartition) of one technique after two-way refinement."""
    part = TECHNIQUES[technique](g, limit, seed)
    part = fm2(g, rebalance(g, part, 2, limit), limit, 2, seed)
    w = g.weights(part, 2)
    return g.km1(part), max(w[0] - limit[0], w[1] - limit[1], 0), part


#: Runs of each technique: at least, at most, and whether the ones after the least depend on their use.
RUNS = (5, 20, True)


def worth_rerun(values: list[float], best: float) -> bool:
    """Another run may beat ``best``: it lies within two deviations under the mean."""
    n = len(values)
    mean = sum(values) / n
    sd = math.sqrt(sum((x - mean) ** 2 for x in values) / (n - 1)) if n > 1 else 0.0
    return mean - 2 * sd <= best


def portfolio(g: Local, limit: list[int], min_runs: int = 5, max_runs: int = 20, adaptive: bool = True, seed: int = 0) -> list[int]:
    best = None
    for i, name in enumerate(TECHNIQUES):
        values: list[float] = []
        while len(values) < min_runs or adaptive and len(values) < max_runs and worth_rerun(values, best[1]):
            cut, over, part = candidate(g, name, limit, seed * 7919 + i * 101 + len(values))
            values.append(cut)
            if best is None or (over, cut) < best[:2]:
                best = (over, cut, part)
    return best[2]


# -- multilevel in one task ---------------------------------------------------------------------


def cluster(g: Local, c_max: int, seed: int, labels: list[int] | None = None) -> list[int]:
    """Representatives after one pass in random order: each single node joins its best rated cluster that has room."""
    rng = random.Random(seed)
    rep, load, single = list(range(g.n)), list(g.node_weight), [True] * g.n
    order = list(range(g.n))
    rng.shuffle(order)
    for u in order:
        if not single[u]:
            continue
        score: dict[int, float] = {}
        for e in g.nets[u]:
            vs = g.pins[e]
            if len(vs) > 1:
                w = g.net_weight[e] / (len(vs) - 1)
                for v in {rep[v] for v in vs}:
                    if v != u:
                        score[v] = score.get(v, 0.0) + w
        best = max(((s, -v) for v, s in score.items() if load[v] + load[u] <= c_max and (labels is None or labels[v] == labels[u])), default=None)
        if best:
            t = -best[1]
            rep[u] = t
            load[t] += load[u]
            single[u] = single[t] = False
    return rep


def contract(g: Local, rep: list[int]) -> tuple[Local, list[int]]:
    """Coarse hypergraph without single-pin nets, equal nets merged, and the coarse number of every node."""
    number: dict[int, int] = {}
    to = [number.setdefault(r, len(number)) for r in rep]
    weight = [0] * len(number)
    for u, c in enumerate(to):
        weight[c] += g.node_weight[u]
    merged: dict[tuple[int, ...], int] = {}
    for vs, w in zip(g.pins, g.net_weight, strict=True):
        key = tuple(sorted({to[v] for v in vs}))
        if len(key) > 1:
            merged[key] = merged.get(key, 0) + w
    return Local([list(k) for k in merged], list(merged.values()), weight), to


def adaptive_eps(total: int, k: int, part_total: int, k_part: int, eps: float) -> float:
    """Imbalance that each of the remaining bisections may have so that the final blocks keep ``eps``."""
    if k_part <= 1 or not part_total:
        return eps
    return ((1 + eps) * total / k * k_part / part_total) ** (1 / math.ceil(math.log2(k_part))) - 1


def bipartition(g: Local, limit: list[int], seed: int = 0, coarse_to: int = 320, runs: tuple[int, int, bool] = RUNS) -> list[int]:
    levels, maps = [g], []
    c_max = max(1, sum(g.node_weight) // coarse_to)
    while levels[-1].n > coarse_to:
        small, to = contract(levels[-1], cluster(levels[-1], c_max, seed + len(maps)))
        if small.n > 0.95 * levels[-1].n:
            break
        levels.append(small)
        maps.append(to)
    part = portfolio(levels[-1], limit, *runs, seed)
    for g_, to in zip(reversed(levels[:-1]), reversed(maps), strict=True):
        part = fm2(g_, label_propagation(g_, [part[c] for c in to], 2, limit, 2, seed), limit, 1, seed)
    return rebalance(g, part, 2, limit)


def recursive(g: Local, k: int, eps: float, seed: int = 0, runs: tuple[int, int, bool] = RUNS, total: int | None = None, k_all: int | None = None) -> list[int]:
    """Blocks 0..k-1 by bisection into ceil(k / 2) and floor(k / 2) shares."""
    if k == 1 or not g.n:
        return [0] * g.n
    own = sum(g.node_weight)
    total, k_all = total if total is not None else own, k_all or k
    e = max(0.0, adaptive_eps(total, k_all, own, k, eps))
    left = -(-k // 2)
    limit = [math.floor((1 + e) * own * x / k + 1e-9) for x in (left, k - left)]
    # room for the heaviest node, else nothing fits
    short = own - sum(limit)
    if short > 0:
        limit = [x + short for x in limit]
    part = bipartition(g, limit, seed, runs=runs)
    out = [0] * g.n
    for side, k_side, first in ((0, left, 0), (1, k - left, left)):
        keep = [u for u in range(g.n) if part[u] == side]
        for u, b in zip(keep, recursive(g.part_of(keep), k_side, eps, seed + 1 + side, runs, total, k_all), strict=True):
            out[u] = first + b
    return out


# -- references for tests and small pieces ------------------------------------------------------


def recalc_sequential(g: Local, part: list[int], moves: list[tuple[int, int]]) -> list[int]:
    """True gain of each (node, to) when made in turn."""
    at, out = State(g, part, max([*part, *(t for _, t in moves)]) + 1), []
    for u, t in moves:
        out.append(0 if at.part[u] == t else at.gain(u, t))
        if at.part[u] != t:
            at.move(u, t)
    return out


def exact(g: Local, k: int, limit: int) -> tuple[int, list[int]] | None:
    """Best partition by enumeration; for a dozen nodes."""
    best = None
    for part in itertools.product(range(k), repeat=g.n):
        if max(g.weights(list(part), k)) <= limit and (best is None or g.km1(list(part)) < best[0]):
            best = (g.km1(list(part)), list(part))
    return best


def swap_prefix_walk(a: list[int], b: list[int], most_in_t: int, most_in_s: int) -> tuple[int, int]:
    """Last feasible (i, j) on the walk that takes from a (moving into t) while at most as much has come as gone, else from b.

    x = sum(a[:i]) - sum(b[:j]) must stay within [-most_in_s, most_in_t].
    """
    i = j = x = 0
    best = (0, 0)
    while i < len(a) or j < len(b):
        if j >= len(b) or i < len(a) and x <= 0:
            x += a[i]
            i += 1
        else:
            x -= b[j]
            j += 1
        if -most_in_s <= x <= most_in_t:
            best = (i, j)
    return best


def swap_prefix_recursive(a: list[int], b: list[int], most_in_t: int, most_in_s: int) -> tuple[int, int]:
    """A feasible prefix pair by searching halves of the merged order from its long end."""
    order, i, j, sa, sb = [(0, 0, 0)], 0, 0, 0, 0
    while i < len(a) or j < len(b):
        if j >= len(b) or i < len(a) and sa <= sb:
            sa += a[i]
            i += 1
        else:
            sb += b[j]
            j += 1
        order.append((i, j, sa - sb))

    def search(lo, hi):
        if lo > hi:
            return None
        if lo == hi:
            return order[lo][:2] if -most_in_s <= order[lo][2] <= most_in_t else None
        mid = (lo + hi) // 2
        return search(mid + 1, hi) or search(lo, mid)

    return search(0, len(order) - 1) or (0, 0)
