"""Flow refinement of pairs of blocks by array operations: synchronous push-relabel, piercing, and application of results."""

from __future__ import annotations

import numpy as np

from .arrays import Csr, State, spread


class Flow:
    """A preflow on an expanded hypergraph that grows as terminals are added.

    Vertices are the nodes, then an in- and an out-vertex for each net over two pins, joined by a bridge of its weight; nets of two pins are plain edges.
    With ``implicit`` a net's pin arcs are not bounded, which leaves the value alone. A round discharges all active vertices against the labels of
    its beginning, so the result doesn't depend on any order: pushes go one label down, along arcs in their order while excess lasts; then what is
    left over relabels its vertex by the residual arcs as they now are.
    """

    def __init__(self, g: Csr, implicit: bool = False):
        n = g.n
        two, big = np.flatnonzero(g.size == 2), np.flatnonzero(g.size > 2)
        a2, b2, w2 = g.node[g.ptr[two]], g.node[g.ptr[two] + 1], g.net_weight[two]
        pins, at = g.pins_of(big), np.repeat(np.arange(len(big)), g.size[big])
        w = g.net_weight[big]
        wide = np.full(len(pins), 1 << 50) if implicit else w[at]
        inside, outside = n + 2 * np.arange(len(big)), n + 2 * np.arange(len(big)) + 1
        # pairs of arcs, each other's reverse: edges, bridges, pins into nets, nets out to pins
        tail = np.concatenate([a2, inside, pins, outside[at]])
        head = np.concatenate([b2, outside, inside[at], pins])
        cap = np.concatenate([w2, w, wide, wide])
        back = np.concatenate([w2, np.zeros(len(w) + 2 * len(pins), np.int64)])
        m = len(tail)
        self.n, self.nodes = n + 2 * len(big), n
        src, dst, c = np.concatenate([tail, head]), np.concatenate([head, tail]), np.concatenate([cap, back])
        order = np.argsort(src, kind="stable")
        place = np.empty(2 * m, np.int64)
        place[order] = np.arange(2 * m)
        self.src, self.dst, self.cap = src[order], dst[order], c[order].astype(np.int64)
        self.rev = place[np.concatenate([np.arange(m, 2 * m), np.arange(m)])[order]]
        self.degree = np.bincount(self.src, minlength=self.n)
        self.ptr = np.concatenate([[0], np.cumsum(self.degree)])
        self.excess = np.zeros(self.n, np.int64)
        self.source, self.sink = np.zeros(self.n, bool), np.zeros(self.n, bool)
        self.label = np.zeros(self.n, np.int64)
        self.stale = True

    def _arcs(self, v: np.ndarray) -> np.ndarray:
        return spread(self.ptr[v], self.degree[v])

    def add_source(self, v: np.ndarray) -> None:
        """New sources push all they can at once; their labels are out of reach."""
        v = v[~self.source[v]]
        self.source[v] = True
        self.label[v] = self.n
        i = self._arcs(v)
        i = i[(self.cap[i] > 0) & ~self.source[self.dst[i]]]
        x = self.cap[i]
        self.cap[i] = 0
        self.cap[self.rev[i]] += x
        self.excess += np.bincount(self.dst[i], weights=x, minlength=self.n).astype(np.int64)

    def add_sink(self, v: np.ndarray) -> None:
        self.sink[v] = True
        self.stale = True  # labels no longer bound distances

    def reach(self, start: np.ndarray, forward: bool = True, blocked: np.ndarray | None = None) -> np.ndarray:
        """Mask of the vertices reached from ``start`` over residual arcs, or that reach it; and, as distances, when."""
        seen = np.full(self.n, self.n, np.int64)
        seen[start] = 0
        layer, d = np.unique(start), 0
        while len(layer):
            d += 1
            i = self._arcs(layer)
            open_ = self.cap[i] > 0 if forward else self.cap[self.rev[i]] > 0
            to = self.dst[i[open_]]
            to = to[seen[to] == self.n]
            if blocked is not None:
                to = to[~blocked[to]]
            seen[to] = d
            layer = np.unique(to)
        return seen

    def relabel_all(self) -> None:
        """Exact distances to the sinks, the number of vertices where none is reached."""
        self.label = self.reach(np.flatnonzero(self.sink), forward=False, blocked=self.source)
        self.label[self.source] = self.n

    def run(self, bound: int | None = None, idle: int = 500, few: int = 1500) -> int:
        """A maximum preflow; what the sinks hold. Stops early once that is over ``bound``.

        Labels are made exact after work in proportion to the network, and when ``idle`` rounds of under ``few`` active vertices have not changed the value.
        """
        if self.stale:
            self.relabel_all()
            self.stale = False
        work, still, value = 0, 0, -1
        terminal = self.source | self.sink
        while True:
            v = np.flatnonzero((self.excess > 0) & (self.label < self.n) & ~terminal)
            now = int(self.excess[self.sink].sum())
            if not len(v) or bound is not None and now > bound:
                return now
            still = still + 1 if now == value and len(v) < few else 0
            value = now
            i, owner = self._arcs(v), np.repeat(np.arange(len(v)), self.degree[v])
            down = (self.cap[i] > 0) & (self.label[self.dst[i]] == self.label[v][owner] - 1)
            x = np.where(down, self.cap[i], 0)
            run = np.cumsum(x)
            start = np.concatenate([[0], run])[np.cumsum(self.degree[v]) - self.degree[v]]
            before = run - x - start[owner]
            push = np.clip(self.excess[v][owner] - before, 0, x)
            on = push > 0
            j, y = i[on], push[on]
            self.cap[j] -= y
            self.cap[self.rev[j]] += y
            self.excess += np.bincount(self.dst[j], weights=y, minlength=self.n).astype(np.int64)
            self.excess[v] -= np.bincount(owner[on], weights=y, minlength=len(v)).astype(np.int64)
            left = self.excess[v] > 0
            low = np.where((self.cap[i] > 0) & ~self.source[self.dst[i]], self.label[self.dst[i]], self.n)
            least = np.minimum.reduceat(np.append(low, self.n), np.cumsum(self.degree[v]) - self.degree[v]) if len(i) else np.full(len(v), self.n)
            fresh = np.where(self.degree[v] > 0, np.minimum(least + 1, self.n), self.n)
            raise_ = left & (fresh > self.label[v])
            self.label[v[raise_]] = fresh[raise_]
            work += len(i)
            if work > 6 * len(self.dst) + self.n or still >= idle:
                self.relabel_all()
                work = still = 0

    def source_side(self) -> np.ndarray:
        """Reach of the sources and of what is left over outside the sinks: a minimum cut without undoing the leftovers."""
        return self.reach(np.flatnonzero(self.source | (self.excess > 0) & ~self.sink)) < self.n

    def sink_side(self) -> np.ndarray:
        return self.reach(np.flatnonzero(self.sink), forward=False) < self.n


def pierce(g: Csr, source: int, sink: int, most: tuple[int, int], distance: np.ndarray, bound: int, bulk: bool = True, warmup: int = 3, implicit: bool = False) -> tuple[np.ndarray, int, int] | None:
    """(side of each node, cut value, rounds) of the first minimum cut that both blocks have room for; None if it would cost over ``bound``.

    Of a maximum preflow, the smallest source side and the smallest sink side are candidates. If neither fits, the lighter one becomes
    terminal as a whole and takes further nodes: at best such that no augmenting path arises (outside both reaches), of those the
    farther from the old cut. From round ``warmup`` on it takes as many as half the weight still missing seems to need.
    """
    n, total = g.n, g.total
    flow = Flow(g, implicit)
    flow.add_sink(np.array([sink]))
    flow.add_source(np.array([source]))
    rounds, pierced, gained = [0, 0], [0, 0], [0, 0]
    start = [int(g.node_weight[source]), int(g.node_weight[sink])]
    before = list(start)
    while True:
        value = flow.run(bound)
        if value > bound:
            return None
        reach = flow.source_side(), flow.sink_side()
        weight = [int(g.node_weight[r[:n]].sum()) for r in reach]
        for x in (0, 1):
            if weight[x] <= most[x] and total - weight[x] <= most[1 - x]:
                return (~reach[0][:n]).astype(np.int64) if x == 0 else reach[1][:n].astype(np.int64), value, sum(rounds)
        x = 0 if weight[0] <= weight[1] else 1
        own = weight[x]
        gained[x] += max(0, own - before[x])
        before[x] = own
        inside = np.flatnonzero(reach[x] & ~flow.source & ~flow.sink)
        (flow.add_source if x == 0 else flow.add_sink)(inside)
        open_ = np.flatnonzero(~flow.source[:n] & ~flow.sink[:n])
        if not len(open_):
            return None
        open_ = open_[np.lexsort((open_, -distance[open_], reach[1 - x][open_]))]
        rounds[x] += 1
        count = 1
        if bulk and rounds[x] > warmup and pierced[x]:
            goal = (total / 2 - start[x]) * (1 - 0.5 ** rounds[x])
            count = max(1, int((start[x] + goal - own) / max(1e-9, gained[x] / pierced[x])))
        take = open_[:count]
        fits = own + np.cumsum(g.node_weight[take]) <= most[x]
        take = take[: max(1, int(fits.sum()))]
        pierced[x] += len(take)
        (flow.add_source if x == 0 else flow.add_sink)(take)


def region(state: State, nets: np.ndarray, block: int, most: int, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """(nodes, hops) of ``block`` around the pins of ``nets``, breadth first up to ``depth`` hops and ``most`` weight."""
    g = state.g
    seen, used = np.zeros(g.n, bool), np.zeros(g.m, bool)
    found, hops, load = [], [], 0
    used[nets] = True
    layer = np.unique(g.pins_of(nets))
    for hop in range(depth + 1):
        layer = layer[(state.part[layer] == block) & ~seen[layer]]
        seen[layer] = True
        run = load + np.cumsum(g.node_weight[layer])
        take = layer[run <= most]
        found.append(take)
        hops.append(np.full(len(take), hop))
        load += int(g.node_weight[take].sum())
        if len(take) < len(layer) or hop == depth:
            break
        hit = np.zeros(g.m, bool)
        hit[g.nets_of(layer)] = True
        hit &= ~used
        used |= hit
        layer = np.unique(g.pins_of(np.flatnonzero(hit)))
    return np.concatenate(found), np.concatenate(hops)


def refine_pair(state: State, i: int, j: int, limit: np.ndarray, alpha: float = 16.0, depth: int = 2, bulk: bool = True, implicit: bool = False) -> tuple[np.ndarray, np.ndarray, int]:
    """(nodes, targets, expected gain) of a better or as good but better balanced cut between blocks i and j; nothing changes ``state``.

    Only what nets have in the two blocks counts, which is exact for connectivity. What lies outside the regions is
    contracted to a terminal on each side. A region's weight is bounded so that the two blocks can exchange no more than (1 + alpha eps) allows.
    """
    return solve_pair(pair_problem(state, i, j, limit, alpha, depth), bulk, implicit)


def pair_problem(state: State, i: int, j: int, limit: np.ndarray, alpha: float = 16.0, depth: int = 2) -> tuple | None:
    """The regions of a pair as a hypergraph of its own, with what ``solve_pair`` needs to know beside it: all that a task has to get. None if there is nothing to do."""
    g, none = state.g, None
    nets = np.flatnonzero((state.phi[:, i] > 0) & (state.phi[:, j] > 0))
    if not len(nets):
        return none
    weight = int(state.weight[i]), int(state.weight[j])
    half = (sum(weight) + 1) // 2
    eps = max(0.0, min(int(limit[i]), int(limit[j])) / max(1.0, sum(weight) / 2) - 1)
    sides = []
    for x, b in enumerate((i, j)):
        nodes, hops = region(state, nets, b, max(1, int((1 + alpha * eps) * half) - weight[1 - x]), depth)
        if len(nodes) and int(g.node_weight[nodes].sum()) == weight[x]:
            nodes, hops = nodes[:-1], hops[:-1]  # the terminal keeps a node
        sides.append((nodes, hops))
    nodes = np.concatenate([sides[0][0], sides[1][0]])
    if not len(nodes):
        return none
    number = np.full(g.n, -1, np.int64)
    number[state.part == i] = 0
    number[state.part == j] = 1
    number[nodes] = 2 + np.arange(len(nodes))
    hit = np.zeros(g.m, bool)
    hit[g.nets_of(nodes)] = True
    hit[nets] = True
    own = np.flatnonzero(hit)
    pins, at = number[g.pins_of(own)], np.repeat(np.arange(len(own)), g.size[own])
    on = pins >= 0
    key = np.sort(at[on] * (len(nodes) + 2) + pins[on])
    key = key[np.concatenate([[True], key[1:] != key[:-1]])]
    at, pins = key // (len(nodes) + 2), key % (len(nodes) + 2)
    size = np.bincount(at, minlength=len(own))
    keep = (size >= 2)[at]
    name = np.cumsum(size >= 2) - 1
    node_weight = np.concatenate([[weight[x] - int(g.node_weight[sides[x][0]].sum()) for x in (0, 1)], g.node_weight[nodes]])
    small = Csr(name[at[keep]], pins[keep], g.net_weight[own][size >= 2], node_weight)
    side = np.concatenate([[0, 1], np.repeat([0, 1], [len(sides[0][0]), len(sides[1][0])])])
    old = small.objective(side, 2)
    distance = np.concatenate([[0, 0], sides[0][1], sides[1][1]])
    return small, side, distance, old, nodes, (i, j), weight, (int(limit[i]), int(limit[j]))


def solve_pair(problem: tuple | None, bulk: bool = True, implicit: bool = False) -> tuple[np.ndarray, np.ndarray, int]:
    """(nodes, targets, expected gain) of ``pair_problem``."""
    none = np.zeros(0, np.int64), np.zeros(0, np.int64), 0
    if problem is None:
        return none
    small, side, distance, old, nodes, (i, j), weight, most = problem
    got = pierce(small, 0, 1, most, distance, old, bulk, implicit=implicit)
    if got is None:
        return none
    new, value, _ = got
    moved = np.flatnonzero(new[2:] != side[2:])
    if value == old:
        after = [int(small.node_weight[new == x].sum()) for x in (0, 1)]
        if max(a - b for a, b in zip(after, most, strict=True)) >= max(w - b for w, b in zip(weight, most, strict=True)):
            return none
    return nodes[moved], np.array([i, j])[new[2:][moved]], old - value


def apply_pair(state: State, nodes: np.ndarray, dst: np.ndarray, src: np.ndarray, limit: np.ndarray) -> tuple[int, str]:
    """Apply one pair's result to the present partition; (gain, what became of it).

    Nodes that have left the block they were found in are dropped. A result that would now overload a block, or whose exact joint gain is negative, is
    taken back.
    """
    keep = state.part[nodes] == src
    nodes, dst, src = nodes[keep], dst[keep], src[keep]
    if not len(nodes):
        return 0, "gone"
    was = np.maximum(state.weight - limit, 0).sum()
    got = state.apply(nodes, dst)
    if np.maximum(state.weight - limit, 0).sum() > was:
        state.apply(nodes, src)
        return 0, "unbalanced"
    if got < 0:
        state.apply(nodes, src)
        return 0, "worse"
    return got, "dropped some" if not keep.all() else "applied"


def active_pairs(state: State, active: set[int]) -> list[tuple[int, int]]:
    """Adjacent pairs with an active block, the heaviest cut first."""
    on = (state.phi > 0).astype(np.float64)
    shared = (on * state.g.net_weight[:, None]).T @ on
    pairs = [(-shared[i, j], i, j) for i in range(state.k) for j in range(i + 1, state.k) if shared[i, j] and (i in active or j in active)]
    return [(i, j) for _, i, j in sorted(pairs)]


def refine(state: State, limit: np.ndarray, rounds: int = 2, least: float = 1e-3, solve=None, alpha: float = 16.0, depth: int = 2, log: list | None = None) -> int:
    """Rounds over the active adjacent pairs; a block stays active while a pair of it improves, rounds end when they gain under a thousandth.

    ``solve(state, pairs)`` yields results as they come, by other tasks or here one after another; each is judged by itself.
    """
    gained, active = 0, set(range(state.k))
    for r in range(rounds):
        value, nxt, before = state.value(), set(), gained
        pairs = active_pairs(state, active)
        results = solve(state, pairs) if solve else ((p, *refine_pair(state, *p, limit, alpha, depth)) for p in pairs)
        for (i, j), nodes, dst, expected in results:
            if not len(nodes):
                continue
            src = np.where(dst == i, j, i)
            got, what = apply_pair(state, nodes, dst, src, limit)
            if log is not None:
                log.append({"phase": "flows", "round": r, "bi": i, "bj": j, "expected": int(expected), "attributed": got, "result": what})
            gained += got
            if got > 0:
                nxt |= {i, j}
        active = nxt
        if gained - before < least * max(1, value) or not active:
            break
    return gained
