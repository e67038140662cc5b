"""Flows on expanded hypergraphs: push-relabel, augmenting paths, and balanced cuts by piercing."""

from __future__ import annotations

from collections import deque

INF = 1 << 60


class Network:
    """Residual arcs in pairs; arc i and i ^ 1 are each other's reverse."""

    def __init__(self, n: int):
        self.out: list[list[int]] = [[] for _ in range(n)]
        self.to: list[int] = []
        self.cap: list[int] = []

    @property
    def n(self) -> int:
        return len(self.out)

    def arc(self, a: int, b: int, cap: int, back: int = 0) -> None:
        self.out[a].append(len(self.to))
        self.to.append(b)
        self.cap.append(cap)
        self.out[b].append(len(self.to))
        self.to.append(a)
        self.cap.append(back)

    def reach(self, start, forward: bool = True) -> list[bool]:
        """Vertices reached from ``start`` over residual arcs, or that reach it."""
        seen = [False] * self.n
        todo = list(start)
        for v in todo:
            seen[v] = True
        while todo:
            v = todo.pop()
            for i in self.out[v]:
                w = self.to[i]
                if not seen[w] and self.cap[i if forward else i ^ 1] > 0:
                    seen[w] = True
                    todo.append(w)
        return seen


def lawler(pins: list[list[int]], net_weight: list[int], n: int, cap_pins: bool = True) -> Network:
    """Nodes 0..n-1, an in-vertex n + 2 e and an out-vertex n + 2 e + 1 for every net with a bridge of its weight.

    Pin arcs are unbounded; ``cap_pins`` bounds them by the net's weight, which leaves the flow value alone. Two-pin nets become plain edges.
    """
    big = [vs for vs in pins if len(vs) != 2]
    net = Network(n + 2 * len(big))
    j = 0
    for vs, w in zip(pins, net_weight, strict=True):
        if len(vs) == 2:
            net.arc(vs[0], vs[1], w, w)
            continue
        a, b = n + 2 * j, n + 2 * j + 1
        j += 1
        net.arc(a, b, w)
        for v in vs:
            net.arc(v, a, w if cap_pins else INF)
            net.arc(b, v, w if cap_pins else INF)
    return net


def graph_network(edges: list[tuple[int, int, int]], n: int) -> Network:
    net = Network(n)
    for a, b, w in edges:
        net.arc(a, b, w, w)
    return net


class PushRelabel:
    """A preflow that grows as terminals are added. First-in first-out discharging with exact labels now and then."""

    def __init__(self, net: Network):
        self.net, self.excess = net, [0] * net.n
        self.source, self.sink = [False] * net.n, [False] * net.n
        self.label = [0] * net.n
        self.fresh = True

    def add_source(self, v: int) -> None:
        self.source[v] = True

    def add_sink(self, v: int) -> None:
        self.sink[v] = True
        self.fresh = True  # labels no longer bound distances

    def relabel_all(self) -> None:
        """Distance to the sinks in the residual network, number of vertices where none is reached."""
        net, n = self.net, self.net.n
        label = [n] * n
        todo = deque(v for v in range(n) if self.sink[v])
        for v in todo:
            label[v] = 0
        while todo:
            v = todo.popleft()
            for i in net.out[v]:
                w = net.to[i]
                if label[w] == n and not self.source[w] and not self.sink[w] and net.cap[i ^ 1] > 0:
                    label[w] = label[v] + 1
                    todo.append(w)
        self.label = label

    def run(self) -> int:
        """A maximum preflow; the flow value, which is what the sinks hold."""
        net, n, excess = self.net, self.net.n, self.excess
        to, cap, out = net.to, net.cap, net.out
        if self.fresh:
            self.relabel_all()
            self.fresh = False
        for s in range(n):
            if self.source[s]:
                self.label[s] = n
                for i in out[s]:
                    if cap[i] > 0 and not self.source[to[i]]:
                        excess[to[i]] += cap[i]
                        cap[i ^ 1] += cap[i]
                        cap[i] = 0
        queue = deque(v for v in range(n) if excess[v] > 0 and not self.source[v] and not self.sink[v] and self.label[v] < n)
        queued = [False] * n
        for v in queue:
            queued[v] = True
        work = 0
        while queue:
            v = queue.popleft()
            queued[v] = False
            while excess[v] > 0 and self.label[v] < n:
                low = 2 * n
                for i in out[v]:
                    if cap[i] <= 0:
                        continue
                    w = to[i]
                    if self.source[w]:
                        continue
                    if self.label[w] < self.label[v]:
                        d = min(excess[v], cap[i])
                        cap[i] -= d
                        cap[i ^ 1] += d
                        excess[v] -= d
                        excess[w] += d
                        if not self.sink[w] and not queued[w]:
                            queued[w] = True
                            queue.append(w)
                        if not excess[v]:
                            break
                    low = min(low, self.label[w])
                work += len(out[v])
                if excess[v]:
                    self.label[v] = min(n, low + 1)
            if work > 4 * len(to) + n:
                self.relabel_all()
                for s in range(n):
                    if self.source[s]:
                        self.label[s] = n
                work = 0
        return sum(x for v, x in enumerate(excess) if self.sink[v])

    def source_side(self) -> list[bool]:
        """Reach of the sources and of what is left over outside the sinks: a minimum cut without undoing the leftovers."""
        n = self.net.n
        return self.net.reach([v for v in range(n) if self.source[v] or self.excess[v] > 0 and not self.sink[v]])

    def sink_side(self) -> list[bool]:
        return self.net.reach([v for v in range(self.net.n) if self.sink[v]], forward=False)


def augmenting_paths(net: Network, s: int, t: int) -> int:
    """Flow value by shortest augmenting paths; changes the network. A reference for tests."""
    total = 0
    while True:
        via, todo = {s: -1}, deque([s])
        while todo and t not in via:
            v = todo.popleft()
            for i in net.out[v]:
                if net.cap[i] > 0 and net.to[i] not in via:
                    via[net.to[i]] = i
                    todo.append(net.to[i])
        if t not in via:
            return total
        d, v = INF, t
        while v != s:
            d = min(d, net.cap[via[v]])
            v = net.to[via[v] ^ 1]
        v = t
        while v != s:
            net.cap[via[v]] -= d
            net.cap[via[v] ^ 1] += d
            v = net.to[via[v] ^ 1]
        total += d


def sync_push_relabel(net: Network, s: int, t: int) -> int:
    """The same by synchronous rounds on old labels: a pair of active vertices uses an arc between them in one direction only."""
    n = net.n
    label, excess = [0] * n, [0] * n
    label[s] = n
    for i in net.out[s]:
        excess[net.to[i]] += net.cap[i]
        net.cap[i ^ 1] += net.cap[i]
        net.cap[i] = 0
    while True:
        active = [v for v in range(n) if excess[v] > 0 and v != t and v != s and label[v] < n]
        if not active:
            return excess[t]
        delta, fresh = [0] * n, {}
        for v in active:
            left, low = excess[v], 2 * n
            for i in net.out[v]:
                w = net.to[i]
                if net.cap[i] <= 0:
                    continue
                if label[w] < label[v] and left:
                    # arcs to a lower label can be used by the higher end alone, so both ends never push over one
                    d = min(left, net.cap[i])
                    net.cap[i] -= d
                    net.cap[i ^ 1] += d
                    delta[v] -= d
                    delta[w] += d
                    left -= d
                    if net.cap[i] > 0:
                        low = min(low, label[w])
                else:
                    low = min(low, label[w])
            if left:
                fresh[v] = min(n, low + 1)
        for v, d in enumerate(delta):
            excess[v] += d
        for v, x in fresh.items():
            # arcs opened towards v in this round allow lower labels only
            label[v] = max(label[v], x) if label[v] < n else n


def piercing_bipartition(pins: list[list[int]], net_weight: list[int], node_weight: list[int], source: int, sink: int, most_source: int, most_sink: int, distance: list[int] | None = None, bulk: bool = True, warmup: int = 3, stop_at: int | None = None) -> tuple[list[int], int, int] | None:
    """(side of each node, cut value, rounds) of the first cut that both blocks have room for; None if none is found or it costs over ``stop_at``.

    After each maximum preflow the smallest source side and the smallest sink side are candidates. If neither fits, the
    lighter one becomes terminal as a whole and takes further nodes, at best such that no augmenting path arises (outside both reaches), then farther from
    the old cut (``distance``). From round ``warmup`` on, as many as an estimate says that half the weight still
    missing needs.
    """
    n, total = len(node_weight), sum(node_weight)
    net = lawler(pins, net_weight, n)
    flow = PushRelabel(net)
    flow.add_source(source)
    flow.add_sink(sink)
    far = distance or [0] * n
    rounds, start = [0, 0], [node_weight[source], node_weight[sink]]
    pierced, gained = [0, 0], [0, 0]
    before = [start[0], start[1]]
    while True:
        value = flow.run()
        if stop_at is not None and value > stop_at:
            return None
        s_reach, t_reach = flow.source_side(), flow.sink_side()
        s_side = [v for v in range(n) if s_reach[v]]
        t_side = [v for v in range(n) if t_reach[v]]
        ws, wt = sum(node_weight[v] for v in s_side), sum(node_weight[v] for v in t_side)
        done = sum(rounds)
        if ws <= most_source and total - ws <= most_sink:
            return [0 if s_reach[v] else 1 for v in range(n)], value, done
        if wt <= most_sink and total - wt <= most_source:
            return [1 if t_reach[v] else 0 for v in range(n)], value, done
        side = 0 if ws <= wt else 1
        reach, other, own = (s_reach, t_reach, ws) if side == 0 else (t_reach, s_reach, wt)
        gained[side] += max(0, own - before[side])
        before[side] = own
        for v in range(n):
            if reach[v] and not (flow.sink if side == 0 else flow.source)[v]:
                if side == 0 and not flow.source[v]:
                    flow.add_source(v)
                elif side == 1 and not flow.sink[v]:
                    flow.add_sink(v)
        if side == 0:
            # net vertices in the reach belong to the terminal too
            for v in range(n, net.n):
                if reach[v]:
                    flow.add_source(v)
        else:
            for v in range(n, net.n):
                if reach[v] and not flow.source[v]:
                    flow.add_sink(v)
        open_ = [v for v in range(n) if not flow.source[v] and not flow.sink[v]]
        if not open_:
            return None
        open_.sort(key=lambda v: (other[v] or reach[v], -far[v], v))
        rounds[side] += 1
        count = 1
        if bulk and rounds[side] > warmup and pierced[side]:
            goal = (total / 2 - start[side]) * (1 - 0.5 ** rounds[side])
            per = max(1e-9, gained[side] / pierced[side])
            count = max(1, int((start[side] + goal - own) / per))
        most = most_source if side == 0 else most_sink
        for v in open_[:count]:
            if own + node_weight[v] > most and v != open_[0]:
                break
            own += node_weight[v]
            pierced[side] += 1
            if side == 0:
                flow.add_source(v)
            else:
                flow.add_sink(v)
