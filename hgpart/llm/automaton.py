"""Regular expressions to one minimal deterministic automaton over bytes."""

from __future__ import annotations

import numpy as np

DIGIT, UPPER, LOWER = frozenset(range(48, 58)), frozenset(range(65, 91)), frozenset(range(97, 123))
ESCAPES = {"d": DIGIT, "w": DIGIT | UPPER | LOWER | {95}, "s": frozenset((9, 10, 11, 12, 13, 32)), "n": frozenset((10,)), "r": frozenset((13,)), "t": frozenset((9,))}


class _Parser:
    """A tree of the pattern: ``("set", bytes)``, ``("cat", parts)``, ``("alt", parts)`` or ``("rep", part, least, most)``.

    Literals, ``.`` (no newline), classes, ``\\xHH``, groups, ``|`` and greedy ``? * + {m,n}``;
    bytes above 127 are outside every class.
    """

    def __init__(self, pattern: str, any_case: bool = False):
        self.p, self.i, self.any_case = pattern, 0, any_case

    def fold(self, s: frozenset) -> frozenset:
        return frozenset(s | {b ^ 32 for b in s if b in UPPER | LOWER}) if self.any_case else s

    def alt(self):
        parts = [self.cat()]
        while self.i < len(self.p) and self.p[self.i] == "|":
            self.i += 1
            parts.append(self.cat())
        return parts[0] if len(parts) == 1 else ("alt", parts)

    def cat(self):
        parts = []
        while self.i < len(self.p) and self.p[self.i] not in "|)":
            parts.append(self.repeat())
        return ("cat", parts)

    def repeat(self):
        part = self.atom()
        while self.i < len(self.p) and self.p[self.i] in "?*+{":
            c = self.p[self.i]
            if c == "{":
                end = self.p.index("}", self.i)
                low, comma, high = self.p[self.i + 1:end].partition(",")
                part, self.i = ("rep", part, int(low), int(high) if high else None if comma else int(low)), end + 1
            else:
                part, self.i = ("rep", part, int(c == "+"), 1 if c == "?" else None), self.i + 1
        return part

    def escape(self) -> frozenset:
        c = self.p[self.i]
        self.i += 1
        if c == "x":
            self.i += 2
            return frozenset((int(self.p[self.i - 2:self.i], 16),))
        return ESCAPES.get(c, frozenset((ord(c),)))

    def atom(self):
        c = self.p[self.i]
        self.i += 1
        if c == "(":
            if self.p.startswith("?:", self.i):
                self.i += 2
            inner = self.alt()
            if self.p[self.i:self.i + 1] != ")":
                raise ValueError("group without end")
            self.i += 1
            return inner
        if c == "[":
            return ("set", self.fold(self.klass()))
        if c == ".":
            return ("set", frozenset(range(128)) - {10})
        return ("set", self.fold(self.escape() if c == "\\" else frozenset((ord(c),))))

    def klass(self) -> frozenset:
        negated = self.p[self.i] == "^"
        self.i += negated
        found: set[int] = set()
        first = True
        while first or self.p[self.i] != "]":
            first = False
            c = self.p[self.i]
            self.i += 1
            one = self.escape() if c == "\\" else frozenset((ord(c),))
            if self.p[self.i] == "-" and self.p[self.i + 1] != "]" and len(one) == 1:
                self.i += 1
                c = self.p[self.i]
                self.i += 1
                high = self.escape() if c == "\\" else frozenset((ord(c),))
                one = frozenset(range(min(one), max(high) + 1))
            found |= one
        self.i += 1
        return frozenset(range(128)) - found if negated else frozenset(found)


class _Nfa:
    def __init__(self):
        self.empty: list[list[int]] = []
        self.moves: list[list[tuple[frozenset, int]]] = []

    def state(self) -> int:
        self.empty.append([])
        self.moves.append([])
        return len(self.empty) - 1

    def add(self, tree, start: int) -> int:
        """Build ``tree`` from state ``start``; its end state."""
        if tree[0] == "set":
            end = self.state()
            self.moves[start].append((tree[1], end))
            return end
        if tree[0] == "cat":
            for part in tree[1]:
                start = self.add(part, start)
            return start
        if tree[0] == "alt":
            end = self.state()
            for part in tree[1]:
                head = self.state()
                self.empty[start].append(head)
                self.empty[self.add(part, head)].append(end)
            return end
        _, part, least, most = tree
        for _ in range(least):
            start = self.add(part, start)
        if most is None:
            head = self.state()
            self.empty[start].append(head)
            self.empty[self.add(part, head)].append(head)
            end = self.state()
            self.empty[head].append(end)
            return end
        end = self.state()
        self.empty[start].append(end)
        for _ in range(most - least):
            start = self.add(part, start)
            self.empty[start].append(end)
        return end

    def closure(self, states) -> frozenset:
        found, todo = set(states), list(states)
        while todo:
            for t in self.empty[todo.pop()]:
                if t not in found:
                    found.add(t)
                    todo.append(t)
        return frozenset(found)


class Automaton:
    """``next[state, byte]``, ``accepts[state]`` (bit k: rule k ends here), start state 0, ``dead`` state or -1."""

    def __init__(self, table: np.ndarray, accepts: np.ndarray):
        self.next, self.accepts = table, accepts
        self.dead = next((s for s in range(len(accepts)) if not accepts[s] and (table[s] == s).all()), -1)


def compile_rules(rules: list[tuple[str, bool]], anywhere: bool, max_states: int = 20_000) -> Automaton:
    """One automaton for all ``rules`` (pattern, any_case); with ``anywhere`` a match may start at every byte."""
    nfa = _Nfa()
    start = nfa.state()
    finals: dict[int, int] = {}
    for k, (pattern, any_case) in enumerate(rules):
        parser = _Parser(pattern, any_case)
        tree = parser.alt()
        if parser.i != len(pattern):
            raise ValueError(f"unbalanced pattern {pattern!r}")
        head = nfa.state()
        nfa.empty[start].append(head)
        finals[nfa.add(tree, head)] = 1 << k
    # bytes that no rule tells apart share a column
    sets = {s for moves in nfa.moves for s, _ in moves}
    kinds: dict[tuple, int] = {}
    kind = np.array([kinds.setdefault(tuple(b in s for s in sets), len(kinds)) for b in range(256)])
    member = {s: frozenset(kind[list(s)].tolist()) for s in sets}
    first = nfa.closure([start])
    ids, todo, rows = {first: 0}, [first], []
    while todo:
        state = todo.pop(0)
        row = []
        for c in range(len(kinds)):
            to = {t for s in state for got, t in nfa.moves[s] if c in member[got]}
            if anywhere:
                to.add(start)
            to = nfa.closure(to)
            if to not in ids:
                if len(ids) >= max_states:
                    raise ValueError("the rules need too many states")
                ids[to] = len(ids)
                todo.append(to)
            row.append(ids[to])
        rows.append(row)
    table = np.array(rows, np.int64).reshape(len(ids), len(kinds))
    accepts = np.array([sum({finals[s] for s in state if s in finals}) for state in ids], np.int64)
    # partition refinement until states of a class go to the same classes
    _, part = np.unique(accepts, return_inverse=True)
    while True:
        signature = np.column_stack([part[:, None], part[table]])
        _, fresh = np.unique(signature, axis=0, return_inverse=True)
        fresh = fresh.reshape(-1)
        if fresh.max() == part.max():
            break
        part = fresh
    order: dict[int, int] = {}
    for p in part:
        order.setdefault(int(p), len(order))
    part = np.array([order[int(p)] for p in part])
    lead = np.array([int(np.argmax(part == k)) for k in range(len(order))])
    small = part[table[lead]]
    return Automaton(small[:, kind].astype(np.int32), accepts[lead])
