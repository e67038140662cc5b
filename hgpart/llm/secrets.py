"""Secret scanning by one combined deterministic automaton."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .automaton import compile_rules
from .common import as_bytes, column_stretches, small_batches, tidy, worker_cache

# fixed values: (kind, pattern, letters in either case, least bytes of the match, least bytes of the value)
# Least lengths are tested on whole matches, not counted by the automaton, but for hex: counts of several rules
# would multiply its states, while every word with a letter from a to f would match hex of any length.
RULES = (
    ("assign", r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?[A-Za-z0-9+/_.=-]+""", True, 0, 6),
    ("access", r"AKIA[A-Z0-9]+", False, 20, 0),
    ("hex", r"[0-9a-f]{12,}", False, 24, 0),
    ("key_block", r"-----BEGIN [A-Z ]*PRIVATE KEY-----", False, 0, 0),
    ("web_token", r"eyJ[A-Za-z0-9_-]+\.eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+", False, 0, 0),
    ("forge_token", r"gh[pousr]_[A-Za-z0-9]+", False, 40, 0),
    ("chat_token", r"xox[abprs]-[A-Za-z0-9-]+", False, 15, 0),
)
BASE = ("assign", "access", "hex")
SEPARATORS = b":="
#: Fewer texts than this still open: they go on one at a time.
LOCKSTEP = 48


class Tagged:
    """All anchored automata run together over a text, with a register for the start of every open match.

    A state lists, rule by rule, the states of the rule's automaton in which matches are open, oldest start first, each state once:
    of two matches in one state only the older can be leftmost. Once a match accepts, younger ones of its rule are dropped and none starts
    until it ends. States and their transitions are made when a text first needs them and kept as rows of 256 entries; a
    transition says which registers the next state keeps (-1: a match starts here), which matches now end at the next byte at the earliest and which
    ended before this one. So each byte is read once, whatever it repeats.
    """

    def __init__(self, automata, most: int = 50_000):
        self.automata, self.most = automata, most
        # once these accept they accept until they die, so that nothing is read again after a match
        self.simple = [all(a.accepts[t] or t == a.dead for s in np.flatnonzero(a.accepts) for t in set(a.next[s].tolist())) for a in automata]
        self.tables = [([r.tolist() for r in a.next], [bool(x) for x in a.accepts], a.dead) for a in automata]
        self._clear()

    def _clear(self) -> None:
        empty = tuple(() for _ in self.automata)
        self.number, self.states, self.rows = {empty: 0}, [empty], [[None] * 256]

    def _step(self, state: int, byte: int):
        """(next state, registers kept, (rule, register) of matches that end before this byte, rules whose younger matches ended under an open older one)."""
        base, keep, ended, odd, nxt = 0, [], [], [], []
        for k, open_ in enumerate(self.states[state]):
            table, accepts, dead = self.tables[k]
            was = [accepts[s] for s in open_]
            moved = [(table[s][byte], base + i) for i, s in enumerate(open_)]
            live = [(t, r) for t, r in moved if t != dead]
            for i, (t, r) in enumerate(moved):
                if t == dead and was[i]:
                    if any(r2 < r for _, r2 in live):
                        odd.append(k)
                    else:
                        ended.append((k, r))
            base += len(open_)
            if not any(w and t != dead for w, (t, _) in zip(was, moved, strict=True)):
                first = table[0][byte]
                if first != dead:
                    live.append((first, -1))
            seen, out = set(), []
            for t, r in live:
                if t in seen:
                    continue
                seen.add(t)
                out.append((t, r))
                if accepts[t]:
                    break
            nxt.append(tuple(t for t, _ in out))
            keep += [r for _, r in out]
        key = tuple(nxt)
        to = self.number.get(key)
        if to is None:
            to = self.number[key] = len(self.states)
            self.states.append(key)
            self.rows.append([None] * 256)
        same = keep == list(range(base))
        return to, None if same else tuple(keep), tuple(ended) or None, tuple(odd) or None

    def spans(self, text: bytes) -> tuple[list[tuple[int, int, int]], set[int]]:
        """(start, rule, end) of the leftmost longest matches that do not overlap, rule by rule; and rules that must be looked at again."""
        if len(self.states) > self.most:
            self._clear()
        rows, state, regs, out, again = self.rows, 0, (), [], {k for k, x in enumerate(self.simple) if not x}
        for j, byte in enumerate(text):
            found = rows[state][byte]
            if found is None:
                found = rows[state][byte] = self._step(state, byte)
            state, keep, ended, odd = found
            if ended:
                for k, r in ended:
                    out.append((regs[r], k, j))
            if odd:
                again.update(odd)
            if keep is not None:
                regs = tuple([regs[r] if r >= 0 else j for r in keep])
        base = 0
        for k, open_ in enumerate(self.states[state]):
            accepts = self.tables[k][1]
            on = [i for i, s in enumerate(open_) if accepts[s]]
            if on:
                out.append((regs[base + on[0]], k, len(text)))
            base += len(open_)
        return [x for x in out if x[1] not in again], again


class Scanner:
    """One pass of the combined automaton over all texts finds those with a match of any rule; one pass over each of those gives the spans."""

    def __init__(self, rules=RULES):
        self.rules = rules
        self.all = compile_rules([(p, c) for _, p, c, _, _ in rules], anywhere=True)
        self.flat = self.all.next.astype(np.int32).ravel()
        self.rows = [bytes(r.tolist()) if self.all.next.max() < 256 else r.tolist() for r in self.all.next]
        self.accepts = self.all.accepts.tolist()
        own = [compile_rules([(pattern, any_case)], anywhere=False) for _, pattern, any_case, _, _ in rules]
        self.own = [([r.tolist() for r in a.next], a.accepts.tolist(), a.dead, np.flatnonzero(a.next[0] != a.dead)) for a in own]
        self.tagged = Tagged(own)

    def occurring(self, texts: list[bytes]) -> np.ndarray:
        """Bit k of each text: rule k matches somewhere. Texts advance in lockstep, a byte of each at a time."""
        order = sorted(range(len(texts)), key=lambda i: -len(texts[i]))
        sizes = np.array([len(texts[i]) for i in order], np.int64)
        found = np.zeros(len(texts), np.int64)
        if not len(texts):
            return found
        data = np.frombuffer(b"".join(texts[i] for i in order), np.uint8)
        start = np.concatenate([[0], np.cumsum(sizes)[:-1]])
        state = np.zeros(len(texts), np.int32)
        longest = int(sizes[LOCKSTEP - 1]) if len(texts) >= LOCKSTEP else 0
        live = np.searchsorted(-sizes, -np.arange(1, longest + 1), side="right")
        bits = self.all.accepts
        flat = self.flat
        for j in range(longest):
            n = live[j]
            s = flat[(state[:n] << 8) + data[start[:n] + j]]
            state[:n] = s
            found[:n] |= bits[s]
        rows, accepts = self.rows, self.accepts
        for i in range(min(LOCKSTEP, len(texts))):
            s, seen = int(state[i]), 0
            for b in texts[order[i]][longest:]:
                s = rows[s][b]
                if accepts[s]:
                    seen |= accepts[s]
            found[i] |= seen
        out = np.zeros(len(texts), np.int64)
        out[order] = found
        return out

    def spans(self, text: bytes, k: int) -> list[tuple[int, int]]:
        """Leftmost longest matches of rule k that do not overlap, found start by start: for rules that the single pass cannot settle; byte offsets."""
        table, accepts, dead, heads = self.own[k]
        starts = np.flatnonzero(np.isin(np.frombuffer(text, np.uint8), heads)).tolist()
        out, free, n = [], 0, len(text)
        for i in starts:
            if i < free:
                continue
            s, end, j = 0, -1, i
            while j < n:
                s = table[s][text[j]]
                if s == dead:
                    break
                j += 1
                if accepts[s]:
                    end = j
            if end < 0:
                continue
            free = end
            out.append((i, end))
        return out

    def long_enough(self, text: bytes, start: int, k: int, end: int) -> bool:
        """Short matches are consumed, then dropped."""
        _, _, _, least, value = self.rules[k]
        return end - start >= least and (not value or self.value_size(text, start, end) >= value)

    @staticmethod
    def value_size(text: bytes, start: int, end: int) -> int:
        """Length of the value of an assignment: what follows the first separator, blanks and an opening quote."""
        at = min(p for p in (text.find(b, start, end) for b in (b":", b"=")) if p >= 0) + 1
        while text[at] == 32:
            at += 1
        return end - at - (text[at] in b"\"'")

    def scan(self, texts: list[bytes]) -> list[list[tuple[int, int, int]]]:
        """Spans (start, rule, end) of each text in code points, by start, then rule."""
        out = []
        for text, kinds in zip(texts, self.occurring(texts).tolist(), strict=True):
            found = []
            if kinds:
                found, again = self.tagged.spans(text)
                found += [(s, k, e) for k in again if kinds >> k & 1 for s, e in self.spans(text, k)]
                found = [x for x in found if self.long_enough(text, *x)]
            if found and not text.isascii():
                code = np.concatenate([[0], np.cumsum((np.frombuffer(text, np.uint8) & 0xC0) != 0x80)])
                found = [(int(code[s]), k, int(code[e])) for s, k, e in found]
            out.append(sorted(found))
        return out


def _join(spans, rules) -> str:
    return ",".join(f"{rules[k][0]}:{s}:{e}" for s, k, e in spans)


def _scan(rules):
    def run(batches):
        cache = worker_cache()
        scanner = cache.get(("scanner", rules)) or cache.setdefault(("scanner", rules), Scanner(rules))
        for batch in batches:
            found = [spans for _, part in column_stretches(batch.column("body"), 4 << 20) for spans in scanner.scan(part)]
            base = [[x for x in spans if rules[x[1]][0] in BASE] for spans in found]
            keep = [n for n in batch.schema.names if n != "body"]
            counts = [pa.array([sum(rules[k][0] == kind for _, k, _ in spans) for spans in found], pa.int64()) for kind in BASE]
            digest = pa.array([hashlib.sha256(_join(b, rules).encode()).hexdigest() for b in base], pa.string())
            yield pa.RecordBatch.from_arrays([*(batch.column(n) for n in keep), *counts, digest, pa.array([_join(s, rules) for s in found], pa.string())], [*keep, *(f"n_{k}" for k in BASE), "base_sha256", "spans"])

    return run


def scan_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rules=RULES) -> DataFrame:
    """One row per document: id, n_assign, n_access, n_hex, base_sha256, spans.

    ``spans`` lists kind:start:end by start, then by the order of the rules, in code points with exclusive ends.
    Every text is scanned whole in one pass of the combined automaton, without
    a shuffle; a text with a match is read once more, by all rules together, for the spans. Null and empty texts have no spans; repeated rows and null ids are returned as they are.
    Non-ASCII characters belong to no rule's classes.
    """
    small_batches(docs.sparkSession)
    kind = docs.schema[id_col].dataType.simpleString()
    rows = docs.select(F.col(id_col).alias("id"), as_bytes(text_col).alias("body"))
    out = rows.mapInArrow(tidy(_scan(tuple(rules))), f"id {kind}, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")
    return out.withColumnRenamed("id", id_col)
