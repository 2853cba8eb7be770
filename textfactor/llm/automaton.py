"""Byte automata: a small regex dialect, subset construction, minimisation.

Dialect: literals, escapes (``\\xHH``, ``\\n``, ``\\t``, ``\\d``, ``\\w``, escaped signs), ``.``, classes, groups
``(...)``/``(?:...)``, ``(?i:...)`` for A-Z in either case, ``|`` and ``? * + {m} {m,} {m,n}``. Patterns work on UTF-8 bytes
and must not match the empty string.
"""

from __future__ import annotations

import numpy as np

_ESCAPES = {"n": {10}, "t": {9}, "r": {13}, "d": set(range(48, 58)), "w": {*range(48, 58), *range(65, 91), *range(97, 123), 95}}


class Nfa:
    """``edges[state]`` lists (set of bytes or None, target); one start and one accepting state."""

    def __init__(self, pattern: str):
        self.edges: list[list[tuple[frozenset | None, int]]] = []
        self._p, self._i = pattern, 0
        self.start, self.accept = self._alternatives(False)
        if self._i != len(pattern):
            raise ValueError(f"can't read {pattern!r} at {self._i}")
        if self.accept in self.closure({self.start}):
            raise ValueError(f"{pattern!r} matches the empty string")

    def _new(self) -> int:
        self.edges.append([])
        return len(self.edges) - 1

    def _alternatives(self, fold: bool) -> tuple[int, int]:
        parts = [self._sequence(fold)]
        while self._peek() == "|":
            self._i += 1
            parts.append(self._sequence(fold))
        if len(parts) == 1:
            return parts[0]
        a, z = self._new(), self._new()
        for s, e in parts:
            self.edges[a].append((None, s))
            self.edges[e].append((None, z))
        return a, z

    def _peek(self) -> str:
        return self._p[self._i] if self._i < len(self._p) else ""

    def _sequence(self, fold: bool) -> tuple[int, int]:
        a = z = self._new()
        while self._peek() not in ("", "|", ")"):
            mark = self._i
            s, e = self._atom(fold)
            low, high = self._repeat()
            if (low, high) != (1, 1):
                after = self._i
                chain = []
                for k in range(max(low, high or low, 1)):
                    if k:
                        self._i = mark
                        s, e = self._atom(fold)
                    chain.append((s, e))
                self._i = after
                join = self._new()
                first = chain[0][0]
                for k, (s, e) in enumerate(chain):
                    if k:
                        self.edges[chain[k - 1][1]].append((None, s))
                    if k + 1 >= low:
                        self.edges[e].append((None, join))
                if low == 0:
                    self.edges[first].append((None, join))
                if high is None:
                    self.edges[chain[-1][1]].append((None, chain[-1][0]))
                s, e = first, join
            self.edges[z].append((None, s))
            z = e
        return a, z

    def _repeat(self) -> tuple[int, int | None]:
        c = self._peek()
        if c and c in "?*+":
            self._i += 1
            return {"?": (0, 1), "*": (0, None), "+": (1, None)}[c]
        if c == "{":
            end = self._p.index("}", self._i)
            low, comma, high = self._p[self._i + 1 : end].partition(",")
            self._i = end + 1
            return int(low), (int(high) if high else None) if comma else int(low)
        return 1, 1

    def _atom(self, fold: bool) -> tuple[int, int]:
        c = self._peek()
        if c == "(":
            self._i += 1
            if self._p.startswith("?i:", self._i):
                self._i, fold = self._i + 3, True
            elif self._p.startswith("?:", self._i):
                self._i += 2
            found = self._alternatives(fold)
            if self._peek() != ")":
                raise ValueError(f"unclosed group in {self._p!r}")
            self._i += 1
            return found
        if c == "[":
            return self._step(self._class(), fold)
        if c == ".":
            self._i += 1
            return self._step(set(range(256)) - {10}, fold)
        if c == "\\":
            return self._step(self._escaped(), fold)
        self._i += 1
        s = e = self._new()
        for b in c.encode():
            _, nxt = self._step({b}, fold, e)
            e = nxt
        return s, e

    def _step(self, chars: set[int], fold: bool, s: int | None = None) -> tuple[int, int]:
        if fold:
            chars = chars | {b ^ 32 for b in chars if 65 <= b & 223 <= 90}
        s, e = self._new() if s is None else s, self._new()
        self.edges[s].append((frozenset(chars), e))
        return s, e

    def _escaped(self) -> set[int]:
        c = self._p[self._i + 1]
        if c == "x":
            self._i += 4
            return {int(self._p[self._i - 2 : self._i], 16)}
        self._i += 2
        return set(_ESCAPES.get(c, {ord(c)}))

    def _class(self) -> set[int]:
        self._i += 1
        negate = self._peek() == "^"
        self._i += negate
        out: set[int] = set()
        while self._peek() != "]":
            if self._peek() == "\\":
                got = self._escaped()
            else:
                got = {ord(self._peek())}
                self._i += 1
            if self._peek() == "-" and self._p[self._i + 1] != "]" and len(got) == 1:
                self._i += 1
                if self._peek() == "\\":
                    top = max(self._escaped())
                else:
                    top = ord(self._peek())
                    self._i += 1
                got = set(range(min(got), top + 1))
            out |= got
        self._i += 1
        return set(range(256)) - out if negate else out

    def closure(self, states) -> frozenset:
        seen, todo = set(states), list(states)
        while todo:
            for chars, t in self.edges[todo.pop()]:
                if chars is None and t not in seen:
                    seen.add(t)
                    todo.append(t)
        return frozenset(seen)

    def reversed(self) -> "Nfa":
        r = object.__new__(Nfa)
        r.edges = [[] for _ in self.edges]
        for s, es in enumerate(self.edges):
            for chars, t in es:
                r.edges[t].append((chars, s))
        r.start, r.accept = self.accept, self.start
        return r


class LazyDfa:
    """Deterministic states of one automaton, made when first met. ``all_alive`` starts in every state."""

    def __init__(self, nfa: Nfa, all_alive: bool = False):
        self.nfa, self.ids, self.sets, self.next = nfa, {}, [], []
        self.start = self._id(frozenset(range(len(nfa.edges))) if all_alive else nfa.closure({nfa.start}))

    def _id(self, states: frozenset) -> int:
        if states not in self.ids:
            self.ids[states] = len(self.sets)
            self.sets.append((states, self.nfa.accept in states))
            self.next.append({})
        return self.ids[states]

    def step(self, s: int, b: int) -> int:
        t = self.next[s].get(b)
        if t is None:
            t = self.next[s][b] = self._id(
                self.nfa.closure({t for q in self.sets[s][0] for chars, t in self.nfa.edges[q] if chars is not None and b in chars})
            )
        return t

    def accepts(self, s: int) -> bool:
        return self.sets[s][1]

    def dead(self, s: int) -> bool:
        return not self.sets[s][0]


def combined(nfas: list[Nfa], limit: int = 50_000) -> tuple[np.ndarray, np.ndarray, int]:
    """One minimal automaton for all rules, unanchored: after every byte it tells for which rules the shortest match from some
    start ends there.

    Returns the transition array (states x 256), the bit mask of rules per state, and the start state. States are
    numbered so that those with a mask come last.
    """
    base = np.cumsum([0, *(len(n.edges) for n in nfas)])
    moves: list[list[tuple[frozenset, int]]] = []
    close: list[frozenset] = []
    for n, o in zip(nfas, base):
        moves += [[(c, t + o) for c, t in es if c is not None] for es in n.edges]
        reached = [n.closure({s}) for s in range(len(n.edges))]
        # what has come to an end goes no further: the earliest end of every start is enough to report it
        close += [frozenset({n.accept + o} if n.accept in c else {q + o for q in c}) for c in reached]
    marks = np.zeros((256, 0), bool)
    kinds = sorted({c for es in moves for c, _ in es}, key=sorted)
    if kinds:
        marks = np.array([[b in c for c in kinds] for b in range(256)])
    _, byte_class = np.unique(marks, axis=0, return_inverse=True)
    byte_class = byte_class.ravel()
    sample = [int(np.flatnonzero(byte_class == k)[0]) for k in range(byte_class.max() + 1)]
    begin = frozenset().union(*(close[n.start + o] for n, o in zip(nfas, base)))
    begin = frozenset(q for q in begin if moves[q])
    accept = {n.accept + o: 1 << i for i, (n, o) in enumerate(zip(nfas, base))}
    ids, todo, table, masks = {(begin, 0): 0}, [(begin, 0)], [], [0]
    k = 0
    while k < len(todo):
        states, _ = todo[k]
        k += 1
        row = []
        for b in sample:
            out = set(begin)
            for q in states:
                for c, t in moves[q]:
                    if b in c:
                        out |= close[t]
            mask = 0
            for q in out:
                mask |= accept.get(q, 0)
            key = (frozenset(q for q in out if moves[q]), mask)
            if key not in ids:
                if len(ids) >= limit:
                    raise ValueError(f"the rules need more than {limit} states")
                ids[key] = len(todo)
                todo.append(key)
                masks.append(mask)
            row.append(ids[key])
        table.append(row)
    t, m = np.array(table), np.array(masks, dtype=np.int64)
    group = np.unique(m, return_inverse=True)[1].ravel()
    while True:
        finer = np.unique(np.column_stack([group, group[t]]), axis=0, return_inverse=True)[1].ravel()
        if finer.max() == group.max():
            break
        group = finer
    first = np.array([np.flatnonzero(group == g)[0] for g in range(group.max() + 1)])
    order = np.argsort(m[first] != 0, kind="stable")
    rank = np.empty(len(order), np.int64)
    rank[order] = np.arange(len(order))
    small = rank[group[t[first[order]]]]
    return small[:, byte_class].astype(np.int32), m[first[order]], int(rank[group[0]])
