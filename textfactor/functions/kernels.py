"""NumPy kernels over a batch of texts laid end to end.

Positions are 0-based and global within the batch; text ``k`` has the symbols ``first[k]:first[k + 1]``. Every text is thought to
be closed by a sentinel smaller than all symbols, at position ``first[k + 1]``, which is not stored. All kernels treat texts as
independent, so a batch of many small texts costs as few NumPy calls as one large one.
"""

from __future__ import annotations

import heapq
from bisect import bisect_left, bisect_right

import numpy as np


def as_batch(texts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    first = np.zeros(len(texts) + 1, np.int64)
    np.cumsum([len(x) for x in texts], out=first[1:])
    return (np.concatenate(texts) if texts else np.zeros(0, np.int64)), first


def symbols_of(text: str, unit: str = "codepoint") -> np.ndarray:
    if unit == "byte":
        return np.frombuffer(text.encode("utf-8"), np.uint8).astype(np.int64)
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)


#: Pairs of positions that are compared at a time.
PAIRS = 1 << 18


class _Some:
    """Ranks of some positions: a bit for every position, how many are set before each word, and the ranks in order."""

    def __init__(self, pos: np.ndarray, rank: np.ndarray):
        has = np.zeros(-(-len(rank) // 64) * 64, bool)
        has[pos] = True
        self.words = np.packbits(has, bitorder="little").view(np.uint64)
        count = np.bitwise_count(self.words).astype(np.int32)
        self.before = np.cumsum(count, dtype=np.int32) - count
        self.ranks = rank[pos]

    def __getitem__(self, x: np.ndarray) -> np.ndarray:
        low = self.words[x >> 6] & ((np.uint64(1) << (x & 63).astype(np.uint64)) - np.uint64(1))
        return self.ranks[self.before[x >> 6] + np.bitwise_count(low)]


class Suffixes:
    """Suffix order of all texts of a batch by prefix doubling on packed symbols.

    ``order``: positions sorted by (text, suffix). ``levels[k]`` has a rank for the positions whose rank was not unique before round k,
    which is equal for two of them exactly if their next ``width * 2**k`` symbols are: all ranks, or a ``_Some`` if these are fewer
    than an eighth; ``last``: the last level that has a position. Positions whose rank is unique leave the working set. Bounds and text
    numbers take 4 bytes a symbol.
    """

    def __init__(self, t: np.ndarray, first: np.ndarray):
        n = len(t)
        self.t, self.first, self.n = t, first, n
        small = np.int32 if n < 1 << 30 else np.int64
        self.text = np.repeat(np.arange(len(first) - 1, dtype=small), np.diff(first))
        self.end = first[1:].astype(small)[self.text] if n else np.zeros(0, small)
        self.rank = np.zeros(0, np.int64)
        if not n:
            self.order, self.levels, self.width = np.zeros(0, np.int64), [], 1
            return
        kinds = np.unique(np.concatenate([np.unique(t[i : i + PAIRS]) for i in range(0, n, PAIRS)]))
        sym = np.concatenate([np.searchsorted(kinds, t[i : i + PAIRS]).astype(np.int32) for i in range(0, n, PAIRS)]) + 1
        bits = max(1, int(len(kinds)).bit_length())
        spare = 63 - int(len(first)).bit_length()
        self.width = width = max(1, spare // bits)
        key = self.text.astype(np.int64)
        for k in range(width):
            key <<= bits
            if k < n:
                key[: n - k] += np.where(np.arange(k, n) < self.end[: n - k], sym[k:], 0)
        del sym
        order = np.argsort(key)
        key = key[order]
        fresh = np.ones(n, bool)
        fresh[1:] = key[1:] != key[:-1]
        del key
        rank = np.empty(n, np.int32)
        rank[order] = np.maximum.accumulate(np.where(fresh, np.arange(n, dtype=np.int32), 0))
        self.levels, self.last = [rank.copy()], np.zeros(n, np.uint8)
        h = width
        while True:
            alone = fresh & np.append(fresh[1:], True)
            at = np.flatnonzero(~alone)
            if not len(at):
                break
            pos = order[at]
            ahead = pos + h
            second = np.where(ahead < self.end[pos], rank[np.minimum(ahead, n - 1)] + 1, 0).astype(np.int64)
            key = rank[pos].astype(np.int64) * (n + 1) + second
            by = np.argsort(key)
            pos, key = pos[by], key[by]
            order[at] = pos
            new = np.ones(len(at), bool)
            new[1:] = key[1:] != key[:-1]
            fresh[at] = new
            rank[pos] = np.maximum.accumulate(np.where(new, at, 0))
            self.last[pos] = len(self.levels)
            if len(at) < n // 8:
                self.levels.append(_Some(np.sort(pos), rank))
            else:
                self.levels.append(rank.copy())
            h *= 2
        self.order, self.rank = order, rank

    def common(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Length of the common prefix of the suffixes at i and j, which belong to one text (or start at its end)."""
        i, j = np.asarray(i), np.asarray(j)
        if len(i) > PAIRS:
            out = np.empty(len(i), np.int64)
            for a in range(0, len(i), PAIRS):
                out[a : a + PAIRS] = self.common(i[a : a + PAIRS], j[a : a + PAIRS])
            return out
        out = np.zeros(len(i), np.int64)
        live = np.flatnonzero((i < self.n) & (j < self.n))
        live = live[(self.text[i[live]] == self.text[j[live]]) & (i[live] != j[live])]
        end = self.end[i[live]]
        a, b = i[live].copy(), j[live].copy()
        for k in range(len(self.levels) - 1, -1, -1):
            step, level = self.width << k, self.levels[k]
            at = np.flatnonzero((a < end) & (b < end))
            if k:  # others have ranks of their own
                at = at[self.last[a[at]] >= k]
                at = at[self.last[b[at]] >= k]
            at = at[level[a[at]] == level[b[at]]]
            a[at] += step
            b[at] += step
        open_ = np.ones(len(live), bool)
        for _ in range(self.width - 1):
            open_ &= (a < end) & (b < end)
            at = np.flatnonzero(open_)
            if not len(at):
                break
            same = self.t[a[at]] == self.t[b[at]]
            open_[at[~same]] = False
            a[at[same]] += 1
            b[at[same]] += 1
        out[live] = a - i[live]
        return out

    def phi(self) -> np.ndarray:
        """The suffix before each one in suffix order; the sentinel's position for the first of a text."""
        out = np.empty(self.n, np.int64)
        if self.n:
            before = np.empty(self.n, np.int64)
            before[1:] = self.order[:-1]
            opens = self.first[:-1][np.diff(self.first) > 0]
            before[opens] = self.end[self.order[opens]]
            out[self.order] = before
        return out

    def plcp(self, phi: np.ndarray) -> np.ndarray:
        """Irreducible values by comparison, all others from the last reach, which never decreases."""
        n = self.n
        if not n:
            return np.zeros(0, np.int64)
        i = np.arange(n)
        begin = self.first[self.text]
        own = (i == begin) | (phi == begin) | (phi >= self.end)
        rest = np.flatnonzero(~own)
        own[rest] = self.t[rest - 1] != self.t[phi[rest] - 1]
        at = np.flatnonzero(own)
        reach = np.zeros(n, np.int64)
        reach[at] = at + self.common(at, phi[at])
        return np.maximum.accumulate(np.maximum(reach, begin)) - i if n else reach

    def previous_factors(self) -> tuple[np.ndarray, np.ndarray]:
        """For every position the longest factor that occurs earlier (``lpf``) and its smallest nearest source (``-1``: none)."""
        n, order = self.n, self.order
        if not n:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        cand = []
        for direction in (1, -1):
            o = order[::direction]
            near = _nearest_smaller(o, self.text[o])
            src = np.full(n, -1, self.end.dtype)
            has = near >= 0
            src[o[has]] = o[near[has]]
            del near, has
            length = np.zeros(n, self.end.dtype)
            for a in range(0, n, PAIRS):
                at = a + np.flatnonzero(src[a : a + PAIRS] >= 0)
                length[at] = self.common(at, src[at].astype(np.int64))
            cand.append((src, length))
        (s1, l1), (s2, l2) = cand
        better = (l2 > l1) | ((l2 == l1) & (s2 >= 0) & ((s1 < 0) | (s2 < s1)))
        lpf = np.maximum(l1, l2).astype(np.int64)
        return lpf, np.where(lpf > 0, np.where(better, s2, s1), -1).astype(np.int64)


def _nearest_smaller(v: np.ndarray, group: np.ndarray) -> np.ndarray:
    """Index of the nearest earlier element of the same group with a smaller value, or -1: pointers that jump over larger ones."""
    small = np.int32 if len(v) < 1 << 30 else np.int64
    p = np.arange(-1, len(v) - 1, dtype=small)
    todo = np.arange(len(v), dtype=small)
    while len(todo):
        q = p[todo]
        ok = q >= 0
        todo, q = todo[ok], q[ok]
        alien = group[q] != group[todo]
        p[todo[alien]] = -1
        more = ~alien & (v[q] > v[todo])
        todo, q = todo[more], q[more]
        p[todo] = p[q]
    return p


def reach_steps(plcp: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Positions where position + value grows (each text's first position if its value is positive)."""
    n = len(plcp)
    if not n:
        return np.zeros(0, np.int64)
    reach = np.arange(n) + plcp
    before = np.empty(n, np.int64)
    before[0] = 0
    before[1:] = reach[:-1]
    opens = first[:-1][np.diff(first) > 0]
    before[opens] = opens
    return np.flatnonzero(reach > before)


def interesting_peaks(pos: np.ndarray, reach: np.ndarray) -> np.ndarray:
    """Which candidates no earlier one of at least their value reaches over; candidates ascend and so do their reaches."""
    value = reach - pos
    p = np.arange(len(pos)) - 1
    out = np.zeros(len(pos), bool)
    todo = np.arange(len(pos))
    while len(todo):
        q = p[todo]
        free = (q < 0) | (reach[q] <= pos[todo])
        out[todo[free]] = True
        todo, q = todo[~free], q[~free]
        low = value[q] < value[todo]
        todo, q = todo[low], q[low]
        p[todo] = p[q]
    return out


def maximal_peaks(pos: np.ndarray, reach: np.ndarray) -> np.ndarray:
    """Indexes of the interesting candidates after which the next interesting one starts behind their reach."""
    at = np.flatnonzero(interesting_peaks(pos, reach))
    nxt = np.append(pos[at][1:], np.iinfo(np.int64).max)
    return at[nxt >= reach[at]]


def rounds_factors(plcp: np.ndarray, first: np.ndarray, min_len: int, trace: list | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Leftmost-longest factors (start, length) of all texts, see ``rounds_on_steps``."""
    pos = reach_steps(plcp, first)
    return rounds_on_steps(pos, pos + plcp[pos], min_len, trace)


def rounds_on_steps(step_pos: np.ndarray, step_reach: np.ndarray, min_len: int, trace: list | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Leftmost-longest factors (start, length) in parallel rounds, from the reach steps alone.

    All maximal peaks of a round are factors. They clip the reach of what stands before them, remove what they cover, and
    the position behind each one becomes a candidate, with the reach of the last step up to it.
    """
    pos, reach = step_pos, step_reach
    starts, lengths = np.zeros(0, np.int64), np.zeros(0, np.int64)
    far = np.iinfo(np.int64).max
    while True:
        keep = reach - pos >= min_len
        pos, reach = pos[keep], reach[keep]
        if len(pos):
            grow = np.ones(len(pos), bool)
            grow[1:] = reach[1:] > reach[:-1]
            pos, reach = pos[grow], reach[grow]
        if not len(pos):
            break
        if trace is not None:
            trace.append(len(pos))
        top = maximal_peaks(pos, reach)
        d, e = pos[top], reach[top]
        order = np.argsort(np.concatenate([starts, d]), kind="stable")
        starts = np.concatenate([starts, d])[order]
        lengths = np.concatenate([lengths, e - d])[order]
        k = np.searchsorted(d, pos, "right") - 1
        inside = (k >= 0) & (pos < e[np.maximum(k, 0)])
        pos, reach = pos[~inside], reach[~inside]
        limit = np.append(starts, far)
        reach = np.minimum(reach, limit[np.searchsorted(starts, pos)])
        own = step_reach[np.searchsorted(step_pos, e, "right") - 1]
        cut = np.minimum(own, limit[np.searchsorted(starts, e)])
        more = cut - e >= min_len
        pos, at = np.unique(np.concatenate([pos, e[more]]), return_index=True)
        reach = np.concatenate([reach, cut[more]])[at]
    return starts, lengths


def definition_factors(plcp: np.ndarray, min_len: int, steps: list | None = None) -> list[tuple[int, int]]:
    """The scheme as it is defined, for one text: replace the leftmost largest value, lower what reaches into it, clear it."""
    v = plcp.copy()
    out = []
    while len(v):
        d = int(v.argmax())
        size = int(v[d])
        if size < min_len:
            break
        out.append((d, size))
        a = max(0, d - size)
        v[a:d] = np.minimum(v[a:d], d - np.arange(a, d))
        v[d : d + size] = 0
        if steps is not None:
            steps.append(v.copy())
    return out


def heap_factors(plcp: np.ndarray, min_len: int, tie: str = "leftmost") -> list[tuple[int, int]]:
    """Longest first by a heap with lazy re-insertion; ``tie``: which of equal lengths comes first."""
    n = len(plcp)
    rank = {
        "leftmost": lambda i: i,
        "rightmost": lambda i: -i,
        "hash": lambda i: (i * 0x9E3779B1 + 12345) % 0x7FFFFFFF,
        "stable": lambda i: i % 64 * n + i,
    }[tie]
    heap = [(-int(p), rank(i), i) for i, p in enumerate(plcp.tolist()) if p >= min_len]
    heapq.heapify(heap)
    taken = np.zeros(n + 1, bool)
    limit: list[int] = []
    out = []
    import bisect

    while heap:
        size, r, i = heapq.heappop(heap)
        size = -size
        if taken[i]:
            continue
        k = bisect.bisect_left(limit, i)
        room = limit[k] - i if k < len(limit) else n - i
        if room < size:
            if room >= min_len:
                heapq.heappush(heap, (-room, r, i))
            continue
        out.append((i, size))
        taken[i : i + size] = True
        bisect.insort(limit, i)
    return out


def split_factors(plcp: np.ndarray, first: np.ndarray, min_len: int) -> list[tuple[int, int]]:
    """By segments: the leftmost highest candidate of a segment is a factor, the parts on its two sides are segments again."""
    steps = reach_steps(plcp, first)
    return _split(plcp.tolist(), steps.tolist(), (steps + plcp[steps]).tolist(), [(0, len(plcp))], min_len)


def _split(v: list[int], steps: list[int], reach: list[int], todo: list[tuple[int, int]], min_len: int) -> list[tuple[int, int]]:
    out = []
    while todo:
        low, high = todo.pop()
        if high - low < min_len:
            continue
        a, b = bisect_left(steps, low), bisect_left(steps, high)
        best, at = min(v[low], high - low), low
        for k in range(a, b):
            w = min(reach[k], high) - steps[k]
            if w > best:
                best, at = w, steps[k]
        if best >= min_len:
            out.append((at, best))
            todo.append((low, at))
            todo.append((at + best, high))
    return out


def cut_factors(plcp: np.ndarray, first: np.ndarray, min_len: int) -> list[tuple[int, int]]:
    """One parallel round of all maximal peaks, which cuts the text into short segments, then the segments by splitting."""
    steps = reach_steps(plcp, first)
    reach = steps + plcp[steps]
    tall = reach - steps >= min_len
    pos, high = steps[tall], reach[tall]
    if not len(pos):
        return []
    top = maximal_peaks(pos, high)
    d, e = pos[top], high[top]
    segments = list(zip(np.append(0, e).tolist(), np.append(d, len(plcp)).tolist()))
    return sorted(list(zip(d.tolist(), (e - d).tolist())) + _split(plcp.tolist(), steps.tolist(), reach.tolist(), segments, min_len))


def preliminary_factors(plcp: np.ndarray, min_len: int) -> list[tuple[int, int]]:
    """By recursion: the leftmost maximal peak of a segment is a factor, the parts on its two sides are segments again."""
    out, todo = [], [(0, len(plcp))]
    while todo:
        low, high = todo.pop()
        if high - low < min_len:
            continue
        reach = np.minimum(np.arange(low, high) + plcp[low:high], high)
        tall = np.flatnonzero(reach - np.arange(low, high) >= min_len)
        grow = np.ones(len(tall), bool)
        grow[1:] = reach[tall[1:]] > np.maximum.accumulate(reach[tall])[:-1]
        pos = tall[grow] + low
        if not len(pos):
            continue
        first = maximal_peaks(pos, reach[pos - low])[0]
        d, e = int(pos[first]), int(reach[pos[first] - low])
        out.append((d, e - d))
        todo += [(low, d), (e, high)]
    return sorted(out)


def scan_factors(plcp: np.ndarray, min_len: int, stats: dict | None = None, check: bool = False) -> list[tuple[int, int]]:
    """One left-to-right pass that keeps interesting peaks only.

    A stack holds (position, value) of all peaks that still reach over the current position, for the interest test; the list
    holds the interesting ones that wait, whose values ascend. When the scan leaves the reach of the last one it is maximal and
    a factor. Then the list is settled from its right end: of the peaks that the new factor clips only the first can stay
    interesting; the rightmost maximal peak becomes a factor, which clips in turn, and the one position that may become a peak
    is the one behind it. ``check`` asserts the two facts this rests on, against all values.
    """
    n = len(plcp)
    v = plcp.tolist()
    out: list[tuple[int, int]] = []
    waiting: list[tuple[int, int]] = []
    stack: list[tuple[int, int]] = []
    longest = 0
    i, fresh = 0, True

    def settle(high: int) -> None:
        """Factors of the waiting peaks before ``high``, where a factor starts."""
        while waiting:
            clipped = len(waiting)
            while clipped and waiting[clipped - 1][0] + waiting[clipped - 1][1] >= high:
                clipped -= 1
            del waiting[clipped + 1 :]
            j, size = waiting.pop()
            size = min(size, high - j)
            if waiting and waiting[-1][1] >= size:
                j, size = waiting.pop()
            end = j + size
            if size >= min_len:
                out.append((j, size))
                if high - end >= min_len and v[end] >= min_len:
                    out.append((end, min(v[end], high - end)))
                high = j

    def ascending() -> None:
        values = [w for _, w in waiting]
        assert all(x < y for x, y in zip(values, values[1:])), "values of the waiting peaks ascend"

    while i <= n:
        # the waiting peak that nothing interesting follows within its reach
        if waiting and (i == n or i >= waiting[-1][0] + waiting[-1][1]):
            if check:
                ascending()
            p, size = waiting.pop()
            out.append((p, size))
            settle(p)
            stack.clear()
            i = p + size
            fresh = True
            continue
        if i == n:
            break
        value = v[i]
        if value >= min_len and (fresh or v[i - 1] < value):
            while stack and (stack[-1][0] + stack[-1][1] <= i):
                stack.pop()
            if not any(q + w > i and w >= value for q, w in stack):
                waiting.append((i, value))
                longest = max(longest, len(waiting))
            while stack and stack[-1][1] <= value:
                stack.pop()
            stack.append((i, value))
        fresh = False
        i += 1
    if stats is not None:
        stats["longest_list"] = longest
    out.sort()
    if check:
        _no_new_peaks(plcp, out, min_len)
    return out


def _peaks_of(v: np.ndarray, min_len: int) -> set[int]:
    return set(np.flatnonzero((v >= min_len) & (np.concatenate([[True], v[1:] > v[:-1]]) if len(v) else v > 0)).tolist())


def _no_new_peaks(plcp: np.ndarray, factors: list[tuple[int, int]], min_len: int) -> None:
    """Replacing a factor makes no position a peak but the one behind it."""
    v = plcp.copy()
    for d, size in sorted(factors, key=lambda f: (-f[1], f[0])):
        before = _peaks_of(v, min_len)
        a = max(0, d - int(plcp.max()))
        v[a:d] = np.minimum(v[a:d], d - np.arange(a, d))
        v[d : d + size] = 0
        assert _peaks_of(v, min_len) <= before | {d + size}, "a new peak"


def greedy_parse(step: np.ndarray, first: np.ndarray, block: int = 256) -> np.ndarray:
    """Start positions of the phrases when each phrase at i has ``max(1, step[i])`` symbols and none leaves its text.

    Every position's first phrase start behind its block is found by doubling; the path then takes a block a step, and the
    phrases inside all blocks are followed side by side.
    """
    n = len(step)
    nxt = np.arange(n) + np.maximum(1, step)
    border = np.minimum((np.arange(n) // block + 1) * block, n)
    leave = nxt.copy()
    todo = np.flatnonzero(leave < border)
    while len(todo):
        leave[todo] = leave[leave[todo]]
        todo = todo[leave[todo] < border[todo]]
    at, i = [], 0
    while i < n:
        at.append(i)
        i = int(leave[i])
    now, out = np.array(at, np.int64), []
    while len(now):
        out.append(now)
        ahead = nxt[now]
        now = ahead[ahead < border[now]]
    return np.sort(np.concatenate(out)) if out else np.zeros(0, np.int64)


def window_parse(t: np.ndarray, window: int, min_len: int) -> list[tuple[int, int, int]]:
    """(start, source, length), literals with source -1: sources begin at most ``window`` symbols back."""
    from collections import defaultdict, deque

    seen: dict[bytes, deque] = defaultdict(deque)
    data = t.astype(np.int32).tobytes()
    n, i, out, w = len(t), 0, [], max(2, min_len)
    sig = lambda k: data[4 * k : 4 * (k + w)]
    while i < n:
        best, src = 0, -1
        if i + w <= n:
            places = seen[sig(i)]
            while places and i - places[0] > window:
                places.popleft()
            for j in places:  # of equal lengths the first counts
                if data[4 * j : 4 * (j + best + 1)] == data[4 * i : 4 * (i + best + 1)]:
                    best, src = _extend(data, j, i, max(w, best + 1), n - i), j
                    if i + best == n:
                        break
        size = best if best >= min_len else 1
        out.append((i, src if best >= min_len else -1, size))
        for k in range(i, i + size):
            if k + w <= n:
                seen[sig(k)].append(k)
        i += size
    return out


def end_aligned_parse(t: np.ndarray, min_len: int, gram: int = 0) -> list[tuple[int, int, int]]:
    """Unidirectional phrases whose source ends where an earlier phrase ends; the longest one, then the first.

    From a phrase's start its neighbours in suffix order are passed, on both sides, as long as they share the best length so far; each
    earlier one is cut back to the last phrase end in reach. ``gram`` belonged to an earlier form and has no effect.
    """
    return next(end_aligned_parses(t, np.array([0, len(t)]), min_len))


def end_aligned_parses(t: np.ndarray, first: np.ndarray, min_len: int):
    """``end_aligned_parse`` of each text of a batch, whose suffixes are sorted together."""
    s = Suffixes(t, first)
    lcp = s.plcp(s.phi())[s.order] if s.n else s.order
    for a, b in zip(first[:-1].tolist(), first[1:].tolist()):
        yield _end_aligned((s.order[a:b] - a).tolist(), (s.rank[a:b] - a).tolist(), [*lcp[a:b].tolist(), 0], min_len)


def _end_aligned(order: list[int], rank: list[int], lcp: list[int], min_len: int) -> list[tuple[int, int, int]]:
    """``lcp``: in suffix order, with the suffix before; 0 for the first and behind the last."""
    n, i, out = len(order), 0, []
    last = [0] * (n + 1)  # the last phrase end up to each parsed position
    while i < n:
        best, src = min_len - 1, -1
        r, size = rank[i], n
        while True:
            size = min(size, lcp[r])
            if size < best or size < min_len:
                break
            r -= 1
            j = order[r]
            if j < i:
                k = last[j + size if j + size < i else i] - j
                if k > best or (k == best and j < src):
                    best, src = k, j
        r, size = rank[i] + 1, n
        while True:
            size = min(size, lcp[r])
            if size < best or size < min_len:
                break
            j = order[r]
            if j < i:
                k = last[j + size if j + size < i else i] - j
                if k > best or (k == best and j < src):
                    best, src = k, j
            r += 1
        size = best if src >= 0 else 1
        out.append((i, src, size))
        last[i + 1 : i + size] = [i] * (size - 1)
        i += size
        last[i] = i
    return out


def _extend(data: bytes, a: int, b: int, k: int, top: int) -> int:
    """The longest common prefix of the symbols at ``a`` and ``b`` up to ``top``; the first ``k`` are known to be equal."""
    step = 16
    while k < top:
        step = min(step, top - k)
        if data[4 * (a + k) : 4 * (a + k + step)] == data[4 * (b + k) : 4 * (b + k + step)]:
            k += step
            step *= 2
        elif step == 1:
            break
        else:
            step //= 2
            top = min(top, k + 2 * step)
    return k


def _against(piece: np.ndarray, block: np.ndarray, count: int, starts: int) -> tuple[np.ndarray, np.ndarray]:
    """For the first ``count`` positions of ``block``: their longest match with one of the first ``starts`` positions of ``piece``."""
    kinds = np.unique(np.concatenate([piece, block]), return_inverse=True)[1].astype(np.int64) + 1
    t = np.concatenate([kinds[: len(piece)], [0], kinds[len(piece) :]])
    s = Suffixes(t, np.array([0, len(t)]))
    slot = np.arange(len(t))
    ours = s.order < starts
    shift = len(piece) + 1
    size, src = np.zeros(count, np.int64), np.full(count, -1, np.int64)
    for direction in (1, -1):
        o, mine = s.order[::direction], ours[::direction]
        near = np.maximum.accumulate(np.where(mine, slot, -1))
        at = np.flatnonzero((o >= shift) & (o < shift + count) & (near >= 0))
        i, j = o[at], o[near[at]]
        got = np.minimum(s.common(i, j), len(piece) - j)
        better = (got > size[i - shift]) | ((got == size[i - shift]) & (got > 0) & (j < src[i - shift]))
        size[i[better] - shift], src[i[better] - shift] = got[better], j[better]
    return size, src


def scan_parse(t: np.ndarray, block: int, min_len: int) -> list[tuple[int, int, int]]:
    """Unidirectional greedy parse by blocks: the longest earlier match of all positions of a block is found by passing all the
    text before it, a block at a time, so no array is longer than a few blocks; the passes make it quadratic in the text.

    Blocks are read with ``ahead`` symbols behind them. A phrase that long may go on, so its block is passed again with twice as many.
    """
    n, i, out = len(t), 0, []
    for a in range(0, n, block):
        b, ahead = min(a + block, n), block
        while i < b:
            mine = t[a : min(b + ahead, n)]
            best, src = (x[: b - a].copy() for x in Suffixes(mine, np.array([0, len(mine)])).previous_factors())
            src[src >= 0] += a
            for c in range(0, a, block):
                size, at = _against(t[c : min(c + block + ahead, n)], mine, b - a, min(block, a - c))
                better = size > best
                best[better], src[better] = size[better], at[better] + c
            while i < b and (best[i - a] < ahead or ahead >= n):
                size, at = (int(best[i - a]), int(src[i - a])) if best[i - a] >= min_len else (1, -1)
                out.append((i, at, size))
                i += size
            ahead *= 2
    return out


def memory_parse(s: Suffixes, min_len: int) -> list[tuple[int, int, int]]:
    """Unidirectional greedy parse of one text that is kept in memory: the smaller neighbours in suffix order are found for
    all positions, but symbols are compared at the starts of phrases only, so no array of lengths is made."""
    n, i, out = s.n, 0, []
    data = s.t.astype(np.int32).tobytes()
    sides = []
    for direction in (1, -1):
        o = s.order[::direction]
        near = _nearest_smaller(o, s.text[o])
        src = np.full(n, -1, np.int64)
        src[o[near >= 0]] = o[near[near >= 0]]
        sides.append(src)
    while i < n:
        size, at = 1, -1
        for j in sorted({int(x[i]) for x in sides if x[i] >= 0}):
            got = _extend(data, j, i, 0, n - i)
            if got >= min_len and got > (size if at >= 0 else 0):
                size, at = got, j
        out.append((i, at, size))
        i += size
    return out


def bwt_run_parse(s: Suffixes) -> tuple[np.ndarray, np.ndarray]:
    """Source of every position by its neighbour in suffix order, -1 for the literals at the heads of the runs of the
    transformed text: inside a run, the symbols before two neighbouring suffixes are equal."""
    src = np.full(s.n, -1, np.int64)
    if s.n < 2:
        return src, np.arange(s.n)
    a, b = s.order[1:], s.order[:-1]
    begin = s.first[s.text]
    ok = (s.text[a] == s.text[b]) & (a > begin[a]) & (b > begin[b])
    a, b = a[ok], b[ok]
    same = s.t[a - 1] == s.t[b - 1]
    src[a[same] - 1] = b[same] - 1
    return src, np.flatnonzero(src < 0)


def resolve(parent: np.ndarray) -> tuple[np.ndarray, int]:
    """Follow parents to the roots (``parent[i] == i``) by doubling; the roots and the number of rounds."""
    rounds, limit = 0, int(len(parent)).bit_length() + 2
    root = parent == np.arange(len(parent))
    while True:
        nxt = parent[parent]
        if (nxt == parent).all():
            if not root[parent].all():  # doubling turns a circle of 2**k positions into positions that stand still
                raise ValueError("the references run in a circle")
            return parent, rounds
        parent, rounds = nxt, rounds + 1
        if rounds > limit:
            raise ValueError("the references run in a circle")


def resolve_in_order(parent: np.ndarray) -> int:
    """Rounds of pointer jumping when positions are taken from left to right and see what the round has moved already."""
    p, rounds, limit = parent.tolist(), 0, int(len(parent)).bit_length() + 2
    while True:
        moved = False
        for i, q in enumerate(p):
            if p[q] != q:
                p[i], moved = p[q], True
        if not moved:
            return rounds
        rounds += 1
        if rounds > limit:
            raise ValueError("the references run in a circle")


def unresolved(parent: np.ndarray) -> np.ndarray:
    """Positions that never come to a root: they lie on a circle or lead to one."""
    root = parent == np.arange(len(parent))
    for _ in range(int(len(parent)).bit_length() + 1):
        parent = parent[parent]
    return np.flatnonzero(~root[parent])


def depths(parent: np.ndarray) -> np.ndarray:
    """Number of steps from every position to its root."""
    root = parent == np.arange(len(parent))
    hops = (~root).astype(np.int64)
    p = parent.copy()
    for _ in range(int(len(p)).bit_length() + 2):
        if (p[p] == p).all():
            if not root[p].all():
                break
            return hops
        hops, p = hops + hops[p], p[p]
    raise ValueError("the references run in a circle")


def char_parents(n: int, dst: np.ndarray, src: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The parent position of every position; literals are their own."""
    p = np.arange(n)
    if len(dst):
        at = np.repeat(dst, size) + ramp(size)
        p[at] = np.repeat(src, size) + ramp(size)
    return p


def ramp(size: np.ndarray) -> np.ndarray:
    total = int(size.sum())
    return np.arange(total) - np.repeat(np.cumsum(size) - size, size)


def optimal_bidirectional(text: str, min_len: int = 2) -> int:
    """Fewest factors over all cycle-free codings of a tiny text, by exhaustive search; literals count one each."""
    n = len(text)
    best = n
    p = list(range(n))

    def circle(a: int, b: int) -> bool:
        for i in range(a, b):
            seen, j = set(), i
            while p[j] != j:
                if j in seen:
                    return True
                seen.add(j)
                j = p[j]
        return False

    def go(i: int, used: int) -> None:
        nonlocal best
        if used >= best:
            return
        if i == n:
            best = used
            return
        for size in range(n - i, min_len - 1, -1):
            for s in range(0, n - size + 1):
                if s != i and text[s : s + size] == text[i : i + size]:
                    p[i : i + size] = range(s, s + size)
                    if not circle(i, i + size):
                        go(i + size, used + 1)
                    p[i : i + size] = range(i, i + size)
        go(i + 1, used + 1)

    go(0, 0)
    return best


def nested_text(m: int) -> list[int]:
    """A family of m * m symbols whose list of waiting peaks grows with m: nested palindromes, from the innermost outwards."""
    blocks, inner = [], [m]
    blocks.append(inner)
    for i in range(m - 1, 0, -1):
        inner = [i, *inner, i]
        blocks.append(inner)
    return [x for b in blocks for x in b]
