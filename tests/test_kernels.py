import random

import numpy as np
import pytest

from textfactor.functions import kernels as K

EXAMPLE = "ababbabababbabbaababa"


def arrays_of(text):
    t, first = K.as_batch([K.symbols_of(text)])
    s = K.Suffixes(t, first)
    phi = s.phi()
    return s, phi, s.plcp(phi), first


def test_running_example():
    s, phi, plcp, first = arrays_of(EXAMPLE)
    assert [22, *(s.order + 1)] == [22, 21, 16, 19, 17, 6, 1, 8, 13, 3, 10, 20, 15, 18, 5, 7, 12, 2, 9, 14, 4, 11]
    assert (phi + 1).tolist() == [6, 12, 13, 14, 18, 17, 5, 1, 2, 3, 4, 7, 8, 9, 20, 21, 19, 15, 16, 10, 22]
    assert plcp.tolist() == [4, 5, 4, 3, 4, 5, 5, 7, 6, 5, 4, 3, 2, 1, 2, 1, 3, 2, 1, 0, 0]
    steps = []
    assert [(d + 1, n) for d, n in K.definition_factors(plcp, 2, steps)] == [(8, 7), (2, 5), (17, 3), (15, 2)]
    assert steps[0].tolist() == [4, 5, 4, 3, 3, 2, 1, 0, 0, 0, 0, 0, 0, 0, 2, 1, 3, 2, 1, 0, 0]
    assert steps[1].tolist() == [1, 0, 0, 0, 0, 0, 1, 0, 0, 0, 0, 0, 0, 0, 2, 1, 3, 2, 1, 0, 0]
    at = K.reach_steps(plcp, first)
    assert [(p + 1, p + v + 1) for p, v in zip(at, plcp[at]) if v >= 2] == [(1, 5), (2, 7), (5, 9), (6, 11), (7, 12), (8, 15), (15, 17), (17, 20)]
    assert (at[plcp[at] >= 2][K.maximal_peaks(at[plcp[at] >= 2], (at + plcp[at])[plcp[at] >= 2])] + 1).tolist() == [2, 8, 15, 17]


def naive(x):
    n, t = len(x), [*x, -1]
    sa = sorted(range(n + 1), key=lambda i: t[i:])
    phi = [0] * (n + 1)
    for r, i in enumerate(sa):
        phi[i] = sa[r - 1] if r else n
    lcp = lambda i, j: next((k for k in range(n) if i + k >= n or j + k >= n or x[i + k] != x[j + k]), 0) if i != j else 0
    return sa[1:], phi[:n], [lcp(i, phi[i]) for i in range(n)]


@pytest.mark.parametrize("seed", range(6))
def test_all_methods_agree(seed):
    random.seed(seed)
    for _ in range(25):
        texts = [[random.randint(1, random.choice([1, 2, 3, 5])) for _ in range(random.randint(0, 50))] * random.choice([1, 2, 3]) for _ in range(random.randint(1, 4))]
        t, first = K.as_batch([np.array(x, np.int64) for x in texts])
        s = K.Suffixes(t, first)
        phi = s.phi()
        v = s.plcp(phi)
        lpf, src = s.previous_factors()
        for m in (2, 3, 5):
            got = sorted(zip(*(x.tolist() for x in K.rounds_factors(v, first, m))))
            want = []
            for k, x in enumerate(texts):
                a, b = int(first[k]), int(first[k + 1])
                sa, p, n = naive(x)
                assert (s.order[a:b] - a).tolist() == sa and (phi[a:b] - a).tolist() == p and v[a:b].tolist() == n
                d = sorted(K.definition_factors(v[a:b], m))
                assert sorted(K.heap_factors(v[a:b], m)) == d == K.scan_factors(v[a:b], m)
                assert b == a or sorted(K.split_factors(v[a:b], np.array([0, b - a]), m)) == d
                # the list of waiting peaks ascends, and a factor makes no new peak but behind it: asserted inside
                assert K.scan_factors(v[a:b], m, check=True) == d and K.preliminary_factors(v[a:b], m) == d
                assert K.cut_factors(v[a:b], np.array([0, b - a]), m) == d
                want += [(i + a, n) for i, n in d]
            assert got == want
        for i in np.flatnonzero(lpf).tolist():
            a, b = first[s.text[i]], first[s.text[i] + 1]
            n = int(lpf[i])
            assert src[i] < i and t[src[i] : src[i] + n].tolist() == t[i : i + n].tolist()
            longer = t[i : i + n + 1].tolist()
            assert i + n == b or not any(t[j : j + n + 1].tolist() == longer for j in range(a, i))


def test_worst_case_list():
    for m in (5, 8, 12, 100):
        t, first = K.as_batch([np.array(K.nested_text(m), np.int64)])
        s = K.Suffixes(t, first)
        v = s.plcp(s.phi())
        stats = {}
        K.scan_factors(v, 2, stats)
        at = K.reach_steps(v, first)
        at = at[v[at] >= 2]
        peaks = at[(at == 0) | (v[at] > v[np.maximum(at, 1) - 1])]
        good = peaks[K.interesting_peaks(at, at + v[at])[np.isin(at, peaks)]]
        assert len(t) == m * m and len(good) == m - 1 and v[good].tolist() == list(range(2, 2 * m, 2))
        assert stats["longest_list"] == m - 1  # the maximal one waits as well until it is seen to be maximal


def test_optimum_is_a_bound():
    random.seed(4)
    for _ in range(25):
        x = "".join(random.choice("ab") for _ in range(random.randint(1, 9)))
        _, _, v, first = arrays_of(x)
        d, n = K.rounds_factors(v, first, 2)
        assert K.optimal_bidirectional(x) <= len(d) + len(x) - n.sum()


def test_circle_is_found():
    with pytest.raises(ValueError):
        K.resolve(np.array([1, 2, 0]))
    # factors that point at each other while no symbol runs in a circle
    p = K.char_parents(9, np.array([0, 4]), np.array([5, 1]), np.array([4, 4]))
    assert K.depths(p).max() == 8 and set(K.resolve(p)[0]) == {8}


def copies(seed, n=700, longest=320):
    """Random symbols with long copies of what stands before, and runs."""
    rng = random.Random(seed)
    x = [rng.randint(1, 3) for _ in range(5)]
    while len(x) < n:
        a = rng.randrange(len(x))
        x += rng.choice([x[a : a + rng.randint(1, longest)], [rng.randint(1, 3) for _ in range(rng.randint(1, 30))], [1] * rng.randint(1, 40), [1, 2] * rng.randint(1, 90)])
    return np.array(x, np.int64)


def end_aligned_exact(t, min_len):
    """All phrase ends and all lengths are tried."""
    t, i, out, ends = t.tolist(), 0, [], []
    while i < len(t):
        best, src = 0, -1
        for e in ends:
            for k in range(min(e, len(t) - i), max(best, min_len - 1), -1):
                if t[e - k : e] == t[i : i + k]:
                    best, src = k, e - k
                    break
        out.append((i, src, max(1, best)))
        i += max(1, best)
        ends.append(i)
    return out


def test_end_aligned_phrases_have_no_bound():
    long = 0
    for seed in range(12):
        t = copies(seed)
        for m in (2, 5):
            want = end_aligned_exact(t, m)
            long += sum(n > 128 for _, _, n in want)
            assert K.end_aligned_parse(t, m) == want
            for gram in (2, 6, 40):
                assert K.end_aligned_parse(t, m, gram) == want
    assert long > 3
    rng = random.Random(1)
    t = np.tile(np.array([rng.randint(1, 9) for _ in range(500)], np.int64), 4)
    for m in (2, 150):
        assert K.end_aligned_parse(t, m) == end_aligned_exact(t, m)


def test_end_aligned_phrases_of_a_batch_take_few_steps():
    """Texts of a batch as one by one; the time for a symbol is far below that of a table of all strings at phrase ends."""
    import time

    words = [copies(5, 300), np.zeros(0, np.int64), np.array([7]), copies(6, 200, 50), np.zeros(0, np.int64)]
    t, first = K.as_batch(words)
    assert list(K.end_aligned_parses(t, first, 2)) == [end_aligned_exact(x, 2) for x in words]
    rng = random.Random(8)
    text = "".join(rng.choice("etaoin shrdlu") for _ in range(60_000))
    a = time.process_time()
    list(K.end_aligned_parses(*K.as_batch([K.symbols_of(text[i : i + 500]) for i in range(0, len(text), 500)]), 2))
    assert time.process_time() - a < len(text) * 15e-6


def window_exact(t, window, min_len):
    """All places of the window are tried."""
    t, i, out = t.tolist(), 0, []
    while i < len(t):
        best, src = 0, -1
        for j in range(max(0, i - window), i):
            k = 0
            while i + k < len(t) and t[i + k] == t[j + k]:
                k += 1
            if k > best:
                best, src = k, j
        ok = best >= min_len
        out.append((i, src if ok else -1, best if ok else 1))
        i += out[-1][2]
    return out


def test_window_keeps_all_places():
    for seed in range(6):
        t = copies(seed, 500, 60)
        for window in (1, 16, 256, 1024):
            for m in (2, 3):
                assert K.window_parse(t, window, m) == window_exact(t, window, m)
    # one signature, many places: the longest source is the oldest of 100
    rng = random.Random(3)
    t = [*b"abcXYZW"] + [x for _ in range(100) for x in (*b"abc", 300 + rng.randrange(1000))] + [*b"abcXYZW"]
    got = K.window_parse(np.array(t, np.int64), 1024, 3)
    assert got[-1] == (len(t) - 7, 0, 7)


def test_baselines_agree():
    """The parse through the array, by blocks and in memory have the same phrases; sources are earlier and equal."""
    random.seed(9)
    for _ in range(150):
        w = [random.randint(0, random.choice([0, 1, 3])) for _ in range(random.randint(0, 40))]
        w = (w * random.randint(1, 4))[: random.randint(0, 90)]
        t = np.array(w, np.int64)
        first = np.array([0, len(w)])
        s = K.Suffixes(t, first)
        lpf, _ = s.previous_factors()
        step, want, i = np.where(lpf >= 2, lpf, 1), [], 0
        while i < len(w):
            want.append((i, int(step[i])))
            i += int(step[i])
        assert K.greedy_parse(step, first, 4).tolist() == [i for i, _ in want]
        for got in (K.scan_parse(t, 5, 2), K.scan_parse(t, 64, 2), K.memory_parse(s, 2)):
            assert [(i, n) for i, _, n in got] == want
            assert all(j < 0 or (j < i and w[j : j + n] == w[i : i + n]) for i, j, n in got)


def test_jumps_in_order_are_no_slower():
    random.seed(4)
    for _ in range(60):
        p = np.array([random.randint(0, i) for i in range(50)])
        root, rounds = K.resolve(p.copy())
        assert K.resolve_in_order(p) <= rounds <= max(0, int(K.depths(p).max()) - 1).bit_length() and not len(K.unresolved(p))
    assert K.unresolved(np.array([1, 0, 2, 0])).tolist() == [0, 1, 3]


def test_memory_of_a_long_text(monkeypatch):
    """Both schemes take under 140 bytes a symbol; levels in which few positions are left and pairs by pieces change no result."""
    import tracemalloc

    rng = np.random.default_rng(3)
    part = rng.integers(97, 123, 6000)
    t = np.concatenate([rng.integers(97, 123, 200_000), part, rng.integers(97, 123, 50_000), part, part[100:4000]]).astype(np.uint32)
    first = np.array([0, len(t)])

    def run():
        s = K.Suffixes(t, first)
        v = s.plcp(s.phi())
        refs = K.rounds_factors(v, first, 2)
        size, src = s.previous_factors()
        return [v, *refs, size, src, K.greedy_parse(np.where(size >= 2, size, 1), first)], s.levels

    monkeypatch.setattr(K, "PAIRS", 1 << 15)
    tracemalloc.start()
    got, levels = run()
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 140 * len(t), peak / len(t)
    assert len(levels) > 5 and any(not isinstance(x, np.ndarray) for x in levels)
    order = sorted(range(len(t)), key=lambda i, b=t.astype(np.uint8).tobytes(): b[i : i + 6100])
    assert (K.Suffixes(t, first).order == order).all()
    monkeypatch.setattr(K, "PAIRS", 1 << 22)
    assert all((a == b).all() for a, b in zip(got, run()[0]))
