"""Suffix ranks of one long text by prefix doubling on packed arrays.

Text and order are cut into parts of about ``PART`` positions. A row holds the arrays that one part sends to another, so Spark moves a few
rows for each pair of parts and NumPy does the rest. A round asks for ranks of the positions only that share theirs, sorts
these by two ranks, and drops its tables when the next is written.

What crosses the borders of parts (counts, first and last rank, candidates for the next borders) is one row per part, taken to the driver.
"""

from __future__ import annotations

from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textfactor.plans.scratch import Scratch

PART = 1 << 20
#: Candidates for the borders of the next round that each part gives.
BORDERS = 64
DEALT = "to int, pos binary, old binary, a binary"
SORTED = "part int, n long, first long, last long, head long, tail long, left long, borders binary, pos binary, old binary, start binary, alone binary"
LEVEL = "pos long, rank long, alone boolean"
#: What a part of the text gets: all its ranks (``STORE``), positions behind which ranks are asked for and their own ranks (``ASKED``), or
#: positions and ranks that changed in round k (k).
STORE, ASKED = -2, -1
SENT = "to int, kind int, x binary, y binary"


class _Sorted(NamedTuple):
    """The sorted positions of a round, and for each part the first group and how many rows of it stand in the parts before."""

    table: DataFrame
    carry: dict[int, tuple[int, int]]
    size: int
    left: int
    borders: np.ndarray


def _numbers(data: bytes | None, kind) -> np.ndarray:
    return np.frombuffer(data or b"", kind)


def _joined(data: list, kind) -> np.ndarray:
    return np.frombuffer(b"".join(x or b"" for x in data), kind)


def _batch(schema: str, cols: list) -> pa.RecordBatch:
    kinds = {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary(), "boolean": pa.bool_()}
    fields = [c.split() for c in schema.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array(c, kinds[k]) for c, (_, k) in zip(cols, fields)], [name for name, _ in fields])


def _split(to: np.ndarray, *cols: np.ndarray):
    """``(number, arrays)`` of the rows that go to the same part."""
    by = np.argsort(to, kind="stable")
    to = to[by]
    cuts = np.flatnonzero(np.diff(to, prepend=-1, append=-1)) if len(to) else np.zeros(0, np.int64)
    cols = [c[by] for c in cols]
    for a, z in zip(cuts[:-1].tolist(), cuts[1:].tolist()):
        yield int(to[a]), [c[a:z] for c in cols]


def _place(old: np.ndarray, a: np.ndarray, borders: np.ndarray, top: int) -> np.ndarray:
    """The part of each pair, which ascends with the pairs; a group that is a border several times is dealt by its second rank."""
    low, high = np.searchsorted(borders, old, "left"), np.searchsorted(borders, old, "right")
    return low + a * (high - low + 1) // top


def _small(n: int):
    return np.int32 if n < (1 << 31) - 2 else np.int64


def _sort(dealt: DataFrame, parts: int, n: int, scratch: Scratch) -> _Sorted:
    """Sorts pairs ``old, a``: in each group of equal ``old`` the number of rows before, and whether the pair is there once."""
    small = _small(n)

    def run(it):
        got = [[], [], []]
        part = None
        for b in it:
            part = b.column(0)[0].as_py() if b.num_rows else part
            for k in range(3):
                got[k] += b.column(k + 1).to_pylist()
        if part is None:
            return
        pos, old, a = _joined(got[0], small), _joined(got[1], small), _joined(got[2], np.int64)
        got.clear()
        if old.min() == old.max():
            by = np.argsort(a)
        elif small is np.int32:
            by = np.argsort((old - old.min()).astype(np.int64) * (n + 2) + a)
        else:
            by = np.lexsort((a, old))
        pos, old, a = pos[by], old[by], a[by]
        at = np.arange(len(pos))
        opens = np.append(True, old[1:] != old[:-1])
        fresh = opens | np.append(True, a[1:] != a[:-1])
        group = np.maximum.accumulate(np.where(opens, at, 0))
        start = np.maximum.accumulate(np.where(fresh, at, 0)) - group
        alone = fresh & np.append(fresh[1:], True)
        open_ = (old.astype(np.int64) + start)[~alone]
        some = open_[np.linspace(0, len(open_) - 1, BORDERS).astype(np.int64)] if len(open_) else open_
        head = int(np.searchsorted(old, old[0], "right"))
        row = (part, len(pos), int(old[0]), int(old[-1]), head, len(pos) - int(group[-1]), len(open_), some.tobytes())
        yield _batch(SORTED, [[v] for v in (*row, pos.tobytes(), old.tobytes(), start.astype(small).tobytes(), alone.tobytes())])

    table = scratch.save(dealt.repartitionById(parts, "to").mapInArrow(run, SORTED), "ranked")
    carry, before, tail, size, left, ranks, weights = {}, None, 0, 0, 0, [], []
    for r in sorted(table.drop("pos", "old", "start", "alone").collect(), key=lambda r: r["part"]):
        c = tail if before == r["first"] else 0
        carry[r["part"]] = (r["first"], c)
        tail = r["tail"] + (c if r["first"] == r["last"] else 0)
        before, size, left = r["last"], size + r["n"], left + r["left"]
        some = _numbers(r["borders"], np.int64)
        ranks.append(some + np.where(some < r["first"] + r["head"], c, 0))
        weights.append(np.full(len(some), r["left"] / max(1, len(some))))
    ranks, weights = (np.concatenate(x) if x else np.zeros(0) for x in (ranks, weights))
    by = np.argsort(ranks)
    full = np.cumsum(weights[by])
    cuts = np.searchsorted(full, np.arange(1, -(-left // PART)) * PART) if left else np.zeros(0, np.int64)
    return _Sorted(table, carry, size, left, ranks[by][np.minimum(cuts, len(by) - 1)].astype(np.int64))


def _ranks(b: pa.RecordBatch, carry: dict[int, tuple[int, int]], small):
    """``pos, rank, alone`` of each part of a batch of ``SORTED``."""
    get = lambda name: b.column(b.schema.get_field_index(name)).to_pylist()
    for part, pos, old, start, alone in zip(*map(get, ("part", "pos", "old", "start", "alone"))):
        first, before = carry[part]
        old = _numbers(old, small)
        yield _numbers(pos, small), old + _numbers(start, small) + np.where(old == first, before, 0).astype(small), _numbers(alone, bool)


def _held(it):
    """The first two columns of about ``PART`` rows at a time."""
    held, size = [], 0
    for b in it:
        if b.num_rows:
            held.append((b.column(0).to_numpy(), b.column(1).to_numpy()))
            size += b.num_rows
        if size >= PART:
            yield [np.concatenate(x) for x in zip(*held)]
            held, size = [], 0
    if held:
        yield [np.concatenate(x) for x in zip(*held)]


def _keyed(symbols: DataFrame, n: int, parts: int) -> DataFrame:
    """``DEALT`` of the first round: no rank yet, the next symbols are compared."""
    small = _small(n)
    stride = max(1, n // (BORDERS * parts))
    keys = symbols.where(F.col("pos") % stride == 0).select("key").toArrow().column(0).to_numpy()
    borders = np.sort(keys)[np.arange(1, parts) * len(keys) // parts]

    def run(it):
        for pos, key in _held(it):
            rows = [(to, p.astype(small).tobytes(), np.zeros(len(p), small).tobytes(), k.tobytes()) for to, (p, k) in _split(np.searchsorted(borders, key), pos, key)]
            yield _batch(DEALT, list(zip(*rows)))

    return symbols.select("pos", "key").mapInArrow(run, DEALT)


def _sent(now: _Sorted, n: int, k: int, ahead: int | None = None) -> DataFrame:
    """``SENT``: the ranks that round k made, to the parts of their positions; or (``ahead``) what is open, to the parts it asks."""
    small, carry, size = _small(n), now.carry, PART

    def run(it):
        for b in it:
            for pos, rank, alone in _ranks(b, carry, small):
                if ahead is not None:
                    pos, rank = pos[~alone], rank[~alone]
                at = pos.astype(np.int64) - 1 + (ahead or 0)
                rows = [(to, k if ahead is None else ASKED, x.tobytes(), y.tobytes()) for to, (x, y) in _split(np.minimum(at, n - 1) // size, pos, rank)]
                if rows:
                    yield _batch(SENT, list(zip(*rows)))

    return now.table.select("part", "pos", "old", "start", "alone").mapInArrow(run, SENT)


def _gathered(it, n: int, size: int):
    """What came to one part: its number, its ranks, and the positions that ask with their ranks."""
    small = _small(n)
    rows = sorted(((r["to"], r["kind"], r["x"], r["y"]) for b in it for r in b.to_pylist()), key=lambda r: r[1])
    if not rows:
        return
    part = rows[0][0]
    rank = np.zeros(min(size, n - part * size), small)
    for _, kind, x, y in rows:
        if kind == STORE:
            rank = _numbers(x, small).copy()
        elif kind != ASKED:
            rank[_numbers(x, small) - 1 - part * size] = _numbers(y, small)
    yield part, rank, *(_joined([r[c] for r in rows if r[1] == ASKED], small) for c in (2, 3))


def levels(symbols: DataFrame, n: int, width: int, scratch: Scratch) -> list[DataFrame]:
    """``pos, rank, alone`` for each doubling round, of the positions whose rank was not unique before; ``symbols``: ``pos, key`` of the next
    ``width`` symbols of each of the ``n`` positions."""
    small, size = _small(n), PART
    parts = max(1, -(-n // size))
    out, pending, store = [], [], None

    def level(now: _Sorted) -> DataFrame:
        carry = now.carry

        def run(it):
            for b in it:
                for pos, rank, alone in _ranks(b, carry, small):
                    yield _batch(LEVEL, [pos.astype(np.int64), rank.astype(np.int64), alone])

        return scratch.save(now.table.select("part", "pos", "old", "start", "alone").mapInArrow(run, LEVEL), "level")

    def sent(*more: DataFrame) -> DataFrame:
        rows = [*([store] if store is not None else []), *(_sent(x, n, k) for k, x in pending), *more]
        all_ = rows[0]
        for x in rows[1:]:
            all_ = all_.unionByName(x)
        return all_.repartitionById(parts, "to")

    def kept(it):
        for part, rank, _, _ in _gathered(it, n, size):
            yield _batch(SENT, [[part], [STORE], [rank.tobytes()], [None]])

    now = _sort(_keyed(symbols, n, parts), parts, n, scratch)
    out.append(level(now))
    for k in range(64):
        if not now.left:
            for x in [now, *(x for _, x in pending)]:
                scratch.drop(x.table)
            if store is not None:
                scratch.drop(store)
            return out
        pending.append((k, now))
        if store is None or sum(x.size for _, x in pending) > n // 4:
            old, store = store, scratch.save(sent().mapInArrow(kept, SENT), "store")
            if old is not None:
                scratch.drop(old)
            for _, x in pending:
                if x is not now:
                    scratch.drop(x.table)
            pending = []
        h, borders = width << k, now.borders

        def paired(it):
            for part, rank, pos, own in _gathered(it, n, size):
                if not len(pos):
                    continue
                at = pos.astype(np.int64) - 1 + h
                a = np.where(at < n, rank[np.minimum(at, n - 1) - part * size].astype(np.int64) + 1, 0)
                rows = [(to, *(v.tobytes() for v in x)) for to, x in _split(_place(own, a, borders, n + 1), pos, own, a)]
                yield _batch(DEALT, list(zip(*rows)))

        past = now
        now = _sort(sent(_sent(past, n, k, h)).mapInArrow(paired, DEALT), len(borders) + 1, n, scratch)
        if not pending:  # the store has its ranks
            scratch.drop(past.table)
        out.append(level(now))
    raise RuntimeError("ranks did not settle")
