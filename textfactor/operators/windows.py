"""Common prefixes of pairs of suffixes of one long text: windows of symbols are compared, by parts of the text.

A pair is taken to the part of its first suffix, which adds a window of symbols, and then to the part of its second one, which compares.
Pairs that a whole window agrees on go on with one four times as long, as long as all windows of a round together stay short.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textfactor.operators import order
from textfactor.plans.scratch import Scratch

#: Symbols of the first window, and windows' symbols of a round, in lengths of the text.
WINDOW, MOST = 32, 4
#: Symbols that a task compares at a time.
STEP = 1 << 22
TEXT = "to int, kind int, i binary, j binary, n binary, window binary"
FOUND = "i long, j long, n long"


def text_parts(blocks: DataFrame, symbols: list[int], n: int) -> DataFrame:
    """``TEXT`` rows of kind 0: the symbols of each part of the text, in the place of ``window``."""
    size, kinds, small = order.PART, np.array(symbols, np.int64), _code(symbols)

    def cut(it):
        for b in it:
            rows = []
            for start, body in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                code = np.searchsorted(kinds, np.frombuffer(body.encode("utf-32-le", "surrogatepass"), np.uint32)).astype(small)
                at = start - 1
                for part in range(at // size, -(-(at + len(code)) // size)):
                    low = max(at, part * size)
                    rows.append((part, low - part * size, code[low - at : (part + 1) * size - at].tobytes()))
            if rows:
                yield order._batch("to int, off long, body binary", list(zip(*rows)))

    def join(it):
        rows = sorted((r["to"], r["off"], r["body"]) for b in it for r in b.to_pylist())
        if rows:
            yield order._batch(TEXT, [[rows[0][0]], [0], [None], [None], [None], [b"".join(r[2] for r in rows)]])

    dealt = blocks.select("start", "body").mapInArrow(cut, "to int, off long, body binary")
    return dealt.repartitionById(max(1, -(-n // size)), "to").mapInArrow(join, TEXT)


def _code(symbols: list[int]):
    return np.uint8 if len(symbols) < 1 << 8 else np.uint16 if len(symbols) < 1 << 16 else np.uint32


def _rows(size: int, small, kind: int, at: np.ndarray, i: np.ndarray, j: np.ndarray, k: np.ndarray, window: np.ndarray | None = None) -> list[tuple]:
    """``TEXT`` rows that take pairs to the parts of the positions ``at``."""
    cols = [i.astype(small), j.astype(small), k.astype(small), *([window] if window is not None else [])]
    return [(to, kind, *(x.tobytes() for x in c), *([None] if window is None else [])) for to, c in order._split(at // size, *cols)]


def _asked(it, k: int, size: int, small, code):
    """The text of a part, where it begins, and in steps the pairs that came to it."""
    text = None
    for b in it:
        for r in b.to_pylist():
            if r["kind"] == 0:
                text, part = np.frombuffer(r["window"], code), r["to"]
                continue
            i, j, m = (np.frombuffer(r[c], small).astype(np.int64) for c in "ijn")
            w = np.frombuffer(r["window"], code).reshape(-1, k) if r["window"] is not None else None
            for a in range(0, len(i), max(1, STEP // k)):
                z = a + max(1, STEP // k)
                yield text, part * size, i[a:z], j[a:z], m[a:z], None if w is None else w[a:z]


def _at_text(texts: DataFrame, rows: DataFrame, n: int) -> DataFrame:
    return texts.unionByName(rows).repartitionById(max(1, -(-n // order.PART)), "to").sortWithinPartitions("to", "kind")


def dealt(pairs: DataFrame, n: int) -> DataFrame:
    """``TEXT`` rows of kind 1, pairs, from ``i, j``."""
    size, small = order.PART, order._small(n)

    def run(it):
        for b in it:
            if b.num_rows:
                i, j = (b.column(c).to_numpy() for c in (0, 1))
                yield order._batch(TEXT, list(zip(*_rows(size, small, 1, i - 1, i, j, np.zeros(len(i), small)))))

    return pairs.select("i", "j").mapInArrow(run, TEXT)


def neighbours(ranks: DataFrame, texts: DataFrame, symbols: list[int], n: int) -> DataFrame:
    """``TEXT`` rows of kind 1: each position and the one before it in suffix order, where the symbols before both differ or one has none."""
    size, small, code = order.PART, order._small(n), _code(symbols)

    def by_rank(it):
        for rank, pos in order._held(it):
            again = ((rank + 1) % size == 0) & (rank + 1 < n)  # the last of a part stands before the first of the next one
            to = np.concatenate([rank // size, rank[again] // size + 1])
            rank, pos = (np.concatenate([x, x[again]]).astype(small) for x in (rank, pos))
            yield order._batch(order.SENT, list(zip(*((t, 0, x.tobytes(), y.tobytes()) for t, (x, y) in order._split(to, rank, pos)))))

    def pairs(it):
        rows = [r for b in it for r in b.to_pylist()]
        if not rows:
            return
        low = rows[0]["to"] * size
        rank, pos = (order._joined([r[c] for r in rows], small) for c in "xy")
        by = np.zeros(min(size, n - low) + 1, np.int64)
        by[rank.astype(np.int64) - low + 1] = pos
        i, j = (by[1:], by[:-1]) if low else (by[2:], by[1:-1])
        if len(i):
            yield order._batch(TEXT, list(zip(*_rows(size, small, 1, np.maximum(i - 2, 0), i, j, np.zeros(len(i), small)))))

    def before(it):
        for text, low, i, j, m, _ in _asked(it, 1, size, small, code):
            yield order._batch(TEXT, list(zip(*_rows(size, small, 1, np.maximum(j - 2, 0), i, j, m, text[np.maximum(i - 2, 0) - low]))))

    def differ(it):
        for text, low, i, j, m, w in _asked(it, 1, size, small, code):
            own = (i == 1) | (j == 1) | (w[:, 0] != text[np.maximum(j - 2, 0) - low])
            if own.any():
                yield order._batch(TEXT, list(zip(*_rows(size, small, 1, i[own] - 1, i[own], j[own], m[own]))))

    first = ranks.select("rank", "pos").mapInArrow(by_rank, order.SENT).repartitionById(max(1, -(-n // size)), "to").mapInArrow(pairs, TEXT)
    return _at_text(texts, _at_text(texts, first, n).mapInArrow(before, TEXT), n).mapInArrow(differ, TEXT)


def compare(now: DataFrame, texts: DataFrame, symbols: list[int], n: int, scratch: Scratch) -> tuple[list[DataFrame], DataFrame, DataFrame | None]:
    """Tables to be dropped, and of these ``i, j, n`` of pairs of two positions (``dealt``); at last the same of pairs that may agree further when
    windows get too long."""
    size, small, code = order.PART, order._small(n), _code(symbols)
    width, tables = WINDOW, []

    def add(k):
        def run(it):
            for text, low, i, j, m, _ in _asked(it, k, size, small, code):
                at = i + m - 1 - low
                w = text[np.minimum(at[:, None] + np.arange(k), len(text) - 1)]
                yield order._batch(TEXT, list(zip(*_rows(size, small, 1, j + m - 1, i, j, m, w))))

        return run

    def check(k):
        def run(it):
            for text, low, i, j, m, w in _asked(it, k, size, small, code):
                at = j + m - 1 - low
                same = w == text[np.minimum(at[:, None] + np.arange(k), len(text) - 1)]
                # neither window goes on behind its part
                room = np.minimum(np.minimum(len(text) - at, k), size - (i + m - 1) % size)
                room = np.minimum(room, n + 1 - np.maximum(i, j) - m)
                got = np.minimum(np.where(same.all(1), k, same.argmin(1)), room)
                m = m + got
                on = (got == room) & (np.maximum(i, j) + m <= n)
                rows = _rows(size, small, 1, (i + m - 1)[on], i[on], j[on], m[on])
                if not on.all():
                    rows.append((0, 2, *(x[~on].astype(small).tobytes() for x in (i, j, m)), None))
                yield order._batch(TEXT, list(zip(*rows)))

        return run

    def rows(it):
        for b in it:
            for r in b.to_pylist():
                yield order._batch(FOUND, [np.frombuffer(r[c], small).astype(np.int64) for c in "ijn"])

    found = None
    while True:
        sent = _at_text(texts, now, n).mapInArrow(add(width), TEXT)
        tables.append(scratch.save(_at_text(texts, sent, n).mapInArrow(check(width), TEXT), "compared"))
        more = tables[-1].where("kind = 2").mapInArrow(rows, FOUND)
        found = more if found is None else found.unionByName(more)
        now = tables[-1].where("kind = 1")
        left = now.agg(F.sum(F.length("i"))).first()[0] or 0
        left //= np.dtype(small).itemsize
        if not left:
            return tables, found, None
        width *= 4
        if left * width > MOST * n or width > size:
            return tables, found, now.mapInArrow(rows, FOUND)
