"""Benchmark decontamination by SimHash fingerprints of item-sized windows.

Words are runs of ASCII letters, digits and bytes of longer code points, A-Z as a-z. An item of m shingles (``K`` words each)
is compared with every window of m shingles of a document (with the whole document if that is shorter). Windows whose
number of benchmark shingles is under ``THRESHOLD`` * m cannot reach the threshold and get no fingerprint. Of the others,
the 64-bit SimHash is looked up in a multi-index: the bits are cut into ``BLOCKS`` blocks, and the index lists an item
under all block values within ``RADIUS`` // ``BLOCKS`` bits of its own, so every item within ``RADIUS`` bits of a window
shares a list with it. Candidates within the radius are verified by the exact similarity of the weighted shingles
(multisets: sum of minima over sum of maxima of the counts).

Items travel to the executors in blocks of at most ``ITEM_BYTES`` of text, each block met by all documents in one scan.

Defined cases: null or empty texts and items have no window; a text or an item with fewer than ``K`` words is one shingle,
its whole sequence; items that repeat are each reported; rows that repeat are each searched; a null id is kept; a table
without rows or items gives no pair; other columns are ignored.
"""

from __future__ import annotations

import itertools
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textfactor.llm.scratch import bounded_batches
from textfactor.llm.textscan import Words, pieces, shingles

K = 5
THRESHOLD = 0.8
#: Two bags with a similarity of 0.8 differ in 10 of 64 bits on average, with a deviation of 3. With these blocks the lists of a
#: window hold about a quarter of the items of its size.
RADIUS = 19
BLOCKS = (13, 13, 13, 13, 12)
ITEM_BYTES = 8 << 20
_BREAK = np.array([not (48 <= b <= 57 or 65 <= b <= 90 or 97 <= b <= 122 or b >= 128) for b in range(256)])
_FILTER_BITS = 20
_STARTS = 4096


def fingerprints(values: np.ndarray, start: np.ndarray, m: int) -> np.ndarray:
    """64-bit SimHash of the windows ``values[s:s + m]``, for ascending starts."""
    low = int(start[0])
    part = np.ascontiguousarray(values[low : int(start[-1]) + m])
    signs = np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1).astype(np.int32) * 2 - 1
    run = np.zeros((len(part) + 1, 64), np.int32)
    np.cumsum(signs, axis=0, out=run[1:])
    at = start - low
    return np.packbits(run[at + m] - run[at] > 0, axis=1).view(np.uint64).ravel()


def _near(width: int, radius: int) -> np.ndarray:
    """All values of ``width`` bits with at most ``radius`` ones."""
    return np.array([sum(1 << b for b in bits) for r in range(radius + 1) for bits in itertools.combinations(range(width), r)], np.int64)


class ItemIndex:
    """The benchmark's shingles and, for every item size, a multi-index of the items' fingerprints."""

    def __init__(self, ids: list, texts: list):
        w = Words(pa.array(texts, pa.string()), space=_BREAK)
        h, _, bounds = shingles(w, K)
        self.ids, self.bags, by_size = ids, [], defaultdict(list)
        prints = np.zeros(len(ids), np.uint64)
        for i, (a, b) in enumerate(zip(bounds[:-1].tolist(), bounds[1:].tolist())):
            self.bags.append(Counter(h[a:b].tolist()))
            if b > a:
                prints[i] = fingerprints(h[a:b], np.zeros(1, np.int64), b - a)[0]
                by_size[b - a].append(i)
        self.known = np.unique(h)
        self.filter = np.zeros(1 << _FILTER_BITS, bool)
        self.filter[(self.known >> np.uint64(64 - _FILTER_BITS)).astype(np.int64)] = True
        self.prints = prints
        self.sizes = sorted(by_size)
        self.tables = {m: self._table(np.array(by_size[m])) for m in self.sizes}

    def _table(self, items: np.ndarray) -> list:
        out, shift = [], 0
        for width in BLOCKS:
            own = ((self.prints[items] >> np.uint64(shift)) & np.uint64((1 << width) - 1)).astype(np.int64)
            keys = (own[:, None] ^ _near(width, RADIUS // len(BLOCKS))[None, :]).ravel()
            who = np.repeat(items, len(keys) // len(items))
            order = np.argsort(keys, kind="stable")
            first = np.searchsorted(keys[order], np.arange((1 << width) + 1))
            out.append((shift, width, first, who[order]))
            shift += width
        return out

    def marks(self, h: np.ndarray) -> np.ndarray:
        """Is a shingle one of the benchmark's?"""
        hit = self.filter[(h >> np.uint64(64 - _FILTER_BITS)).astype(np.int64)]
        at = np.flatnonzero(hit)
        pos = np.searchsorted(self.known, h[at])
        hit[at] = self.known[np.minimum(pos, len(self.known) - 1)] == h[at]
        return hit

    def candidates(self, prints: np.ndarray, m: int) -> tuple[np.ndarray, np.ndarray]:
        """(window, item) pairs of items of size m within the radius."""
        pairs = []
        for shift, width, first, who in self.tables[m]:
            key = ((prints >> np.uint64(shift)) & np.uint64((1 << width) - 1)).astype(np.int64)
            n = first[key + 1] - first[key]
            win = np.repeat(np.arange(len(prints)), n)
            off = np.arange(len(win)) - np.repeat(np.cumsum(n) - n, n)
            pairs.append(np.column_stack([win, who[np.repeat(first[key], n) + off]]))
        found = np.unique(np.concatenate(pairs), axis=0)
        far = np.bitwise_count(prints[found[:, 0]] ^ self.prints[found[:, 1]])
        found = found[far <= RADIUS]
        return found[:, 0], found[:, 1]

    def search(self, h: np.ndarray, hit: np.ndarray) -> list[tuple[int, float, int, int]]:
        """(item, similarity, first shingle, shingles) of the best window of every item found in one document."""
        best: dict[int, tuple[float, int, int]] = {}
        run = np.concatenate([[0], np.cumsum(hit)])
        for m in self.sizes:
            size = min(m, len(h))
            need = THRESHOLD * m - 1e-9
            start = np.flatnonzero(run[size:] - run[:-size] >= need)
            if not len(start):
                continue
            cut = np.flatnonzero((np.diff(start) > 4 * m)) + 1
            for part in np.split(start, cut):
                for a in range(0, len(part), _STARTS):
                    s = part[a : a + _STARTS]
                    win, item = self.candidates(fingerprints(h, s, size), m)
                    for p, i in zip(s[win].tolist(), item.tolist()):
                        sim = self.similarity(h[p : p + size], i)
                        if sim >= THRESHOLD - 1e-12 and sim > best.get(i, (0.0,))[0]:
                            best[i] = (sim, p, size)
        return [(i, *x) for i, x in sorted(best.items())]

    def similarity(self, window: np.ndarray, item: int) -> float:
        bag, mine = self.bags[item], Counter(window.tolist())
        both = sum(min(n, mine[s]) for s, n in bag.items() if s in mine)
        return both / (len(window) + sum(bag.values()) - both)


def _item_blocks(items: DataFrame, item_col: str, item_text: str):
    """The items in blocks of bounded size; what the driver holds at once is one partition's items."""
    ids, texts, size = [], [], 0
    for r in items.select(item_col, item_text).toLocalIterator():
        t = r[1] or ""
        if ids and size + len(t) > ITEM_BYTES:
            yield ids, texts
            ids, texts, size = [], [], 0
        ids.append(r[0]), texts.append(t)
        size += len(t)
    if ids:
        yield ids, texts


def _marked(column: pa.Array, index: ItemIndex):
    """Words, shingles, first words and row bounds of a column, which shingles are the benchmark's, and the rows that have
    enough of them for the smallest item."""
    w = Words(column, space=_BREAK)
    h, at, bounds = shingles(w, K)
    hit = index.marks(h)
    many = np.concatenate([[0], np.cumsum(hit)])
    enough = (many[bounds[1:]] - many[bounds[:-1]] >= THRESHOLD * index.sizes[0] - 1e-9) & (bounds[1:] > bounds[:-1])
    return w, h, at, bounds, hit, np.flatnonzero(enough).tolist()


def drop_contaminated(docs: DataFrame, items: DataFrame, text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """``docs`` without the rows in which some item is found: the same search, row by row, so that no text is shuffled."""
    spark = docs.sparkSession
    bounded_batches(spark)
    place, schema = docs.columns.index(text_col), docs.schema
    for ids, texts in _item_blocks(items, item_col, item_text):
        index = ItemIndex(ids, texts)
        if not index.sizes:
            continue
        sent = spark.sparkContext.broadcast(index)  # of a block of bounded size

        def run(batches, sent=sent):
            index = sent.value
            for b in (p for batch in batches for p in pieces(batch, place)):
                _, h, _, bounds, hit, some = _marked(b.column(place), index)
                keep = np.ones(b.num_rows, bool)
                for r in some:
                    keep[r] = not index.search(h[bounds[r] : bounds[r + 1]], hit[bounds[r] : bounds[r + 1]])
                yield b.filter(pa.array(keep))

        docs = docs.mapInArrow(run, schema)
    return docs


def find_items(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """``id, item_id, similarity, start_byte, end_byte``: the best window of every (document, item) pair that reaches the threshold."""
    bounded_batches(docs.sparkSession)
    spark = docs.sparkSession
    kind, item_kind = docs.schema[id_col].dataType.simpleString(), items.schema[item_col].dataType
    schema = f"id {kind}, item {item_kind.simpleString()}, similarity double, start_byte long, end_byte long"
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    out = None
    arrow_item = pa.string() if item_kind.simpleString() == "string" else None
    for ids, texts in _item_blocks(items, item_col, item_text):
        index = ItemIndex(ids, texts)
        if not index.sizes:
            continue
        sent = spark.sparkContext.broadcast(index)  # of a block of bounded size

        def run(batches, sent=sent):
            index = sent.value
            for b in (p for batch in batches for p in pieces(batch, 1)):
                w, h, at, bounds, hit, some = _marked(b.column(1), index)
                row, found = [], []
                for r in some:
                    u, v = bounds[r], bounds[r + 1]
                    last = w.first[r + 1] - 1
                    for i, sim, p, size in index.search(h[u:v], hit[u:v]):
                        a = at[u + p]
                        e = min(a + size + K - 2, last)
                        row.append(r)
                        found.append((index.ids[i], sim, int(w.start[a] - w.off[r]), int(w.end[e] - w.off[r])))
                cols = list(zip(*found)) if found else [[], [], [], []]
                yield pa.RecordBatch.from_arrays(
                    [b.column(0).take(pa.array(row, pa.int64())), pa.array(cols[0], arrow_item or pa.int64()), pa.array(cols[1], pa.float64()), pa.array(cols[2], pa.int64()), pa.array(cols[3], pa.int64())],
                    ["id", "item", "similarity", "start_byte", "end_byte"],
                )

        part = rows.mapInArrow(run, schema)
        out = part if out is None else out.unionByName(part)
    if out is None:
        out = spark.createDataFrame([], schema)
    return out.withColumnRenamed("id", id_col).withColumnRenamed("item", item_col if item_col != id_col else f"{item_col}_item")


def op8_decontamination(spark, sf_dir: str) -> DataFrame:
    return find_items(
        spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"), spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    )
