"""Longest matches of texts with a small set of items: which documents quote an item?

The items go to all executors in blocks of bounded size; a batch of texts is sorted together with a block. The suffixes around
an item's own are the places that hold all of it; the nearest item suffix on both sides of a text's suffix gives its longest match.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from textfactor.functions import kernels as K
from textfactor.operators.runner import batches_of, symbol_batch
from textfactor.plans.scratch import Scratch

MAX_ITEM_SYMBOLS = 1 << 22


def _blocks(items: DataFrame):
    """The items that have a text, in blocks of at most ``MAX_ITEM_SYMBOLS`` symbols (one longer item is a block); the driver
    holds one block and one partition's items."""
    ids: dict[str, list] = {}
    size = 0
    for r in items.where("text IS NOT NULL").select("item_id", "text").toLocalIterator():
        cost = len(r["text"]) + 1
        if ids and size + cost > MAX_ITEM_SYMBOLS:
            yield ids
            ids, size = {}, 0
        ids.setdefault(r["text"], []).append(r["item_id"])
        size += cost
    if ids:
        yield ids


def _interval(s: K.Suffixes, slot: np.ndarray, size: np.ndarray, way: int) -> np.ndarray:
    """How far from each ``slot`` of the suffix order in direction ``way`` suffixes share its first ``size`` symbols."""
    low, high = np.zeros(len(slot), np.int64), slot.copy() if way < 0 else s.n - 1 - slot
    while (open_ := np.flatnonzero(low < high)).size:
        mid = (low[open_] + high[open_] + 1) // 2
        far = s.common(s.order[slot[open_]], s.order[slot[open_] + way * mid]) >= size[open_]
        low[open_[far]] = mid[far]
        high[open_[~far]] = mid[~far] - 1
    return low


def quotes(texts: DataFrame, items: DataFrame) -> DataFrame:
    """``text_id, item_id, pos, len``: every item that a text holds as a whole, at its first place there; beside that, the
    longest match of every text with the items (of a block) that are nearest to its suffixes.

    ``items(item_id, text)``: equal and nested items are each reported; a null text is no item, an empty one is in every
    text. Items beyond ``MAX_ITEM_SYMBOLS`` symbols are searched in blocks, one pass over the texts for each.
    """
    item_type = items.schema["item_id"].dataType
    parts, scratch = [], Scratch(texts.sparkSession, "quotes")
    for ids in _blocks(items):
        if parts:
            parts[-1] = scratch.save(parts[-1], "block")  # its items need not stay with the driver
        parts.append(_quotes(texts, ids, item_type))
    return reduce(DataFrame.unionByName, parts or [_quotes(texts, {}, item_type)])


def _quotes(texts: DataFrame, ids_of: dict[str, list], item_type) -> DataFrame:
    groups = list(ids_of.values())
    item_syms, item_first = K.as_batch([np.append(K.symbols_of(x), -2 - i) for i, x in enumerate(ids_of)])
    item_of = np.repeat(np.arange(len(groups)), np.diff(item_first))
    kind, item_kind = texts.schema["text_id"].dataType.simpleString(), item_type.simpleString()

    def run(it):
        m = len(item_syms)
        starts, whole = item_first[:-1], np.diff(item_first) - 1
        for text_ids, strings in batches_of(it, 1 << 19):
            if not m:
                continue
            t, first = symbol_batch(strings, "codepoint")
            text_of = np.repeat(np.arange(len(strings)), np.diff(first))
            # every text ends with a symbol of its own, so that no match crosses its end
            closed = np.insert(t.astype(np.int64), first[1:], -2 - len(groups) - np.arange(len(strings)))
            owner = np.insert(text_of, first[1:], -1)
            s = K.Suffixes(np.concatenate([item_syms, closed]), np.array([0, m + len(closed)]))
            is_item = s.order < m
            slot = np.arange(s.n)
            before = np.maximum.accumulate(np.where(is_item, slot, -1))
            after = np.minimum.accumulate(np.where(is_item, slot, s.n)[::-1])[::-1]
            mine = np.flatnonzero(~is_item & (owner[np.maximum(s.order - m, 0)] >= 0))
            best, src = np.zeros(len(mine), np.int64), np.full(len(mine), -1)
            for near in (before[mine], after[mine]):
                ok = np.flatnonzero((near >= 0) & (near < s.n))
                n = s.common(s.order[mine[ok]], s.order[near[ok]])
                up = n > best[ok]
                best[ok[up]], src[ok[up]] = n[up], s.order[near[ok[up]]]
            hit = np.flatnonzero(best > 0)
            pos = s.order[mine[hit]] - m
            found = [_longest(owner[pos], item_of[src[hit]], pos, best[hit])]
            # whole items: all suffixes around an item's first one that share its length
            some = np.flatnonzero(whole > 0)
            at = s.rank[starts[some]].astype(np.int64)
            low, high = at - _interval(s, at, whole[some], -1), at + _interval(s, at, whole[some], 1)
            a = 0
            reach = np.cumsum(high - low + 1)
            while a < len(some):
                z = max(a + 1, int(np.searchsorted(reach, (reach[a - 1] if a else 0) + (1 << 22), "right")))
                size = high[a:z] - low[a:z] + 1
                pos = s.order[np.repeat(low[a:z] - np.cumsum(size) + size, size) + np.arange(int(size.sum()))] - m
                item = np.repeat(some[a:z], size)
                ok = pos >= 0
                found.append(_longest(owner[pos[ok]], item[ok], pos[ok], whole[item[ok]]))
                a = z
            for i in np.flatnonzero(whole == 0).tolist():
                found.append((np.arange(len(strings)), np.full(len(strings), i), first[:-1] + np.arange(len(strings)), np.zeros(len(strings), np.int64)))
            row, item, pos, size = _longest(*(np.concatenate(c) for c in zip(*found)))
            local = pos - (first[row] + row) + 1
            # equal items have one text and several keys
            times = np.array([len(g) for g in groups])[item]
            pick = np.repeat(np.arange(len(row)), times)
            keys = [k for i in item.tolist() for k in groups[i]]
            yield pa.RecordBatch.from_arrays(
                [text_ids.take(pa.array(row[pick])), pa.array(keys, pa.int64() if item_kind == "bigint" else None), pa.array(local[pick]), pa.array(size[pick])],
                ["text_id", "item_id", "pos", "len"],
            )

    return texts.select("text_id", "text").mapInArrow(run, f"text_id {kind}, item_id {item_kind}, pos long, len long")


def _longest(row, item, pos, size):
    """The longest match of every (row, item), then the first."""
    order = np.lexsort((pos, -size, item, row))
    row, item, pos, size = row[order], item[order], pos[order], size[order]
    top = np.ones(len(row), bool)
    top[1:] = (row[1:] != row[:-1]) | (item[1:] != item[:-1])
    return row[top], item[top], pos[top], size[top]
