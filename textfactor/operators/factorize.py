"""Factorizations of a collection: bidirectional ones by several methods, and the unidirectional and windowed baselines.

Every method returns references ``text_id, dst, len, src``; ``coding.encode`` adds the literals between them.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from textfactor import schemas
from textfactor.functions import kernels as K
from textfactor.operators.runner import per_batch

#: method -> what it does
METHODS = {
    "rounds": "all maximal peaks of a round at once, over the whole batch",
    "peaks": "one left-to-right pass with a list of waiting peaks",
    "cut": "all maximal peaks of one round, then the segments between them",
    "preliminary": "the leftmost maximal peak of a segment, then its two sides",
    "segments": "leftmost highest candidate of a segment, then its two sides",
    "heap": "a heap by length, then position",
    "definition": "the mutable array of the definition",
}


def factorize(texts: DataFrame, min_len: int = 2, method: str = "rounds", unit: str = "codepoint", tie: str = "leftmost") -> DataFrame:
    """Bidirectional references, longest repeat first; ``tie`` other than leftmost gives the any-longest scheme (heap only)."""
    if method not in METHODS:
        raise ValueError(f"unknown method: {method}")
    if min_len < 2:
        raise ValueError("min_len must be at least 2")

    def kernel(strings, t, first):
        s = K.Suffixes(t, first)
        phi = s.phi()
        v = s.plcp(phi)
        if method == "rounds":
            dst, size = K.rounds_factors(v, first, min_len)
        else:
            found = []
            for a, b in zip(first[:-1].tolist(), first[1:].tolist()):
                part, whole = v[a:b], np.array([0, b - a])
                if method == "heap":
                    got = K.heap_factors(part, min_len, tie)
                elif method == "segments":
                    got = K.split_factors(part, whole, min_len) if b > a else []
                elif method == "peaks":
                    got = K.scan_factors(part, min_len)
                elif method == "cut":
                    got = K.cut_factors(part, whole, min_len)
                elif method == "preliminary":
                    got = K.preliminary_factors(part, min_len)
                else:
                    got = K.definition_factors(part, min_len)
                found += sorted((i + a, k) for i, k in got)
            dst, size = np.array(found, np.int64).reshape(-1, 2).T
        return _references(s, first, dst, size, phi[dst] if len(dst) else dst)

    return per_batch(texts, schemas.REFERENCES, kernel, unit)


def _references(s, first, dst, size, src):
    row = s.text[dst] if len(dst) else np.zeros(0, np.int64)
    begin = first[:-1][row] if len(dst) else row
    return row, [dst - begin + 1, size, src - begin + 1]


def parse_unidirectional(texts: DataFrame, min_len: int = 2, method: str = "lpf", unit: str = "codepoint", block: int = 1 << 12) -> DataFrame:
    """Greedy parse with earlier sources: through the longest-previous-factor array; ``scan``: by passing the text before each block;
    ``memory``: comparing symbols of a text in memory at the starts of phrases only."""
    if method == "scan":
        return _one_by_one(texts, lambda t: K.scan_parse(t, block, min_len), unit)
    if method == "memory":
        return _one_by_one(texts, lambda t: K.memory_parse(K.Suffixes(t, np.array([0, len(t)])), min_len), unit)
    if method != "lpf":
        raise ValueError(f"unknown method: {method}")

    def kernel(strings, t, first):
        s = K.Suffixes(t, first)
        size, src = s.previous_factors()
        size = np.where(size >= min_len, size, 1)
        at = K.greedy_parse(size, first)
        at = at[size[at] >= min_len]
        return _references(s, first, at, size[at], src[at])

    return per_batch(texts, schemas.REFERENCES, kernel, unit)


def _one_by_one(texts: DataFrame, parse, unit: str) -> DataFrame:
    return _parsed(texts, lambda t, first: (parse(t[a:b]) for a, b in zip(first[:-1].tolist(), first[1:].tolist())), unit)


def _parsed(texts: DataFrame, parses, unit: str) -> DataFrame:
    """References of ``parses(t, first)``, which gives the phrases of a batch text by text."""

    def kernel(strings, t, first):
        found = []
        for k, phrases in enumerate(parses(t, first)):
            # as an array: the phrases of a whole batch as Python numbers take over a hundred bytes each
            got = np.array([(k, i + 1, n, j + 1) for i, j, n in phrases if j >= 0], np.int64).reshape(-1, 4)
            found.append(got.astype(np.int32) if len(t) < 1 << 31 else got)
        cols = np.concatenate(found).astype(np.int64) if found else np.zeros((0, 4), np.int64)
        return cols[:, 0].copy(), [cols[:, 1].copy(), cols[:, 2].copy(), cols[:, 3].copy()]

    return per_batch(texts, schemas.REFERENCES, kernel, unit)


def parse_end_aligned(texts: DataFrame, min_len: int = 2, unit: str = "codepoint") -> DataFrame:
    """Earlier sources that end where an earlier phrase ends."""
    return _parsed(texts, lambda t, first: K.end_aligned_parses(t, first, min_len), unit)


def parse_window(texts: DataFrame, window: int, min_len: int = 3, unit: str = "codepoint") -> DataFrame:
    """Earlier sources that begin at most ``window`` symbols before."""
    return _one_by_one(texts, lambda t: K.window_parse(t, window, min_len), unit)


def parse_bwt_runs(texts: DataFrame, unit: str = "codepoint") -> DataFrame:
    """References of length 1 to the neighbour in suffix order; literals stand at the heads of the runs of the transform."""

    def kernel(strings, t, first):
        s = K.Suffixes(t, first)
        src, _ = K.bwt_run_parse(s)
        at = np.flatnonzero(src >= 0)
        # neighbours whose sources are neighbours too are one reference
        join = np.ones(len(at), bool)
        join[1:] = (np.diff(at) != 1) | (np.diff(src[at]) != 1) | (s.text[at[1:]] != s.text[at[:-1]])
        start = np.flatnonzero(join)
        return _references(s, first, at[start], np.diff(np.append(start, len(at))), src[at[start]])

    return per_batch(texts, schemas.REFERENCES, kernel, unit)


def peak_list_stats(texts: DataFrame, min_len: int = 2, unit: str = "codepoint") -> DataFrame:
    """``text_id, n, longest_list, bwt_runs, bound``: the longest list of waiting peaks beside min(sqrt(n lg n), runs)."""

    def kernel(strings, t, first):
        s = K.Suffixes(t, first)
        v = s.plcp(s.phi())
        _, heads = K.bwt_run_parse(s)
        out = []
        for k, (a, b) in enumerate(zip(first[:-1].tolist(), first[1:].tolist())):
            stats: dict = {}
            K.scan_factors(v[a:b], min_len, stats)
            runs = int(((heads >= a) & (heads < b)).sum())
            out.append((b - a, stats["longest_list"], runs, min(float(np.sqrt((b - a) * np.log2(max(2, b - a)))), runs)))
        n, longest, runs, bound = zip(*out) if out else ([], [], [], [])
        return np.arange(len(first) - 1), [np.array(n, np.int64), np.array(longest, np.int64), np.array(runs, np.int64), pa.array(bound, pa.float64())]

    return per_batch(texts, "text_id {id}, n long, longest_list long, bwt_runs long, bound double", kernel, unit)
