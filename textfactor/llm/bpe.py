"""BPE encoding by content-defined chunks that documents share.

A text is cut where a rolling hash of the last bytes meets a pattern, so equal passages of different documents are cut
into equal chunks. Every worker keeps a bounded store of encoded chunks and encodes a chunk once while it is kept.
Then the joins are repaired. White space after a sign that is neither white space nor part of a longer code point always
opens a pre-token, whatever stands before, and texts on both sides of it are encoded independently; call this a safe
place. At a join, the text between the last safe place before and the first one behind is encoded anew; if a
chunk has none, the window reaches into the next chunks. Tokens outside of the windows agree with those of the whole text.

The vocabulary file (``tokenizers`` format) and its rank file are parameters. Added tokens inside a text count as such.

Defined cases: a null text is empty and has no token; an empty table gives no row; rows that repeat are each encoded;
other columns are ignored. A text is held whole, as is its list of ids.
"""

from __future__ import annotations

import base64
import hashlib
import json
import os
import re
from array import array
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textfactor.llm.scratch import bounded_batches
from textfactor.llm.textscan import mix, tidy

MASK_BITS = 10
WINDOW = 24
STORE_BYTES = 16 << 20
#: Fixed value: how the byte-level vocabularies split a text into pre-tokens.
PRETOKENS = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
_SAFE = re.compile(rb"[!-~](?=[ \n])")


def _vocab_paths(name: str = "byte_bpe_50k") -> tuple[str, str]:
    import public_tokenizers

    return public_tokenizers.path(f"{name}.json"), public_tokenizers.path(f"{name}.tiktoken")


def _byte_signs() -> dict[str, int]:
    """The printable sign that byte-level vocabularies write for every byte: itself, or the next one from U+0100 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class ChunkEncoder:
    def __init__(self, vocab: str, ranks: str, store_bytes: int = STORE_BYTES):
        import tiktoken

        spec = json.load(open(vocab, encoding="utf-8"))
        table = {base64.b64decode(a): int(b) for a, b in (line.split() for line in open(ranks, "rb"))}
        sign = _byte_signs()
        self.bytes_of = {i: bytes(sign[c] for c in t) for t, i in spec["model"]["vocab"].items()}
        self.added = {t["content"]: t["id"] for t in spec["added_tokens"]}
        for t, i in self.added.items():
            self.bytes_of[i] = t.encode()
        for b, i in table.items():
            if self.bytes_of.get(i) != b:
                raise ValueError(f"the rank file disagrees with the vocabulary about id {i}")
        self.core = tiktoken.Encoding("chunks", pat_str=PRETOKENS, mergeable_ranks=table, special_tokens=self.added)
        self.allowed = set(self.added)
        self.text_of = {i: str(i) for i in self.bytes_of}
        self.len_of = {i: len(b) for i, b in self.bytes_of.items()}
        with np.errstate(over="ignore"):
            self.values = mix(np.arange(256, dtype=np.uint64), 13)
        self.store: dict[bytes, tuple] = {}
        self.kept, self.limit = 0, store_bytes

    def _ids(self, data: bytes) -> list[int]:
        return self.core.encode(data.decode("utf-8"), allowed_special=self.allowed)

    def cuts(self, data: bytes) -> list[int]:
        """Places between code points where the hash of the bytes before ends in zeros."""
        n = len(data)
        if not n:
            return [0]
        raw = np.frombuffer(data, np.uint8)
        out = [0]
        for a in range(0, n, 1 << 20):
            part = raw[max(0, a - WINDOW) : a + (1 << 20)]
            with np.errstate(over="ignore"):
                v = self.values[part]
                # a rotating sum: the value of a byte has moved out of the word's top after WINDOW steps of 2 or more bits
                h = v.copy()
                width = 1
                while width < WINDOW // 2:
                    h[width:] = h[width:] + (h[:-width] << np.uint64(2 * width))
                    width *= 2
            hit = np.flatnonzero((mix(h) >> np.uint64(64 - MASK_BITS)) == 0) + max(0, a - WINDOW) + 1
            hit = hit[(hit > a) & (hit <= a + (1 << 20)) & (hit < n)]
            out += hit[(raw[hit] & 0xC0) != 0x80].tolist()
        # chunks of a few bytes cost more than they save; which ones are joined depends on the last cut kept only
        kept = [0]
        for c in out[1:]:
            if c - kept[-1] >= 128:
                kept.append(c)
        return [*kept, n]

    def chunk(self, data: bytes) -> tuple:
        """(ids, tokens before the first safe place, that place, tokens before the last safe place, that place)."""
        got = self.store.get(data)
        if got is None:
            ids = self._ids(data)
            first = _SAFE.search(data)
            if first is None:
                got = (ids, None, None, None, None)
            else:
                p = first.end()
                k = done = 0
                while done < p:
                    done += self.len_of[ids[k]]
                    k += 1
                back, q = 64, p
                while True:
                    at = max(0, len(data) - back)
                    last = [m.end() for m in _SAFE.finditer(data, at)]
                    if last or at == 0:
                        q = last[-1] if last else p
                        break
                    back *= 4
                m, left = len(ids), len(data)
                while left > q:
                    m -= 1
                    left -= self.len_of[ids[m]]
                if done != p or left != q:
                    got = (ids, None, None, None, None)
                else:
                    got = (ids, k, p, m, q)
            got = (array("i", ids), *got[1:])
            cost = len(data) + 4 * len(ids) + 400
            if self.kept + cost > self.limit:
                self.store.clear()
                self.kept = 0
            self.store[data] = got
            self.kept += cost
        return got

    def encode(self, text: str) -> list[int]:
        data = text.encode("utf-8")
        cuts = self.cuts(data)
        if len(cuts) <= 2:
            return list(self.chunk(data)[0]) if data else []
        out: list[int] = []
        start = None  # where the window that is to be encoded anew begins; None: nothing is pending
        for a, b in zip(cuts[:-1], cuts[1:]):
            ids, k, p, m, q = self.chunk(data[a:b])
            if k is None:
                start = a if start is None else start
                continue
            if start is not None:
                out += self._ids(data[start : a + p])
                out += ids[k:m]
            else:
                out += ids[:m]
            start = a + q
        if start is not None:
            out += self._ids(data[start:])
        return out

    def decode(self, ids: list[int]) -> str:
        return b"".join(map(self.bytes_of.__getitem__, ids)).decode("utf-8", "replace")


@lru_cache(2)
def encoder(vocab: str, ranks: str) -> ChunkEncoder:
    """Read once in each Python worker."""
    return ChunkEncoder(vocab, ranks)


def encode_texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocab: str | None = None, ranks: str | None = None, with_ids: bool = True) -> DataFrame:
    """``id, n_tokens, ids_sha256, decoded_sha256`` and, if asked for, ``token_ids``."""
    bounded_batches(docs.sparkSession)
    if vocab is None or ranks is None:
        vocab, ranks = _vocab_paths()
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        e = encoder(vocab, ranks)
        names = ["id", "n_tokens", "ids_sha256", "decoded_sha256"] + ["token_ids"] * with_ids
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                part = batch.slice(at, 500)
                n, sha, back, all_ids = [], [], [], []
                for t in part.column(1):
                    ids = e.encode(t.as_py() or "")
                    n.append(len(ids))
                    sha.append(hashlib.sha256(",".join(map(e.text_of.__getitem__, ids)).encode()).hexdigest())
                    back.append(hashlib.sha256(e.decode(ids).encode("utf-8")).hexdigest())
                    if with_ids:
                        all_ids.append(np.array(ids, np.int32))
                cols = [part.column(0), pa.array(n, pa.int64()), pa.array(sha, pa.string()), pa.array(back, pa.string())]
                if with_ids:
                    cols.append(pa.array(all_ids, pa.list_(pa.int32())))
                yield pa.RecordBatch.from_arrays(cols, names)
            tidy()

    schema = f"id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", token_ids array<int>" * with_ids
    return docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).mapInArrow(run, schema).withColumnRenamed("id", id_col)


def op4_bpe(spark, sf_dir: str) -> DataFrame:
    return encode_texts(spark.read.parquet(f"{sf_dir}/documents.parquet"), with_ids=False)
