"""Secret scans by one combined automaton.

All rules are compiled into a single minimal transition table (``automaton.combined``). It passes once over the bytes of
a text; where it reports the end of a match, the rule's own small automata find the leftmost start and the longest end. So
each rule yields its leftmost, longest, non-overlapping matches.

Defined cases: a null text is empty and has no span; a null id is kept; rows that repeat are each scanned; an empty table
gives no row; other columns are ignored. Work is one row at a time, so memory is bounded by the longest text.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textfactor.llm.scratch import bounded_batches
from textfactor.llm.automaton import LazyDfa, Nfa, combined


@dataclass(frozen=True)
class Rule:
    """Matches shorter than ``min_len`` bytes are dropped after matching, as are those whose last repeated class, counted from
    the first byte at which the rule can end, is shorter than ``min_tail``. Such limits cost no states of the automaton."""

    kind: str
    pattern: str
    min_tail: int = 1
    min_len: int = 1


#: The kinds that every scan counts.
BASE_RULES = (
    Rule("assign", r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?[A-Za-z0-9+/_.=-]+""", 6),
    Rule("access", r"AKIA[A-Z0-9]+", min_len=20),
    Rule("hex", r"[0-9a-f]{24,}"),
)
#: Further kinds.
MORE_RULES = (
    Rule("private_key", r"-----BEGIN (?:[A-Z]+ )*PRIVATE KEY-----"),
    Rule("forge_token", r"gh[pousr]_[A-Za-z0-9]+", min_len=34),
    Rule("chat_token", r"xox[abprs]-[0-9A-Za-z-]+", min_len=15),
    Rule("signed_token", r"eyJ[A-Za-z0-9_-]+\.eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+"),
    Rule("cloud_key", r"AIza[0-9A-Za-z_-]+", min_len=34),
    Rule("url_login", r"[a-z]+://[A-Za-z0-9._-]+:[A-Za-z0-9._-]+@"),
)


class Scanner:
    def __init__(self, rules: tuple[Rule, ...]):
        self.rules = rules
        nfas = [Nfa(r.pattern) for r in rules]
        table, masks, self.start = combined(nfas)
        self.plain = int((masks == 0).sum())
        self.rows = [tuple(r) for r in table.tolist()]
        self.hits = [[k for k in range(len(rules)) if m >> k & 1] for m in masks.tolist()]
        self.ahead = [LazyDfa(n) for n in nfas]
        self.back = [LazyDfa(n.reversed()) for n in nfas]
        self.alive = [LazyDfa(n.reversed(), all_alive=True) for n in nfas]

    def _longest(self, k: int, data: bytes, s: int) -> tuple[int, int] | None:
        """The first and the last end of rule k's matches that start at s."""
        dfa, q, first, last = self.ahead[k], self.ahead[k].start, 0, 0
        for i in range(s, len(data)):
            q = dfa.step(q, data[i])
            if dfa.accepts(q):
                first, last = first or i + 1, i + 1
            elif dfa.dead(q):
                break
        return (first, last) if last else None

    def _starts(self, dfa: LazyDfa, data: bytes, low: int, i: int) -> list[int]:
        q, out = dfa.start, []
        for j in range(i, low - 1, -1):
            q = dfa.step(q, data[j])
            if dfa.accepts(q):
                out.append(j)
            elif dfa.dead(q):
                break
        return out[::-1]

    def scan(self, data: bytes) -> list[tuple[int, int, int]]:
        """(start, rule, end) in bytes, by start and rule."""
        rows, plain, q = self.rows, self.plain, self.start
        free = [0] * len(self.rules)
        found = []
        for i, b in enumerate(data):
            q = rows[q][b]
            if q >= plain:
                for k in self.hits[q]:
                    if i < free[k]:
                        continue
                    ends_here = self._starts(self.back[k], data, free[k], i)
                    if not ends_here:
                        continue
                    for s in self._starts(self.alive[k], data, free[k], i):
                        if s > ends_here[0]:
                            break
                        if got := self._longest(k, data, s):
                            first, e = got
                            if e - first + 1 >= self.rules[k].min_tail and e - s >= self.rules[k].min_len:
                                found.append((s, k, e))
                            free[k] = e
                            break
        return sorted(found)

    def spans(self, text: str) -> list[tuple[str, int, int]]:
        """(kind, start, end) in code points."""
        data = text.encode("utf-8", "surrogatepass")
        found = self.scan(data)
        if found and len(data) != len(text):
            at = {}
            last, chars = 0, 0
            for p in sorted({p for s, _, e in found for p in (s, e)}):
                chars += len(data[last:p].decode("utf-8", "surrogatepass"))
                at[p], last = chars, p
            found = [(at[s], k, at[e]) for s, k, e in found]
        return [(self.rules[k].kind, s, e) for s, k, e in found]


@lru_cache(4)
def scanner(rules: tuple[Rule, ...]) -> Scanner:
    """Compiled once in each Python worker."""
    return Scanner(rules)


_SPAN = pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())])


def scan_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rules: tuple[Rule, ...] = BASE_RULES + MORE_RULES) -> DataFrame:
    """One row per document: the id and ``spans``, an array of (kind, start, end) by start and rule order."""
    bounded_batches(docs.sparkSession)
    scanner(rules)  # a bad rule fails here, not on an executor
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches):
        spans = scanner(rules).spans
        for batch in batches:
            texts = batch.column(1)
            out = []
            for i in range(len(texts)):
                t = texts[i].as_py()
                out.append([{"kind": k, "start": s, "end": e} for k, s, e in spans(t)] if t else [])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.list_(_SPAN))], ["id", "spans"])

    return (
        docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
        .mapInArrow(run, f"id {kind}, spans array<struct<kind:string,start:bigint,end:bigint>>")
        .withColumnRenamed("id", id_col)
    )


def redact(text: str, spans, mark: str = "[secret]") -> str:
    """The text with overlapping spans joined and replaced."""
    out, last = [], 0
    for s, e in sorted((s["start"], s["end"]) for s in spans):
        if s >= last:
            out += [text[last:s], mark]
        last = max(last, e)
    return "".join([*out, text[last:]])


def _line(spans):
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")


def op2_secret_scans(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    base = [r.kind for r in BASE_RULES]
    n = lambda kind: F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    return scan_secrets(docs).select(
        "doc_id",
        *map(n, base),
        F.sha2(F.encode(_line(F.filter("spans", lambda s: s["kind"].isin(base))), "UTF-8"), 256).alias("base_sha256"),
        _line(F.col("spans")).alias("spans"),
    )
