"""Queries over the given tables, one for each method, baseline, measure and experiment, and their SQL."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from textfactor.functions import kernels as K
from textfactor.functions import sql as sql_surface
from textfactor.operators import arrays, coding, compact, decode, experiments, factorize, graph, measures, reuse
from textfactor.operators.global_text import GlobalText
from textfactor.sources import corpus
from textfactor.sources.io import read_table, read_texts
from textfactor.streaming import streams

QUERIES: dict = {}
SQL: dict[str, str] = {}

#: SQL of the text tables as (text_id, text)
SRC = {
    "benchmark": "SELECT item_id AS text_id, coalesce(text, '') AS text FROM benchmark",
    "documents": "SELECT doc_id AS text_id, coalesce(text, '') AS text FROM documents",
    "pages": "SELECT page_id AS text_id, coalesce(html, '') AS text FROM pages",
    "conversations": "SELECT conv_id * 1000 + turn AS text_id, coalesce(text, '') AS text FROM conversations",
}
LETTERS_SQL = (
    "SELECT 0 AS text_id, string_agg(substr('ACGT', quarter(l_shipdate), 1), '' ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate) AS text FROM lineitem"
)


def query(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return put


def _arrays_sql(src: str, longest: int = 1_000_000) -> str:
    """Tables up to ``a(text_id, t, pos, isa, phi, plcp)``; the sentinel is a control character. ``longest`` bounds the work
    for a repeat; it has to be above the longest one of the table."""
    return f"""c AS (SELECT text_id, text || chr(1) AS t FROM ({src})),
p AS (SELECT text_id, t, unnest(range(1, length(t) + 1)) AS pos FROM c),
s AS (SELECT *, row_number() OVER (PARTITION BY text_id ORDER BY substr(t, pos)) AS isa FROM p),
f AS (SELECT *, coalesce(lag(pos) OVER (PARTITION BY text_id ORDER BY isa), pos) AS phi FROM s),
a AS MATERIALIZED (SELECT *, CASE WHEN phi = pos THEN 0 ELSE coalesce(list_max(list_filter(range(1, least({longest}, length(t) - greatest(pos, phi) + 1) + 1),
  lambda k: substr(t, pos, k) = substr(t, phi, k))), 0) END AS plcp FROM f)"""


def _steps_sql(src: str) -> str:
    return f"""{_arrays_sql(src)},
r AS (SELECT text_id, pos, plcp, pos + plcp AS reach, lag(plcp) OVER w AS before, lag(pos + plcp) OVER w AS last FROM a WINDOW w AS (PARTITION BY text_id ORDER BY pos))"""


def _factors_sql(src: str, min_len: int, longest: int = 1_000_000, tie: str = "a.pos") -> str:
    """``fac(text_id, dst, len, src)`` by splitting segments at their highest value, of equal ones that with the least ``tie``."""
    best = f"""SELECT g.text_id, g.lo, g.hi, max(least(a.plcp, g.hi - a.pos)) AS len,
    arg_max(a.pos, least(a.plcp, g.hi - a.pos) * 100000000000 - ({tie})) AS dst
    FROM {{seg}} g JOIN a ON a.text_id = g.text_id AND a.pos >= g.lo AND a.pos < g.hi GROUP BY g.text_id, g.lo, g.hi"""
    return f"""WITH RECURSIVE {_arrays_sql(src, longest)},
seg AS (SELECT text_id, CAST(1 AS BIGINT) AS lo, CAST(length(t) AS BIGINT) AS hi FROM c
  UNION ALL
  SELECT b.text_id, CASE side WHEN 0 THEN b.lo ELSE b.dst + b.len END, CASE side WHEN 0 THEN b.dst ELSE b.hi END
  FROM ({best.format(seg="seg")}) b, (VALUES (0), (1)) v(side) WHERE b.len >= {min_len}),
fac AS (SELECT b.text_id, b.dst, b.len, a.phi AS src FROM ({best.format(seg="seg")}) b JOIN a ON a.text_id = b.text_id AND a.pos = b.dst WHERE b.len >= {min_len})"""


def _uni_sql(src: str, min_len: int = 2) -> str:
    """``phrase(text_id, pos, n)`` of the greedy parse with earlier sources."""
    return f"""WITH RECURSIVE c AS (SELECT text_id, text AS t FROM ({src})),
p AS (SELECT text_id, t, unnest(range(1, length(t) + 1)) AS pos FROM c),
l AS (SELECT text_id, pos, coalesce(list_max(list_filter(range(1, length(t) - pos + 2), lambda k: strpos(t, substr(t, pos, k)) < pos)), 0) AS lpf FROM p),
j AS (SELECT text_id, pos, lpf, CASE WHEN lpf >= {min_len} THEN lpf ELSE 1 END AS n FROM l),
phrase AS (SELECT text_id, pos, n FROM j WHERE pos = 1 UNION ALL
  SELECT j.text_id, j.pos, j.n FROM phrase JOIN j ON j.text_id = phrase.text_id AND j.pos = phrase.pos + phrase.n)"""


def _md5_sql(table: str) -> str:
    return f"SELECT text_id, md5(text) AS digest FROM ({SRC[table]})"


def _digest(texts: DataFrame, decoded: DataFrame) -> DataFrame:
    """Decoded texts as digests; texts without any factor are empty."""
    return texts.select("text_id").join(decoded, "text_id", "left").select("text_id", F.md5(F.coalesce("text", F.lit(""))).alias("digest"))


def _coded(texts: DataFrame, min_len: int = 2) -> DataFrame:
    """A coding written once: loops over it read files, not its making."""
    from textfactor.plans.scratch import Scratch

    return Scratch(texts.sparkSession, "coding").save(coding.encode(factorize.factorize(texts, min_len), texts), "coding")


# ---- arrays --------------------------------------------------------------------------------------------------------
B = SRC["benchmark"]


@query("arr_suffix_array", f"WITH {_arrays_sql(B)} SELECT text_id, isa AS rank, pos FROM a")
def _(spark, sf):
    return arrays.suffix_array(read_texts(spark, sf, "benchmark"))


@query("arr_inverse", f"WITH {_arrays_sql(B)} SELECT text_id, pos, isa FROM a")
def _(spark, sf):
    return arrays.inverse(arrays.suffix_array(read_texts(spark, sf, "benchmark")))


@query("arr_phi", f"WITH {_arrays_sql(B)} SELECT text_id, pos, phi FROM a")
def _(spark, sf):
    return arrays.phi_of(arrays.suffix_array(read_texts(spark, sf, "benchmark")))


@query("arr_bwt", f"WITH {_arrays_sql(B)} SELECT text_id, isa AS rank, CASE WHEN pos = 1 THEN '$' ELSE substr(t, pos - 1, 1) END AS bwt FROM a")
def _(spark, sf):
    return arrays.bwt(read_texts(spark, sf, "benchmark"))


@query("arr_lcp", f"WITH {_arrays_sql(B)} SELECT text_id, isa AS rank, plcp AS lcp FROM a")
def _(spark, sf):
    return arrays.lcp(arrays.build_arrays(read_texts(spark, sf, "benchmark"), {"isa", "plcp"}))


@query("arr_plcp", f"WITH {_arrays_sql(B)} SELECT text_id, pos, plcp FROM a")
def _(spark, sf):
    return arrays.build_arrays(read_texts(spark, sf, "benchmark"), {"plcp"})


@query("arr_plcp_phi_scan", SQL["arr_plcp"])
def _(spark, sf):
    return arrays.plcp_phi_scan(read_texts(spark, sf, "benchmark"))


@query("arr_lpf", _uni_sql(B) + " SELECT text_id, pos, lpf FROM j")
def _(spark, sf):
    return arrays.lpf(read_texts(spark, sf, "benchmark")).select("text_id", "pos", "lpf")


@query("arr_reach_steps", f"WITH {_steps_sql(B)} SELECT text_id, pos, reach FROM r WHERE plcp > 0 AND reach > coalesce(last, 1)")
def _(spark, sf):
    return arrays.reach_steps(read_texts(spark, sf, "benchmark"))


@query(
    "arr_bwt_runs",
    f"""WITH {_arrays_sql(B)}, b AS (SELECT text_id, isa, CASE WHEN pos = 1 THEN '$' ELSE substr(t, pos - 1, 1) END AS x FROM a),
    d AS (SELECT text_id, lag(x) OVER (PARTITION BY text_id ORDER BY isa) IS DISTINCT FROM x AS fresh FROM b)
    SELECT text_id, count(*) FILTER (fresh) AS runs FROM d GROUP BY text_id""",
)
def _(spark, sf):
    return arrays.bwt_runs(arrays.bwt(read_texts(spark, sf, "benchmark")))


ONE = "SELECT 0 AS text_id, string_agg(text || chr(10), '' ORDER BY text_id) AS text FROM ({})"


def _global(spark, sf, table="benchmark") -> GlobalText:
    return GlobalText(corpus.single_text(read_texts(spark, sf, table)))


@query("arr_single_text_sa", f"WITH {_arrays_sql(ONE.format(B), 1000)} SELECT isa AS rank, pos FROM a WHERE isa > 1")
def _(spark, sf):
    return _global(spark, sf).suffix_array()


@query("arr_single_text_plcp", f"WITH {_arrays_sql(ONE.format(B), 1000)} SELECT pos, plcp FROM a WHERE isa > 1")
def _(spark, sf):
    return _global(spark, sf).plcp()


@query(
    "arr_single_text_irreducible",
    f"""WITH {_arrays_sql(ONE.format(B), 1000)} SELECT pos, phi, plcp FROM a
    WHERE isa > 2 AND (pos = 1 OR phi = 1 OR substr(t, pos - 1, 1) <> substr(t, phi - 1, 1))""",
)
def _(spark, sf):
    return _global(spark, sf).irreducible()


@query(
    "peaks_flags",
    f"""WITH {_steps_sql(B)}, k AS (SELECT text_id, pos, plcp FROM r WHERE plcp >= 2 AND (pos = 1 OR before < plcp)),
    i AS (SELECT k.*, NOT EXISTS (SELECT 1 FROM a WHERE a.text_id = k.text_id AND a.pos < k.pos AND k.pos < a.pos + a.plcp AND a.plcp >= k.plcp) AS is_interesting FROM k)
    SELECT i.text_id, i.pos, i.plcp, i.is_interesting,
    i.is_interesting AND NOT EXISTS (SELECT 1 FROM i o WHERE o.text_id = i.text_id AND o.is_interesting AND o.pos > i.pos AND o.pos < i.pos + i.plcp) AS is_maximal FROM i""",
)
def _(spark, sf):
    return arrays.peaks(read_texts(spark, sf, "benchmark"))


@query(
    "islands",
    f"""WITH {_steps_sql(B)}, k AS (SELECT text_id, pos, reach FROM r WHERE plcp >= 2 AND reach > coalesce(last, 1)),
    o AS (SELECT *, CASE WHEN pos >= lag(reach) OVER w THEN 1 WHEN lag(reach) OVER w IS NULL THEN 1 ELSE 0 END AS opens FROM k WINDOW w AS (PARTITION BY text_id ORDER BY pos)),
    n AS (SELECT *, CAST(sum(opens) OVER (PARTITION BY text_id ORDER BY pos) AS BIGINT) AS island FROM o)
    SELECT text_id, island, min(pos) AS low, max(reach) - 1 AS high, count(*) AS steps FROM n GROUP BY text_id, island""",
)
def _(spark, sf):
    return arrays.islands(arrays.reach_steps(read_texts(spark, sf, "benchmark")))


@query(
    "longest_repeat",
    f"""WITH {_arrays_sql(B)} SELECT text_id, arg_max(pos, plcp * 1000000 - pos) AS pos, arg_max(phi, plcp * 1000000 - pos) AS src, max(plcp) AS len
    FROM a GROUP BY text_id HAVING max(plcp) > 0""",
)
def _(spark, sf):
    return arrays.longest_repeat(arrays.build_arrays(read_texts(spark, sf, "benchmark"), {"phi", "plcp"}))


@query("longest_repeat_top10", f"WITH {_arrays_sql(B)} SELECT text_id, max(plcp) AS len FROM a GROUP BY text_id ORDER BY len DESC, text_id LIMIT 10")
def _(spark, sf):
    return arrays.top_repeats(arrays.build_arrays(read_texts(spark, sf, "benchmark"), {"phi", "plcp"}), 10).select("text_id", "len")


# ---- factorizations ------------------------------------------------------------------------------------------------
_LL2 = _factors_sql(B, 2) + " SELECT text_id, dst, len, src FROM fac"

for _method in factorize.METHODS:
    query(f"ll_factors_{_method}", _LL2)(lambda spark, sf, m=_method: factorize.factorize(read_texts(spark, sf, "benchmark"), 2, m))


@query("ll_factors_min3", _factors_sql(B, 3) + " SELECT text_id, dst, len, src FROM fac")
def _(spark, sf):
    return factorize.factorize(read_texts(spark, sf, "benchmark"), 3)


@query("ll_single_text", _factors_sql(ONE.format(B), 2, 1000) + " SELECT dst, len, src FROM fac")
def _(spark, sf):
    return _global(spark, sf).factors(2)


@query("uni_single_text", f"""WITH RECURSIVE phrase AS (SELECT text AS t, CAST(1 AS BIGINT) AS pos, CAST(1 AS BIGINT) AS n FROM ({ONE.format(B)}) UNION ALL
    SELECT t, q, coalesce(list_max(list_filter(range(2, least(1000, length(t) - q + 1) + 1), lambda k: strpos(substr(t, 1, q + k - 2), substr(t, q, k)) > 0)), 1)
    FROM (SELECT t, pos + n AS q FROM phrase) WHERE q <= length(t)) SELECT pos AS dst, n AS len FROM phrase WHERE n >= 2""")
def _(spark, sf):
    return _global(spark, sf).unidirectional(2).select("dst", "len")


@query("uni_factors", _uni_sql(B) + " SELECT text_id, pos AS dst, n AS len FROM phrase WHERE n >= 2")
def _(spark, sf):
    return factorize.parse_unidirectional(read_texts(spark, sf, "benchmark")).select("text_id", "dst", "len")


@query("uni_factors_scan", SQL["uni_factors"])
def _(spark, sf):
    return factorize.parse_unidirectional(read_texts(spark, sf, "benchmark"), method="scan", block=64).select("text_id", "dst", "len")


@query("uni_factors_memory", SQL["uni_factors"])
def _(spark, sf):
    return factorize.parse_unidirectional(read_texts(spark, sf, "benchmark"), method="memory").select("text_id", "dst", "len")


@query("uni_scan_conversations", "SELECT count(*) AS texts, CAST(0 AS BIGINT) AS differing FROM (" + SRC["conversations"] + ")")
def _(spark, sf):
    """Texts on which the scan by blocks and the array of previous factors give another number of references or factors."""
    t = read_texts(spark, sf, "conversations")
    a, b = (coding.reference_counts(factorize.parse_unidirectional(t, method=m, block=256), t) for m in ("scan", "lpf"))
    b = b.select("text_id", F.col("n_refs").alias("r"), F.col("n_factors").alias("f"))
    return a.join(b, "text_id").agg(F.count("*").alias("texts"), F.count_if((F.col("n_refs") != F.col("r")) | (F.col("n_factors") != F.col("f"))).alias("differing"))


_TIES = {"rightmost": "-a.pos", "hash": "((a.pos - 1) * 2654435761 + 12345) % 2147483647", "stable": "(a.pos - 1) % 64 * (length(a.t) - 1) + a.pos - 1"}
for _tie, _rank in _TIES.items():
    query(f"al_factors_{_tie}", _factors_sql(B, 2, tie=_rank) + " SELECT text_id, dst, len, src FROM fac")(
        lambda spark, sf, t=_tie: factorize.factorize(read_texts(spark, sf, "benchmark"), 2, "heap", tie=t)
    )


@query("bwt_parse_literals", f"""WITH {_arrays_sql(B)}, o AS (SELECT text_id, isa, CASE WHEN pos > 1 THEN substr(t, pos - 1, 1) END AS x FROM a WHERE isa > 1),
    k AS (SELECT text_id, x = lag(x) OVER (PARTITION BY text_id ORDER BY isa) AS copied FROM o)
    SELECT text_id, count(*) - count(*) FILTER (copied) AS n_literal_chars FROM k GROUP BY text_id""")
def _(spark, sf):
    t = read_texts(spark, sf, "benchmark")
    return coding.reference_counts(factorize.parse_bwt_runs(t), t).select("text_id", "n_literal_chars")


@query("window_factors", f"""WITH RECURSIVE c AS (SELECT text_id, text AS t FROM ({B})),
    p AS (SELECT text_id, t, unnest(range(1, length(t) + 1)) AS pos FROM c),
    l AS (SELECT text_id, pos, coalesce(list_max(list_filter(range(3, length(t) - pos + 2), lambda k: strpos(substr(t, greatest(1, pos - 64), pos - 1 - greatest(1, pos - 64) + k), substr(t, pos, k)) > 0)), 1) AS n FROM p),
    j AS (SELECT text_id, pos, CASE WHEN pos = 1 THEN 1 ELSE n END AS n FROM l),
    phrase AS (SELECT text_id, pos, n FROM j WHERE pos = 1 UNION ALL SELECT j.text_id, j.pos, j.n FROM phrase JOIN j ON j.text_id = phrase.text_id AND j.pos = phrase.pos + phrase.n)
    SELECT text_id, pos AS dst, n AS len FROM phrase WHERE n >= 3""")
def _(spark, sf):
    return factorize.parse_window(read_texts(spark, sf, "benchmark"), 64).select("text_id", "dst", "len")


@query("end_aligned_factors", f"""WITH RECURSIVE c AS (SELECT text_id, text AS t FROM ({B})),
    phrase AS (SELECT text_id, t, CAST(1 AS BIGINT) AS pos, CAST(1 AS BIGINT) AS n, CAST([1] AS BIGINT[]) AS ends FROM c WHERE length(t) > 0 UNION ALL
      SELECT text_id, t, q, k, list_append(ends, q + k - 1) FROM (SELECT text_id, t, q, ends,
        coalesce(list_max(list_filter(range(2, least(q, length(t) - q + 2)), lambda k: len(list_filter(ends, lambda e: e >= k AND substr(t, e - k + 1, k) = substr(t, q, k))) > 0)), 1) AS k
        FROM (SELECT *, pos + n AS q FROM phrase) WHERE q <= length(t)))
    SELECT text_id, pos AS dst, n AS len FROM phrase WHERE n >= 2""")
def _(spark, sf):
    return factorize.parse_end_aligned(read_texts(spark, sf, "benchmark")).select("text_id", "dst", "len")


@query("uni_sources_ok", _uni_sql(B) + " SELECT text_id, count(*) AS refs, count(*) AS equal, true AS unidirectional FROM phrase WHERE n >= 2 GROUP BY text_id")
def _(spark, sf):
    t = read_texts(spark, sf, "benchmark")
    r = factorize.parse_unidirectional(t)
    return coding.check_occurrences(r, t).join(coding.is_unidirectional(r), "text_id")


@query("factor_counts_bidirectional", _factors_sql(B, 2) + """ SELECT c.text_id, CAST(length(t) - 1 AS BIGINT) AS n, count(dst) AS n_refs,
    CAST(length(t) - 1 - coalesce(sum(len), 0) AS BIGINT) AS n_literal_chars, CAST(length(t) - 1 - coalesce(sum(len), 0) + count(dst) AS BIGINT) AS n_factors
    FROM c LEFT JOIN fac USING (text_id) GROUP BY c.text_id, t""")
def _(spark, sf):
    t = read_texts(spark, sf, "benchmark")
    return coding.reference_counts(factorize.factorize(t), t)


@query("factor_counts_unidirectional", _uni_sql(B) + """ SELECT c.text_id, CAST(length(t) AS BIGINT) AS n, count(*) FILTER (n >= 2) AS n_refs,
    count(*) FILTER (n = 1) AS n_literal_chars, count(pos) AS n_factors FROM c LEFT JOIN phrase USING (text_id) GROUP BY c.text_id, t""")
def _(spark, sf):
    t = read_texts(spark, sf, "benchmark")
    return coding.reference_counts(factorize.parse_unidirectional(t), t)


@query("coding_runs", _factors_sql(B, 2) + """, g AS (SELECT text_id, dst, len FROM fac UNION ALL SELECT text_id, 0, 1 FROM c),
    h AS (SELECT g.text_id, g.dst + g.len AS dst, coalesce(lead(g.dst) OVER (PARTITION BY g.text_id ORDER BY g.dst), length(t)) - g.dst - g.len AS len, t FROM g JOIN c USING (text_id))
    SELECT text_id, CAST(dst AS BIGINT) AS dst, CAST(len AS BIGINT) AS len, substr(t, dst, len) AS literal FROM h WHERE len > 0""")
def _(spark, sf):
    t = read_texts(spark, sf, "benchmark")
    return coding.encode(factorize.factorize(t), t).where("src IS NULL").select("text_id", "dst", "len", "literal")


@query("coding_literal_chars", _factors_sql(B, 2) + """, q AS (SELECT text_id, t, unnest(range(1, length(t))) AS pos FROM c)
    SELECT q.text_id, q.pos AS dst, substr(t, q.pos, 1) AS literal FROM q
    WHERE NOT EXISTS (SELECT 1 FROM fac WHERE fac.text_id = q.text_id AND q.pos >= fac.dst AND q.pos < fac.dst + fac.len)""")
def _(spark, sf):
    t = read_texts(spark, sf, "benchmark")
    return coding.encode(factorize.factorize(t), t, "char").where("src IS NULL").select("text_id", "dst", "literal")


def _valid_sql(table: str) -> str:
    return f"SELECT text_id, true AS tiled, true AS long_enough, true AS in_range, true AS no_self, true AS resolves FROM ({SRC[table]})"


for _table in ("documents", "pages", "conversations"):
    query(f"coding_valid_{_table}", _valid_sql(_table))(
        lambda spark, sf, t=_table: (lambda x: coding.validate(coding.encode(factorize.factorize(x), x), x))(read_texts(spark, sf, t))
    )
    query(f"ll_roundtrip_{_table}", _md5_sql(_table))(
        lambda spark, sf, t=_table: (lambda x: _digest(x, decode.decode_memory(coding.encode(factorize.factorize(x), x))))(read_texts(spark, sf, t))
    )


@query("coding_nested", _md5_sql("conversations"))
def _(spark, sf):
    t = read_texts(spark, sf, "conversations")
    flat = coding.explode_coding(coding.collect_coding(coding.encode(factorize.factorize(t, 3), t)))
    return _digest(t, decode.decode_memory(flat))


@query("coding_occurrences", f"SELECT count(*) AS texts, true AS all_equal FROM ({SRC['documents']})")
def _(spark, sf):
    t = read_texts(spark, sf, "documents")
    c = coding.check_occurrences(factorize.factorize(t), t)
    return t.select("text_id").join(c, "text_id", "left").agg(
        F.count("*").alias("texts"), F.bool_and(F.coalesce("refs", F.lit(0)) == F.coalesce("equal", F.lit(0))).alias("all_equal")
    )


@query("coding_bytes")
def _(spark, sf):
    t = read_texts(spark, sf, "documents")
    per = coding.coding_bytes(coding.encode(factorize.factorize(t, 3), t)).join(t.select("text_id", F.octet_length("text").alias("raw")), "text_id")
    return per.agg(F.sum("raw").alias("raw_bytes"), F.sum("bytes").alias("coded_bytes"))


@query("coding_summary")
def _(spark, sf):
    t = read_texts(spark, sf, "documents")
    return coding.summary(coding.encode(factorize.factorize(t), t))


_PARSES = {
    "al_roundtrip": lambda t: factorize.factorize(t, 2, "heap", tie="hash"),
    "al_rightmost_roundtrip": lambda t: factorize.factorize(t, 2, "heap", tie="rightmost"),
    "al_stable_roundtrip": lambda t: factorize.factorize(t, 2, "heap", tie="stable"),
    "uni_memory_roundtrip": lambda t: factorize.parse_unidirectional(t),
    "end_aligned_roundtrip": lambda t: factorize.parse_end_aligned(t),
    "window_roundtrip": lambda t: factorize.parse_window(t, 256),
    "bwt_parse_roundtrip": lambda t: factorize.parse_bwt_runs(t),
}
for _name, _parse in _PARSES.items():
    query(_name, _md5_sql("conversations"))(
        lambda spark, sf, p=_parse: (lambda x: _digest(x, decode.decode_memory(coding.encode(p(x), x))))(read_texts(spark, sf, "conversations"))
    )


# ---- graph, compaction, decoders -----------------------------------------------------------------------------------
def _edges_sql() -> str:
    return _factors_sql(B, 2) + """, g AS (SELECT text_id, dst, len, src FROM fac UNION ALL
      SELECT text_id, dst, len, NULL FROM (SELECT z.text_id, z.dst + z.len AS dst, coalesce(lead(z.dst) OVER (PARTITION BY z.text_id ORDER BY z.dst), length(t)) - z.dst - z.len AS len
        FROM (SELECT text_id, dst, len FROM fac UNION ALL SELECT text_id, 0, 1 FROM c) z JOIN c USING (text_id)) WHERE len > 0),
    n AS (SELECT *, row_number() OVER (PARTITION BY text_id ORDER BY dst) AS no FROM g),
    e AS (SELECT k.text_id, k.no AS child_no, p.no AS parent_no, greatest(k.src, p.dst) AS ov_start, least(k.src + k.len, p.dst + p.len) - greatest(k.src, p.dst) AS ov_len,
      k.src >= p.dst AND k.src + k.len <= p.dst + p.len AS contained FROM n k JOIN n p ON k.text_id = p.text_id AND k.src < p.dst + p.len AND p.dst < k.src + k.len)"""


@query("dep_edges", _edges_sql() + " SELECT text_id, child_no, parent_no, CAST(ov_start AS BIGINT) AS ov_start, CAST(ov_len AS BIGINT) AS ov_len, contained FROM e")
def _(spark, sf):
    return graph.dependency_edges(_coded(read_texts(spark, sf, "benchmark")))


@query("dep_multi", _edges_sql() + " SELECT text_id, child_no, count(*) AS parents FROM e GROUP BY text_id, child_no HAVING count(*) > 1")
def _(spark, sf):
    return graph.multi_dependent(graph.dependency_edges(_coded(read_texts(spark, sf, "benchmark"))))


@query("dep_first_parent", _edges_sql() + " SELECT text_id, child_no, arg_min(parent_no, ov_start) AS parent_no, arg_min(contained, ov_start) AS contained FROM e GROUP BY text_id, child_no")
def _(spark, sf):
    return graph.first_parent(graph.dependency_edges(_coded(read_texts(spark, sf, "benchmark"))))


_PARENTS = """, q AS (SELECT text_id, t, unnest(range(1, length(t))) AS pos FROM c),
  up AS (SELECT q.text_id, q.pos, fac.src + q.pos - fac.dst AS parent FROM q LEFT JOIN fac ON fac.text_id = q.text_id AND q.pos >= fac.dst AND q.pos < fac.dst + fac.len),
  walk AS (SELECT text_id, pos, parent AS at, CASE WHEN parent IS NULL THEN 0 ELSE 1 END AS hops FROM up UNION ALL
    SELECT walk.text_id, walk.pos, up.parent, walk.hops + 1 FROM walk JOIN up ON up.text_id = walk.text_id AND up.pos = walk.at WHERE up.parent IS NOT NULL)"""


@query("dep_depth", _factors_sql(B, 2) + _PARENTS + " SELECT text_id, CAST(max(hops) AS BIGINT) AS depth FROM walk GROUP BY text_id")
def _(spark, sf):
    return graph.depths(_coded(read_texts(spark, sf, "benchmark"))).select("text_id", "depth")


@query("dep_factor_cycles")
def _(spark, sf):
    return graph.depths(_coded(read_texts(spark, sf, "conversations")))


@query("dep_tree_hops")
def _(spark, sf):
    return compact.tree_depths(_coded(read_texts(spark, sf, "conversations")))


_DECODERS = {
    "jump_decode": lambda f: decode.decode_jump(f),
    "jump_decode_fixed": lambda f: decode.decode_jump(f, double=False),
    "jump_decode_unmerged": lambda f: decode.decode_jump(f, merge=False),
    "char_decode": lambda f: decode.decode_chars(f),
    "char_decode_direct_first": lambda f: decode.decode_chars(f, direct_first=True),
    "forest_compaction_roundtrip": lambda f: decode.decode_memory(compact.compact(f)),
    "layered_compaction_roundtrip": lambda f: decode.decode_memory(compact.compact(f, through_multi=True)),
    "layered_compaction_by_layers": lambda f: decode.decode_memory(compact.compact_layers(f, through_multi=True)),
    "compaction_then_jump": lambda f: decode.decode_jump(compact.compact(f, through_multi=True)),
}
for _name, _dec in _DECODERS.items():
    query(_name, _md5_sql("benchmark"))(lambda spark, sf, d=_dec: (lambda x: _digest(x, d(_coded(x))))(read_texts(spark, sf, "benchmark")))


@query("jump_decode_conversations", _md5_sql("conversations"))
def _(spark, sf):
    t = read_texts(spark, sf, "conversations")
    return _digest(t, decode.decode_jump(_coded(t, 8)))


@query("char_decode_unidirectional", _md5_sql("benchmark"))
def _(spark, sf):
    t = read_texts(spark, sf, "benchmark")
    return _digest(t, decode.decode_chars(coding.encode(factorize.parse_unidirectional(t), t)))


@query("copies_decode", _md5_sql("benchmark"))
def _(spark, sf):
    t = read_texts(spark, sf, "benchmark")
    return _digest(t, decode.decode_copies(_coded(t))[0])


@query("jump_order", _factors_sql(B, 2) + _PARENTS + """, d AS (SELECT text_id, max(hops) AS depth FROM walk GROUP BY text_id)
    SELECT text_id, CAST(ceil(log2(greatest(depth, 1))) AS BIGINT) AS parallel, true AS in_order_no_more FROM d""")
def _(spark, sf):
    r = decode.order_of_jumps(_coded(read_texts(spark, sf, "benchmark")))
    return r.select("text_id", "parallel", (F.col("in_order") <= F.col("parallel")).alias("in_order_no_more"))


def _shape(f: DataFrame) -> DataFrame:
    """Borders and literals of each text's coding as one digest."""
    part = F.concat_ws(":", "dst", "len", F.when(F.col("src").isNull(), F.col("literal")))
    return f.groupBy("text_id").agg(F.md5(F.array_join(F.array_sort(F.collect_list(part)), ",")).alias("shape"))


for _kind, _multi in (("forest", False), ("layered", True)):

    @query(f"compaction_gain_{_kind}", _factors_sql(B, 2) + _PARENTS + " SELECT text_id, CAST(max(hops) AS BIGINT) AS depth, true AS no_deeper, true AS same_shape FROM walk GROUP BY text_id")
    def _(spark, sf, multi=_multi):
        f = _coded(read_texts(spark, sf, "benchmark"))
        g = compact.compact(f, through_multi=multi)
        after = graph.depths(g).select("text_id", F.col("depth").alias("after")).join(_shape(g).withColumnRenamed("shape", "other"), "text_id")
        return graph.depths(f).join(_shape(f), "text_id").join(after, "text_id").select(
            "text_id", "depth", (F.col("after") <= F.col("depth")).alias("no_deeper"), (F.col("shape") == F.col("other")).alias("same_shape")
        )


@query("compaction_report")
def _(spark, sf):
    """Depth of the codings, rounds and seconds of the join decoder without and with compaction."""
    import time

    f = _coded(read_texts(spark, sf, "benchmark"))
    rows = []
    for name, g in (("plain", f), ("forest", compact.compact(f)), ("layered", compact.compact(f, through_multi=True))):
        d = graph.depths(g).agg(F.max("depth"), F.avg("mean_depth")).first()
        a = time.perf_counter()
        rounds = decode.jump(g)[1]
        rows.append((name, d[0], float(d[1]), len(rounds), max((x["pieces"] for x in rounds), default=0), time.perf_counter() - a))
    return spark.createDataFrame(rows, "compaction string, depth long, mean_depth double, rounds int, peak_pieces long, seconds double")


@query("uni_decode", _md5_sql("documents"))
def _(spark, sf):
    t = read_texts(spark, sf, "documents")
    return _digest(t, decode.decode_unidirectional(coding.encode(factorize.parse_unidirectional(t), t)))


@query("extract_range", f"SELECT text_id, substr(text, 21, 40) AS text FROM ({B}) WHERE length(text) > 20")
def _(spark, sf):
    return decode.extract(_coded(read_texts(spark, sf, "benchmark")), 21, 60)


def _single_coding(spark, blocks: DataFrame, min_len: int) -> DataFrame:
    """The coding of one text in blocks, without any row or task that holds the text."""
    from textfactor.plans.scratch import Scratch

    f = coding.encode_blocks(GlobalText(blocks).factors(min_len), blocks)
    return Scratch(spark, "single").save(f.withColumn("text_id", F.lit(0).cast("long")), "coding")


def _single_digests(spark, f: DataFrame, cell: int = 1 << 14) -> DataFrame:
    """Digests of the decoded text by cells of ``cell`` symbols."""
    return decode.cell_digests(decode.decoded_pieces(decode.jump(f)[0], f), cell)


def _cells_sql(src: str, cell: int = 1 << 14) -> str:
    return f"""WITH w AS ({ONE.format(src)}), i AS (SELECT text, CAST(unnest(range(0, (length(text) - 1) // {cell} + 1)) AS BIGINT) AS cell FROM w)
    SELECT cell, md5(substr(text, cell * {cell} + 1, {cell})) AS digest FROM i"""


for _table, _min in (("benchmark", 2), ("conversations", 2), ("pages", 4)):
    query(f"single_text_roundtrip_{_table}", _cells_sql(SRC[_table]))(
        lambda spark, sf, t=_table, m=_min: _single_digests(spark, _single_coding(spark, corpus.single_text(read_texts(spark, sf, t)), m))
    )


@query("single_text_roundtrip_letters", _cells_sql(LETTERS_SQL).replace("text || chr(10)", "text"))
def _(spark, sf):
    return _single_digests(spark, _single_coding(spark, corpus.single_text(corpus.lineitem_letters(read_table(spark, sf, "lineitem")), ""), 2))


@query("uni_single_text_letters")
def _(spark, sf):
    """References, coverage and factors of both schemes for the letters as one text over the cluster, and of the kernels in one task."""
    t = corpus.lineitem_letters(read_table(spark, sf, "lineitem"))
    g = GlobalText(corpus.single_text(t, ""))
    whole = corpus.lineitem_letters_whole(read_table(spark, sf, "lineitem"))
    out = None
    for name, refs, again in (("bidirectional", g.factors(2), factorize.factorize(whole)), ("unidirectional", g.unidirectional(2), factorize.parse_unidirectional(whole))):
        for where, r in (("cluster", refs), ("task", again)):
            c = r.agg(F.count("*").alias("n_refs"), F.sum("len").alias("covered"), F.bit_xor(F.xxhash64("dst", "len")).alias("mark"))
            c = c.select(F.lit(name).alias("scheme"), F.lit(where).alias("where"), "*")
            out = c if out is None else out.unionByName(c)
    return out


@query("jump_rounds")
def _(spark, sf):
    return decode.jump_rounds(_coded(read_texts(spark, sf, "conversations"), 8))


@query("jump_rounds_by_variant")
def _(spark, sf):
    """Rounds and peak pieces with and without doubling, merging and compaction."""
    f = _coded(read_texts(spark, sf, "benchmark"))
    rows = []
    for name, g in (("plain", f), ("forest", compact.compact(f)), ("layered", compact.compact(f, through_multi=True))):
        for double in (True, False):
            for merge in (True, False):
                r = decode.jump(g, double, merge)[1]
                rows.append((name, double, merge, len(r), max((x["pieces"] for x in r), default=0)))
    return spark.createDataFrame(rows, "compaction string, doubling boolean, merging boolean, rounds int, peak_pieces long")


# ---- measures and experiments --------------------------------------------------------------------------------------
def _entropy_sql(src: str, k: int) -> str:
    return f"""WITH c AS ({src}), p AS (SELECT substr(text, i, {k}) AS ctx, substr(text, i + {k}, 1) AS sym FROM (SELECT text, unnest(range(1, length(text) - {k} + 1)) AS i FROM c)),
    n AS (SELECT ctx, sym, count(*) AS n FROM p GROUP BY ALL), m AS (SELECT ctx, sum(n) AS m, sum(n * log2(n)) AS s FROM n GROUP BY ctx)
    SELECT {k} AS k, (SELECT CAST(sum(length(text)) AS BIGINT) FROM c) AS symbols, round(sum(m * log2(m) - s) / (SELECT sum(length(text)) FROM c), 6) AS entropy FROM m"""


def _rounded(df: DataFrame) -> DataFrame:
    return df.withColumn("entropy", F.round("entropy", 6))


for _table in ("documents", "pages"):
    for _k in range(0, 8):
        query(f"entropy_{_table}_{_k}", _entropy_sql(SRC[_table], _k))(
            lambda spark, sf, t=_table, k=_k: _rounded(measures.empirical_entropy(read_texts(spark, sf, t), k))
        )
for _k in range(0, 8):
    # blocks are texts of their own here, as they are in the query
    query(f"entropy_letters_{_k}", _entropy_sql(
        "SELECT string_agg(x, '' ORDER BY i) AS text FROM (SELECT substr('ACGT', quarter(l_shipdate), 1) AS x, row_number() OVER (ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate) - 1 AS i FROM lineitem) GROUP BY i // 65536", _k))(
        lambda spark, sf, k=_k: _rounded(measures.empirical_entropy(corpus.lineitem_letters(read_table(spark, sf, "lineitem")), k))
    )
    query(f"entropy_letters_whole_{_k}", _entropy_sql(LETTERS_SQL, _k))(
        lambda spark, sf, k=_k: _rounded(measures.empirical_entropy(corpus.lineitem_letters_whole(read_table(spark, sf, "lineitem")), k))
    )


@query("alphabet_size", f"SELECT count(DISTINCT x) AS sigma FROM (SELECT unnest(string_split(text, '')) AS x FROM ({SRC['documents']})) WHERE x <> ''")
def _(spark, sf):
    return measures.alphabet_size(read_texts(spark, sf, "documents"))


@query("letters_text", "SELECT i // 65536 AS text_id, md5(string_agg(x, '' ORDER BY i)) AS digest FROM (SELECT substr('ACGT', quarter(l_shipdate), 1) AS x, row_number() OVER (ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate) - 1 AS i FROM lineitem) GROUP BY ALL")
def _(spark, sf):
    return corpus.lineitem_letters(read_table(spark, sf, "lineitem")).select("text_id", F.md5("text").alias("digest"))


def _block_digests(decoded: DataFrame) -> DataFrame:
    """A sequence is factorized and decoded as one text; its digests are taken block by block, as the SQL does."""
    return corpus.cut_text(decoded).select("text_id", F.md5("text").alias("digest"))


@query("letters_roundtrip", SQL["letters_text"])
def _(spark, sf):
    t = corpus.lineitem_letters_whole(read_table(spark, sf, "lineitem"))
    return _block_digests(decode.decode_memory(coding.encode(factorize.factorize(t), t)))


@query("letters_low_sigma_roundtrip", "SELECT i // 65536 AS text_id, md5(string_agg(x, '' ORDER BY i)) AS digest FROM (SELECT o_orderstatus AS x, row_number() OVER (ORDER BY o_orderkey) - 1 AS i FROM orders) GROUP BY ALL")
def _(spark, sf):
    t = corpus.shard_texts(corpus.symbol_text(read_table(spark, sf, "orders"), ["o_orderkey"], F.col("o_orderstatus")), 1 << 40, "")
    return _block_digests(decode.decode_memory(coding.encode(factorize.factorize(t, 5), t)))


@query("prefix_text", f"""WITH t AS (SELECT *, sum(length(text)) OVER (ORDER BY text_id) - length(text) AS start, sum(length(text)) OVER () AS n FROM ({SRC['documents']}))
    SELECT text_id, md5(substr(text, 1, CAST(n // 2 - start AS BIGINT))) AS digest FROM t WHERE start < n // 2""")
def _(spark, sf):
    t = read_texts(spark, sf, "documents")
    n = t.agg(F.sum(F.length("text"))).first()[0]
    return corpus.corpus_prefix(t, n // 2).select("text_id", F.md5("text").alias("digest"))


def _prefix_counts(spark, texts: DataFrame, schemes: bool = True) -> DataFrame:
    """Counts of both schemes on an eighth, a quarter, a half and all of a text table."""
    n = texts.agg(F.sum(F.length("text"))).first()[0]
    out = None
    for part in (8, 4, 2, 1):
        t = texts if part == 1 else corpus.corpus_prefix(texts, n // part)
        rows = measures.compare_schemes(t).withColumn("part", F.lit(1.0 / part))
        out = rows if out is None else out.unionByName(rows)
    return out


@query("prefix_counts_documents")
def _(spark, sf):
    return _prefix_counts(spark, read_texts(spark, sf, "documents"))


@query("prefix_counts_pages")
def _(spark, sf):
    return _prefix_counts(spark, read_texts(spark, sf, "pages"))


@query("prefix_counts_letters")
def _(spark, sf):
    return _prefix_counts(spark, corpus.lineitem_letters_whole(read_table(spark, sf, "lineitem")))


def _letters(spark, sf) -> DataFrame:
    return corpus.lineitem_letters(read_table(spark, sf, "lineitem"))


#: name -> (texts, what stands behind each of them in the single text)
_SINGLE = {
    "documents": (lambda spark, sf: read_texts(spark, sf, "documents"), "\n"),
    "pages": (lambda spark, sf: read_texts(spark, sf, "pages"), "\n"),
    "letters": (_letters, ""),
}
#: name -> minimum lengths
_LENGTHS = {"documents": [2, *range(3, 9)], "pages": [2, *range(3, 9)], "letters": [2, *range(7, 13), *range(17, 23)]}


def _parted(spark, sf, name: str, parts: tuple[int, ...] = experiments.PARTS) -> experiments.Prefixes:
    texts, sep = _SINGLE[name]
    return experiments.parted(texts(spark, sf), parts, sep)


for _name, _lengths in _LENGTHS.items():

    @query(f"single_prefix_counts_{_name}")
    def _(spark, sf, name=_name):
        """References and factors of both schemes on an eighth, a quarter, a half and all of one text."""
        return experiments.prefix_counts(_parted(spark, sf, name))

    @query(f"single_prefix_measures_{_name}")
    def _(spark, sf, name=_name):
        return experiments.prefix_measures(_parted(spark, sf, name), name, [2], "prefixes")

    @query(f"single_min_len_measures_{_name}")
    def _(spark, sf, name=_name, lengths=_lengths):
        return experiments.prefix_measures(_parted(spark, sf, name, (4, 2, 1)), name, lengths[1:], "min_len", 1)


@query("single_prefix_text", """WITH w AS (SELECT string_agg(text || chr(10), '' ORDER BY text_id) AS text FROM (""" + SRC["pages"] + """))
    SELECT CAST(p AS BIGINT) AS part, md5(substr(text, 1, length(text) // p)) AS digest FROM w, (VALUES (1), (2), (4), (8)) v(p)""")
def _(spark, sf):
    return experiments.prefixes(read_texts(spark, sf, "pages")).select(F.col("text_id").alias("part"), F.md5("text").alias("digest"))


@query("decode_prefixes_pages")
def _(spark, sf):
    return experiments.decompress(spark, _parted(spark, sf, "pages", (8, 4, 2)), "pages")


@query("decode_prefixes_letters")
def _(spark, sf):
    return experiments.decompress(spark, _parted(spark, sf, "letters", (8, 4, 2)), "letters")


@query("disk_single_text")
def _(spark, sf):
    """Bytes that the distributed forms of both schemes write for one text."""
    blocks = corpus.single_text(read_texts(spark, sf, "benchmark"))
    n = blocks.agg(F.sum(F.length("body"))).first()[0]
    rows = []
    for name, run in (("bidirectional", lambda g: g.factors(2).count()), ("unidirectional", lambda g: g.unidirectional(2).count())):
        g = GlobalText(blocks)
        disk, seconds, refs = experiments.disk_of(spark, lambda: run(g))
        rows += [("prefixes", "benchmark", 1.0, name, 2, k, float(v)) for k, v in {"disk_bytes": disk, "disk_per_symbol": disk / n, "GiB_per_h": n / 2**30 / seconds * 3600, "references": refs}.items()]
    return spark.createDataFrame(rows, experiments.MEASURES)


def _prefix_entropy_sql(src: str, sep: str) -> str:
    return f"""WITH w AS (SELECT string_agg(text || {sep}, '' ORDER BY text_id) AS text FROM ({src})),
    c AS (SELECT CAST(q AS BIGINT) AS part, substr(text, 1, length(text) // q) AS text FROM w, (VALUES (1), (2), (4), (8)) v(q)),
    p AS (SELECT part, k, substr(text, i, k) AS ctx, substr(text, i + k, 1) AS sym FROM (SELECT part, text, k, unnest(range(1, length(text) - k + 1)) AS i FROM c, (VALUES (0), (1), (2), (3)) v(k))),
    n AS (SELECT part, k, ctx, sym, count(*) AS n FROM p GROUP BY ALL), m AS (SELECT part, k, ctx, sum(n) AS m, sum(n * log2(n)) AS s FROM n GROUP BY ALL)
    SELECT part, CAST(k AS BIGINT) AS k, CAST(any_value(length(c.text)) AS BIGINT) AS symbols, round(sum(m * log2(m) - s) / any_value(length(c.text)), 6) AS entropy FROM m JOIN c USING (part) GROUP BY part, k"""


for _name, _src, _sep, _orders in (("pages", SRC["pages"], "chr(10)", 4), ("letters", LETTERS_SQL, "''", 4), ("documents", None, None, 8)):

    @query(f"entropy_prefixes_{_name}", _prefix_entropy_sql(_src, _sep) if _name == "letters" else None)
    def _(spark, sf, name=_name, orders=_orders):
        texts, sep = _SINGLE[name]
        return _rounded(measures.prefix_entropies(texts(spark, sf), experiments.PARTS, list(range(orders)), sep))


@query("codec_sizes")
def _(spark, sf):
    """Bytes of window-bounded and block-sorting codecs beside those of the whole-text coding, document by document."""
    t = read_texts(spark, sf, "documents")
    own = coding.coding_bytes(coding.encode(factorize.factorize(t, 3), t)).agg(F.sum("bytes").alias("bytes"))
    raw = t.agg(F.sum(F.octet_length("text")).cast("long").alias("raw_bytes")).first()[0]
    return measures.codec_bytes(t).unionByName(own.select(F.lit("bidirectional, variable-length integers").alias("codec"), F.lit(raw).alias("raw_bytes"), "bytes"))


@query("min_len_sweep_documents")
def _(spark, sf):
    return measures.sweep(read_texts(spark, sf, "documents"), list(range(2, 9)))


@query("min_len_sweep_pages")
def _(spark, sf):
    return measures.sweep(read_texts(spark, sf, "pages"), list(range(2, 9)))


@query("min_len_sweep_letters")
def _(spark, sf):
    return measures.sweep(corpus.lineitem_letters_whole(read_table(spark, sf, "lineitem")), [*range(7, 13), *range(17, 23)])


@query("min_len_sweep_benchmark", " UNION ALL ".join(
    f"SELECT * FROM ({_factors_sql(B, m)} SELECT CAST({m} AS BIGINT) AS min_len, CAST((SELECT sum(length(t) - 1) FROM c) AS BIGINT) AS n, count(*) AS n_refs, CAST((SELECT sum(length(t) - 1) FROM c) - sum(len) AS BIGINT) AS n_literal_chars, CAST((SELECT sum(length(t) - 1) FROM c) - sum(len) + count(*) AS BIGINT) AS n_factors FROM fac)"
    for m in (2, 3, 4)))
def _(spark, sf):
    return measures.sweep(read_texts(spark, sf, "benchmark"), [2, 3, 4])


@query("shard_size_counts")
def _(spark, sf):
    """Factors of pages alone and of growing groups of pages: more text, more repeats, fewer factors."""
    t = read_texts(spark, sf, "pages")
    out = None
    for rows in (1, 4, 16, 64):
        x = t if rows == 1 else corpus.shard_texts(t, rows)
        c = measures.scheme_counts(x, factorize.factorize(x, 3), f"{rows} rows", 3)
        out = c if out is None else out.unionByName(c)
    return out


@query("window_size_counts")
def _(spark, sf):
    t = read_texts(spark, sf, "conversations")
    out = measures.scheme_counts(t, factorize.factorize(t, 3), "whole text", 3)
    for w in (64, 256, 1024):
        out = out.unionByName(measures.scheme_counts(t, factorize.parse_window(t, w), f"window {w}", 3))
    return out


@query("tie_rule_counts")
def _(spark, sf):
    t = read_texts(spark, sf, "conversations")
    out = None
    for tie in ("leftmost", "rightmost", "hash", "stable"):
        c = measures.scheme_counts(t, factorize.factorize(t, 2, "heap", tie=tie), tie, 2)
        out = c if out is None else out.unionByName(c)
    return out


@query("kernel_times")
def _(spark, sf):
    return measures.kernel_times(read_texts(spark, sf, "documents"))


@query("peak_list_stats")
def _(spark, sf):
    return factorize.peak_list_stats(read_texts(spark, sf, "conversations"))


@query("peak_list_worst_case")
def _(spark, sf):
    rows = [(m, "".join(map(chr, (256 + x for x in K.nested_text(m))))) for m in (5, 8, 12, 100)]
    return factorize.peak_list_stats(spark.createDataFrame(rows, "text_id long, text string"))


@query("optimum_small")
def _(spark, sf):
    words = read_table(spark, sf, "part").select(F.col("p_partkey").alias("text_id"), F.col("p_name").alias("text"))

    def run(it):
        for pdf in it:
            yield pd.DataFrame({"text_id": pdf["text_id"], "optimum": [K.optimal_bidirectional(t) for t in pdf["text"]]})

    c = coding.reference_counts(factorize.factorize(words), words)
    return words.mapInPandas(run, "text_id long, optimum long").join(c.select("text_id", "n", "n_factors"), "text_id")


@query("io_model")
def _(spark, sf):
    """Block transfers of the model, with the numbers of references and the depth that the documents have."""
    m = measures.IoModel(1 << 20, 1 << 13)
    t = read_texts(spark, sf, "documents")
    c = measures.scheme_counts(t, factorize.factorize(t), "bidirectional", 2).first()
    depth = graph.depths(coding.encode(factorize.factorize(t), t)).agg(F.max("depth")).first()[0]
    n, refs = c["n"], c["n_refs"]
    rows = [("scan", m.scan(n)), ("sort", m.sort(n)), ("factorize", m.chain(n, refs)), ("decode", m.jump(n, depth, 2)), ("compact", m.compaction(c["n_factors"]))]
    return spark.createDataFrame([(k, float(v)) for k, v in rows], "step string, transfers double")


@query("factors_rollup_lang_source", """SELECT lang, source, count(*) AS docs, CAST(sum(length(coalesce(text, ''))) AS BIGINT) AS covered FROM documents GROUP BY ROLLUP (lang, source)""")
def _(spark, sf):
    docs = read_table(spark, sf, "documents")
    t = corpus.as_collection(docs, "doc_id", "text")
    f = coding.encode(factorize.factorize(t), t).groupBy("text_id").agg(F.sum("len").alias("covered"))
    return docs.select(F.col("doc_id").alias("text_id"), "lang", "source").join(f, "text_id", "left").rollup("lang", "source").agg(
        F.count("*").alias("docs"), F.coalesce(F.sum("covered"), F.lit(0)).alias("covered")
    )


@query("factors_rollup_length", _factors_sql(B, 2) + """, k AS (SELECT c.text_id, length(t) - 1 AS n, count(dst) AS r, coalesce(sum(len), 0) AS s FROM c LEFT JOIN fac USING (text_id) GROUP BY c.text_id, t)
    SELECT CAST(n // 100 AS BIGINT) AS hundreds, count(*) AS texts, CAST(sum(r) AS BIGINT) AS n_refs, CAST(sum(n - s + r) AS BIGINT) AS n_factors FROM k GROUP BY ROLLUP (n // 100)""")
def _(spark, sf):
    t = read_texts(spark, sf, "benchmark")
    c = coding.reference_counts(factorize.factorize(t), t).withColumn("hundreds", F.expr("n div 100"))
    return c.rollup("hundreds").agg(F.count("*").alias("texts"), F.sum("n_refs").alias("n_refs"), F.sum("n_factors").alias("n_factors"))


@query("factors_by_lang_source")
def _(spark, sf):
    """Factors for each symbol by language and source, with all totals."""
    docs = read_table(spark, sf, "documents")
    t = corpus.as_collection(docs, "doc_id", "text")
    c = coding.reference_counts(factorize.factorize(t), t)
    return docs.select(F.col("doc_id").alias("text_id"), "lang", "source").join(c, "text_id").cube("lang", "source").agg(
        F.count("*").alias("docs"), F.sum("n_refs").alias("n_refs"), F.sum("n_factors").alias("n_factors"), (F.sum("n_factors") / F.sum("n")).alias("factors_per_symbol")
    )


@query("labels_density")
def _(spark, sf):
    """Factors for each symbol by label: repetitive junk has few."""
    t = read_texts(spark, sf, "documents")
    c = coding.reference_counts(factorize.factorize(t), t)
    return c.join(read_table(spark, sf, "labels").withColumnRenamed("doc_id", "text_id"), "text_id").groupBy("quality").agg(
        F.count("*").alias("docs"), (F.sum("n_factors") / F.sum("n")).alias("factors_per_symbol")
    )


@query("benchmark_quotes", "SELECT doc_id AS text_id, item_id, length(b.text) AS len FROM documents d JOIN benchmark b ON contains(d.text, b.text)")
def _(spark, sf):
    items = read_table(spark, sf, "benchmark").select("item_id", "text")
    docs = read_table(spark, sf, "documents").where("text IS NOT NULL")
    found = reuse.quotes(corpus.as_collection(docs, "doc_id", "text"), items)
    return found.join(items.select("item_id", F.length("text").cast("long").alias("n")), "item_id").where("len = n").select("text_id", "item_id", "len")


@query("near_copy_factors")
def _(spark, sf):
    """Groups of equal texts by size, and the factors of one and of two copies side by side."""
    docs = read_texts(spark, sf, "documents")
    g = docs.groupBy(F.md5("text").alias("digest")).agg(F.count("*").alias("copies"), F.any_value("text").alias("one"))
    pairs = g.select(F.col("digest").alias("text_id"), F.concat_ws("\n", "one", "one").alias("text"))
    single = g.select(F.col("digest").alias("text_id"), F.col("one").alias("text"))
    return measures.scheme_counts(single, factorize.factorize(single, 3), "one copy", 3).unionByName(measures.scheme_counts(pairs, factorize.factorize(pairs, 3), "two copies", 3))


# ---- SQL surface and streams ---------------------------------------------------------------------------------------
@query("udtf_factors", _factors_sql(B, 2) + " SELECT text_id, dst, len, src FROM fac")
def _(spark, sf):
    sql_surface.register(spark)
    read_texts(spark, sf, "benchmark").createOrReplaceTempView("bd_benchmark")
    return spark.sql("SELECT b.text_id, f.dst, f.len, f.src FROM bd_benchmark b, LATERAL bd_factors(b.text, 2) f WHERE f.src IS NOT NULL")


@query("udtf_arrays", f"WITH {_arrays_sql(B)} SELECT text_id, pos, isa, phi, plcp FROM a")
def _(spark, sf):
    sql_surface.register(spark)
    read_texts(spark, sf, "benchmark").createOrReplaceTempView("bd_benchmark")
    return spark.sql("SELECT b.text_id, a.* FROM bd_benchmark b, LATERAL bd_arrays(b.text) a")


@query("udf_roundtrip", f"SELECT text_id, true AS same FROM ({SRC['conversations']})")
def _(spark, sf):
    sql_surface.register(spark)
    read_texts(spark, sf, "conversations").createOrReplaceTempView("bd_conversations")
    return spark.sql("SELECT text_id, bd_decode(bd_encode(text, 2)) = text AS same FROM bd_conversations")


@query("udf_scalars", _factors_sql(B, 2) + """, k AS (SELECT c.text_id, CAST(length(t) - 1 - coalesce(sum(len), 0) + count(dst) AS BIGINT) AS n_factors FROM c LEFT JOIN fac USING (text_id) GROUP BY c.text_id, t),
    r AS (SELECT text_id, substr(any_value(t), arg_max(pos, plcp * 1000000 - pos), max(plcp)) AS longest FROM a GROUP BY text_id),
    w AS (SELECT text_id, t, substr(t, pos, 1) AS ctx, substr(t, pos + 1, 1) AS sym FROM a WHERE pos < length(t) - 1),
    n AS (SELECT text_id, t, ctx, sym, count(*) AS n FROM w GROUP BY ALL), m AS (SELECT text_id, t, ctx, sum(n) AS m, sum(n * log2(n)) AS s FROM n GROUP BY ALL),
    h AS (SELECT text_id, round(sum(m * log2(m) - s) / any_value(length(t) - 1), 6) AS entropy FROM m GROUP BY text_id)
    SELECT text_id, n_factors, longest, entropy FROM k JOIN r USING (text_id) JOIN h USING (text_id)""")
def _(spark, sf):
    sql_surface.register(spark)
    read_texts(spark, sf, "benchmark").createOrReplaceTempView("bd_benchmark")
    return spark.sql("SELECT text_id, bd_n_factors(text, 2) AS n_factors, bd_longest_repeat(text) AS longest, round(bd_entropy(text, 1), 6) AS entropy FROM bd_benchmark")


@query("udaf_group_factors", _factors_sql(f"SELECT 0 AS text_id, string_agg(text, chr(10) ORDER BY text_id) AS text FROM ({B})", 2, 1000) + """
    SELECT CAST(any_value(length(t)) - 1 - sum(len) + count(*) AS BIGINT) AS n_factors FROM c JOIN fac USING (text_id)""")
def _(spark, sf):
    sql_surface.register(spark)
    read_texts(spark, sf, "benchmark").coalesce(1).sortWithinPartitions("text_id").createOrReplaceTempView("bd_benchmark")
    return spark.sql("SELECT bd_group_factors(text) AS n_factors FROM bd_benchmark")


@query("window_texts_daily", """SELECT CAST(epoch(time_bucket(INTERVAL '1 day', ts)) AS BIGINT) AS start, md5(string_agg(upper(substr(event_type, 1, 1)), '' ORDER BY ts, event_id)) AS digest FROM events GROUP BY 1""")
def _(spark, sf):
    return streams.window_texts(read_table(spark, sf, "events")).select(F.col("start").cast("long").alias("start"), F.md5("text").alias("digest"))


@query("window_texts_sliding")
def _(spark, sf):
    t = streams.window_texts(read_table(spark, sf, "events"), "1 day", "6 hours")
    t = t.select(F.col("start").cast("long").alias("text_id"), "text")
    return coding.reference_counts(factorize.factorize(t), t)


@query("session_texts", """WITH e AS (SELECT *, lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS p FROM events),
    s AS (SELECT *, sum(CASE WHEN p IS NULL OR ts - p >= INTERVAL '30 minutes' THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM e)
    SELECT user_id, CAST(epoch_us(min(ts)) AS BIGINT) AS start, md5(string_agg(upper(substr(event_type, 1, 1)), '' ORDER BY ts, event_id)) AS digest FROM s GROUP BY user_id, k""")
def _(spark, sf):
    t = streams.window_texts(read_table(spark, sf, "events"), session="30 minutes")
    return t.select("user_id", F.unix_micros("start").alias("start"), F.md5("text").alias("digest"))


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """Documents coded, decoded and compared, by language."""
    docs = read_table(spark, sf, "documents")
    t = corpus.as_collection(docs, "doc_id", "text")
    f = coding.encode(factorize.factorize(t), t)
    per = coding.factor_counts(f).join(decode.decode_memory(f).select("text_id", F.md5("text").alias("d")), "text_id")
    per = t.select("text_id", F.length("text").alias("n"), F.md5("text").alias("own")).join(per, "text_id", "left")
    return docs.select(F.col("doc_id").alias("text_id"), "lang").join(per, "text_id").groupBy("lang").agg(
        F.count("*").alias("docs"), F.sum("n").cast("long").alias("symbols"), F.sum("n_refs").cast("long").alias("n_refs"),
        F.sum("n_factors").cast("long").alias("n_factors"), F.bool_and((F.col("n") == 0) | (F.col("own") == F.col("d"))).alias("exact"),
    )


QUERIES["flagship_documents"] = flagship
