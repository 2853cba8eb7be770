import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from textfactor import workloads
from textfactor.functions import kernels as K
from textfactor.operators import arrays, coding, compact, decode, factorize, graph, measures, reuse
from textfactor.operators.global_text import GlobalText
from textfactor.plans import checks
from textfactor.sources import corpus, io

EXAMPLE = "ababbabababbabbaababa"


@pytest.fixture(scope="module")
def texts(spark):
    random.seed(2)
    words = ["", "a", "aaaaaaa", EXAMPLE, "né\nné né ß", "abc", "$$a$$", None]
    words += ["".join(random.choice("ab c") for _ in range(random.randint(1, 120))) * random.choice([1, 2]) for _ in range(12)]
    return spark.createDataFrame(list(enumerate(words)), "text_id long, text string").withColumn("text", F.coalesce("text", F.lit(""))).cache()


def as_dict(df):
    return {r["text_id"]: r["text"] for r in df.collect()}


def decoded(df, texts):
    got = as_dict(df)
    return all((got.get(k) or "") == v for k, v in as_dict(texts).items())


def test_references_of_the_example(texts):
    for m in factorize.METHODS:
        r = factorize.factorize(texts, 2, m).where("text_id = 3")
        assert sorted((x["dst"], x["src"], x["len"]) for x in r.collect()) == [(2, 12, 5), (8, 1, 7), (15, 20, 2), (17, 19, 3)]


@pytest.mark.parametrize("min_len", [2, 4])
def test_roundtrips(texts, min_len):
    f = coding.encode(factorize.factorize(texts, min_len), texts).cache()
    assert all(all(r[c] for c in ("tiled", "long_enough", "in_range", "no_self")) for r in coding.validate(f, texts, min_len).collect())
    assert decoded(decode.decode_memory(f), texts)
    assert decoded(decode.decode_jump(f), texts)
    assert decoded(decode.decode_chars(f, direct_first=True), texts)
    for multi in (False, True):
        c = compact.compact(f, multi)
        assert decoded(decode.decode_memory(c), texts)
        a, b = (graph.depths(x).agg(F.sum("mean_depth")).first()[0] for x in (f, c))
        assert b <= a + 1e-9
    assert compact.compact(f, True).exceptAll(compact.compact_layers(f, True)).count() == 0


def test_rounds_of_the_example(texts):
    f = coding.encode(factorize.factorize(texts), texts).where("text_id = 3").cache()
    double, fixed = decode.jump(f, merge=False)[1], decode.jump(f, double=False, merge=False)[1]
    assert [r["requests"] for r in double] == [4, 4, 2] and len(fixed) == 5
    assert graph.depths(f).first()["depth"] == 5


def test_other_parses(texts):
    parses = [
        factorize.parse_unidirectional(texts), factorize.parse_unidirectional(texts, method="scan"), factorize.parse_end_aligned(texts),
        factorize.parse_window(texts, 16), factorize.parse_bwt_runs(texts), factorize.factorize(texts, 2, "heap", tie="hash"),
    ]
    for i, r in enumerate(parses):
        assert decoded(decode.decode_memory(coding.encode(r, texts)), texts)
        if i < 4:
            assert all(x["unidirectional"] for x in coding.is_unidirectional(r).collect())
    u = coding.encode(parses[0], texts)
    assert decoded(decode.decode_unidirectional(u), texts)


def test_unidirectional_decoder_refuses(texts):
    with pytest.raises(Exception, match="unidirectional"):
        decode.decode_unidirectional(coding.encode(factorize.factorize(texts), texts)).collect()


def test_extract(texts):
    f = coding.encode(factorize.factorize(texts), texts)
    got = as_dict(decode.extract(f, 3, 9))
    assert all(got.get(k, "") == v[2:9] for k, v in as_dict(texts).items())


@pytest.mark.parametrize("parts", [1, 5])
def test_one_long_text(spark, texts, parts):
    old = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", parts)
    try:
        blocks = corpus.single_text(texts)
        whole = "".join(r["body"] for r in blocks.orderBy("start").collect())
        one = spark.createDataFrame([(1, whole)], "text_id long, text string")
        want = {r["pos"]: r for r in arrays.build_arrays(one).collect()}
        g = GlobalText(blocks)
        assert all(want[r["pos"]]["isa"] == r["rank"] for r in g.suffix_array().collect())
        assert all(want[r["pos"]]["plcp"] == r["plcp"] for r in g.plcp().collect())
        assert sorted(map(tuple, g.factors(2).collect())) == sorted((r["dst"], r["len"], r["src"]) for r in factorize.factorize(one, 2).collect())
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", old)


def test_entropy_of_the_example(spark):
    t = spark.createDataFrame([(1, EXAMPLE)], "text_id long, text string")
    got = [round(measures.empirical_entropy(t, k).first()["entropy"], 5) for k in range(4)]
    assert got == [0.99836, 0.65849, 0.56082, 0.4169]


def test_longer_minimum_means_fewer_references(texts):
    rows = sorted(measures.sweep(texts, [2, 3, 4, 6]).collect(), key=lambda r: r["min_len"])
    assert all(a["n_refs"] >= b["n_refs"] and a["n_factors"] <= b["n_factors"] for a, b in zip(rows, rows[1:]))


def test_quotes(spark, texts):
    items = spark.createDataFrame([(1, "babbabb"), (2, "né né"), (3, "zzz")], "item_id long, text string")
    got = {(r["text_id"], r["item_id"]): r["len"] for r in reuse.quotes(texts, items).collect()}
    assert got[(3, 1)] == 7 and got[(4, 2)] == 5 and (3, 3) not in got


@pytest.mark.parametrize("most", [1 << 22, 8])
def test_equal_and_nested_quotes(spark, texts, monkeypatch, most):
    monkeypatch.setattr(reuse, "MAX_ITEM_SYMBOLS", most)
    random.seed(9)
    words = ["babbabb", "babbabb", "abba", "b", "né", "né né", "", None, "abbabababbabbaababababa"]
    words += ["".join(random.choice("ab c") for _ in range(random.randint(1, 6))) for _ in range(30)]
    items = spark.createDataFrame(list(enumerate(words)), "item_id long, text string")
    got = {(r["text_id"], r["item_id"]): r["pos"] for r in reuse.quotes(texts, items).collect() if r["len"] == len(words[r["item_id"]])}
    assert got == {(k, i): t.find(w) + 1 for k, t in as_dict(texts).items() for i, w in enumerate(words) if w is not None and w in t}


def test_letters_are_one_text(spark, tmp_path):
    """The letters after the first 65,536 repeat the first ones."""
    x = F.expr("pmod(hash(id % 65536), 4)")
    rows = spark.range(70000).select(F.col("id").alias("l_orderkey"), *(F.lit(1).alias(c) for c in corpus.LINEITEM_ORDER[1:4]), F.make_date(F.lit(2000), x * 3 + 1, F.lit(1)).alias("l_shipdate"))
    rows.write.parquet(str(tmp_path / "lineitem.parquet"))
    got = {r["min_len"]: r for r in workloads.QUERIES["min_len_sweep_letters"](spark, str(tmp_path)).collect()}
    assert got[22]["n_refs"] >= 1 and got[22]["n_literal_chars"] <= 65536
    assert [r["n"] for r in workloads.QUERIES["prefix_counts_letters"](spark, str(tmp_path)).where("part = 1").collect()] == [70000] * 2
    back, want = (workloads.QUERIES[q](spark, str(tmp_path)) for q in ("letters_roundtrip", "letters_text"))
    assert sorted(map(tuple, back.collect())) == sorted(map(tuple, want.collect())) and want.count() == 2


def test_files(spark, texts, tmp_path):
    f = coding.encode(factorize.factorize(texts), texts)
    for kind in ("parquet", "orc"):
        io.write_coding(f, str(tmp_path / kind), kind)
        assert io.read_coding(spark, str(tmp_path / kind), kind).exceptAll(f).count() == 0
    texts.select(F.col("text_id").cast("string").alias("text_id"), "text").write.json(str(tmp_path / "json"))
    assert io.read_files(spark, str(tmp_path / "json"), "json").count() == texts.count()
    (tmp_path / "plain").mkdir()
    (tmp_path / "plain" / "x.txt").write_text("ab\nab")
    assert io.read_files(spark, str(tmp_path / "plain"), "text").first()["text"] == "ab\nab"
    assert io.read_files(spark, str(tmp_path / "plain"), "binary").first()["text"] == "ab\nab"


def test_plans(spark, tmp_path, texts):
    texts.withColumn("unused", F.lit(1)).write.parquet(str(tmp_path / "t"))
    t = corpus.as_collection(spark.read.parquet(str(tmp_path / "t")), "text_id", "text")
    r = factorize.factorize(t)
    assert checks.read_columns(r) == [{"text_id", "text"}] and checks.exchanges(r) == 0
    f = coding.encode(factorize.factorize(texts), texts)
    checks.assert_no_cartesian(graph.dependency_edges(f))
    checks.assert_no_cartesian(decode.advance(decode.make_tiles(f), decode.make_tiles(f)))


def test_one_text_over_the_cluster(spark, monkeypatch):
    """Arrays, both parses and the coding of one text in many cells and partitions equal the kernels'."""
    from textfactor.operators import global_text

    monkeypatch.setattr(global_text, "CELL", 64)
    monkeypatch.setattr(global_text, "PACK", 3)
    monkeypatch.setattr(global_text, "LARGE", 4)
    random.seed(3)
    part = "".join(random.choices("ab", k=200))
    t = part[:150] + part[20:120] + part + "".join(random.choices(["the ", "fox "], k=20)) + "a" * 90
    blocks = spark.createDataFrame([(i + 1, t[i : i + 37]) for i in range(0, len(t), 37)], "start long, body string")
    g = global_text.GlobalText(blocks)
    x = K.symbols_of(t)
    s = K.Suffixes(x, np.array([0, len(x)]))
    phi = s.phi()
    d, n = K.rounds_factors(s.plcp(phi), np.array([0, len(x)]), 2)
    refs = g.factors(2)
    assert sorted(map(tuple, refs.select("dst", "len", "src").collect())) == sorted(zip((d + 1).tolist(), n.tolist(), (phi[d] + 1).tolist()))
    lpf, src = s.previous_factors()
    assert {r["pos"]: (r["lpf"], r["src"]) for r in g.previous_factors().collect()} == {i + 1: (int(lpf[i]), int(src[i]) + 1 if lpf[i] else None) for i in range(len(x))}
    step = np.where(lpf >= 2, lpf, 1)
    at = K.greedy_parse(step, np.array([0, len(x)]), 16)
    want = [(int(a) + 1, int(step[a]), int(src[a]) + 1) for a in at if step[a] >= 2]
    assert sorted(map(tuple, g.unidirectional(2).collect())) == want
    f = coding.encode_blocks(refs, blocks, 50).withColumn("text_id", F.lit(0))
    assert decode.decode_copies(f)[0].first()["text"] == t
    assert sum(r["len"] for r in f.collect()) == len(t)


def test_circles_are_found(spark):
    rows = [(1, 1, 1, 2, 3, None), (1, 2, 3, 2, 1, None), (2, 1, 1, 2, None, "ab"), (2, 2, 3, 2, 1, None), (3, 1, 1, 1, None, "a"), (3, 2, 2, 3, 9, None)]
    f = spark.createDataFrame(rows, "text_id long, factor_no long, dst long, len long, src long, literal string")
    texts = spark.createDataFrame([(1, "abab"), (2, "abab"), (3, "aaaa"), (4, "")], "text_id long, text string")
    assert {r["text_id"]: r["resolves"] for r in coding.validate(f, texts).collect()} == {1: False, 2: True, 3: False, 4: True}


def test_entropies_of_prefixes_need_no_prefix_in_a_task(spark, monkeypatch):
    """Short and empty texts, many parts and symbols, all orders: as the entropies of the prefixes as texts; no row has a prefix."""
    from textfactor.operators import experiments

    monkeypatch.setattr(measures, "GRAM_SYMBOLS", 50)
    monkeypatch.setattr(measures, "GRAM_ROWS", 60)
    monkeypatch.setattr(measures, "BUCKET_SYMBOLS", 500)
    random.seed(6)
    for kinds in ("ab\n", "".join(map(chr, range(32, 400))) + "\U0001f600"):
        words = ["", "a", "", "b"] + ["".join(random.choices(kinds, k=random.randint(0, 90))) for _ in range(60)]
        t = spark.createDataFrame(list(enumerate(words)), "text_id long, text string").repartition(5)
        for sep in ("\n", ""):
            orders = [0, 1, 2, 5, 7]
            got = {(r["part"], r["k"]): (r["symbols"], round(r["entropy"], 9)) for r in measures.prefix_entropies(t, (8, 2, 1), orders, sep).collect()}
            want = {}
            for r in experiments.prefixes(t, (8, 2, 1), sep).collect():
                one = spark.createDataFrame([(0, r["text"])], "text_id long, text string")
                want |= {(r["text_id"], x["k"]): (x["symbols"], round(x["entropy"], 9)) for x in measures.entropies(one, orders).collect()}
            assert got == want
    placed, begins, n = corpus.placed_texts(t, "", 3)
    whole, rows = "".join(words), placed.collect()
    assert n == len(whole) and max(len(r["body"]) for r in rows) <= 90
    for r in rows:
        base, tail = begins[r["part"]]
        at = base + r["off"]
        assert whole[at : at + len(r["body"])] == r["body"] and (tail + r["before"])[-3:] == whole[max(0, at - 3) : at]
    assert measures.prefix_entropies(t.where("text_id < 0"), (2, 1), [0, 1]).count() == 0


def test_entropies_of_page_prefixes_equal_sql(spark):
    """The pages' query, whose prefixes are cut inside of pages, against the SQL of its kind; no kernel makes a text of a prefix."""
    import duckdb

    d = "/root/testdata/sf0.001"
    con = duckdb.connect()
    con.sql(f"CREATE VIEW pages AS SELECT * FROM '{d}/pages.parquet' WHERE page_id < 12")
    want = con.sql(workloads._prefix_entropy_sql(workloads.SRC["pages"], "chr(10)")).fetchall()
    got = measures.prefix_entropies(io.read_texts(spark, d, "pages").where("text_id < 12"), (8, 4, 2, 1), [0, 1, 2, 3])
    got = [tuple(r) for r in got.withColumn("entropy", F.round("entropy", 6)).collect()]
    assert len(want) == 16 and sorted(got) == sorted(want)


@pytest.fixture
def long_prefix(spark, monkeypatch):
    """What a function of prefixes returns with the kernels, and with a kernel call's size below that of the whole text."""
    from textfactor.operators import experiments, global_text

    monkeypatch.setattr(global_text, "CELL", 64)
    random.seed(11)
    part = "".join(random.choices("ab", k=60))
    words = ["", part[:40], "né \U0001f600", part[10:50] + "a" * 20, "", "fox the fox"]
    t = spark.createDataFrame(list(enumerate(words)), "text_id long, text string")
    whole = "\n".join(words) + "\n"

    def run(f):
        x = experiments.parted(t, (4, 1))
        assert {r["text_id"]: r["text"] for r in x.short.collect()} == {p: whole[: len(whole) // p] for p in (1, 4)} and not x.long
        want = f(x)
        monkeypatch.setattr(experiments, "KERNEL_SYMBOLS", len(whole) // 4)
        x = experiments.parted(t, (4, 1))
        assert [r["text_id"] for r in x.short.collect()] == [4] and {p: n for p, (_, n) in x.long.items()} == {1: len(whole)}
        assert max(len(r["body"]) for r in x.long[1][0].collect()) <= max(map(len, words)) + 1
        return want, f(x)

    return run


def test_counts_of_long_prefixes(long_prefix):
    from textfactor.operators import experiments

    want, got = long_prefix(lambda x: sorted(map(tuple, experiments.prefix_counts(x).collect())))
    assert len(want) == 4 and got == want


def test_measures_of_long_prefixes(long_prefix):
    from textfactor.operators import experiments

    def measured(x):
        rows = [tuple(r) for r in experiments.prefix_measures(x, "x", [2, 4], "prefixes", 1).collect()]
        return {r[:6] for r in rows}, sorted(r for r in rows if r[5] in ("symbols", "references", "factors", "factor_ratio"))

    want, got = long_prefix(measured)
    assert len(want[1]) == 22 and got == want


def test_decoding_of_long_prefixes(spark, long_prefix):
    from textfactor.operators import experiments

    def decoded_parts(x):
        rows = [tuple(r) for r in experiments.decompress(spark, x, "x").collect()]
        return {r[:6] for r in rows}, sorted(r[2] for r in rows if r[5] == "same" and r[6] == 1)

    want, got = long_prefix(decoded_parts)
    assert want[1] == [0.25, 1.0] and got == want


def test_tables_of_past_rounds_are_dropped(spark, tmp_path, monkeypatch):
    """Of one text's arrays the blocks, symbols and levels stay, and of the rounds of a comparison the last."""
    from collections import Counter

    monkeypatch.setattr("textfactor.plans.scratch.shared_root", lambda spark: str(tmp_path))
    g = GlobalText(spark.createDataFrame([(1, "abaabbab" * 6), (49, "abba" * 5)], "start long, body string"))
    left = lambda: Counter(x.name[4:] for x in (tmp_path / "textfactor").glob("global-*/*"))
    assert len(g.levels) > 1 and left() == {"blocks": 1, "symbols": 1, "level": len(g.levels)}
    whole = "abaabbab" * 6 + "abba" * 5
    pairs = g.scratch.save(spark.createDataFrame([(1, 9), (2, 5), (49, 1)], "i long, j long"), "asked")
    got = {(r["i"], r["j"]): r["n"] for r in g.common(pairs).collect()}
    assert left()["common"] == 1
    assert got == {(i, j): next((k for k in range(68 - max(i, j) + 1) if whole[i - 1 + k] != whole[j - 1 + k]), 68 - max(i, j) + 1) for i, j in got}


def test_sources_are_looked_up_for_factors_only(spark):
    """No join that a factor's source takes makes the neighbours of all positions: each has the factors on one side."""
    from textfactor.operators.global_text import GlobalText

    text = "abracadabra abracadabra"
    got = GlobalText(spark.createDataFrame([(1, text)], "start long, body string")).factors(2)
    want = factorize.factorize(spark.createDataFrame([(0, text)], "text_id long, text string"), 2).select("dst", "len", "src")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect())) and want.count()
    todo, joins = [got._jdf.queryExecution().optimizedPlan()], []
    while todo:
        node = todo.pop()
        joins += [node.output().mkString(" ")] if node.nodeName() == "Join" else []
        todo += [node.children().apply(i) for i in range(node.children().size())]
    assert len(joins) == 2 and all("len#" in x for x in joins), joins


@pytest.mark.parametrize("most", [0, 1 << 20])
def test_ranks_and_common_prefixes_by_parts(spark, monkeypatch, most):
    """Ranks and common prefixes of a text in many small parts are the kernels', also where a group fills several parts and windows
    give way to levels; no round writes a row for a position before its ranks are known."""
    from textfactor.operators import global_text, order, windows
    from textfactor.plans.scratch import Scratch

    monkeypatch.setattr(order, "PART", 16)
    monkeypatch.setattr(windows, "WINDOW", 2)
    monkeypatch.setattr(windows, "MOST", most)
    wrote, save = [], Scratch.save
    monkeypatch.setattr(Scratch, "save", lambda self, df, name, *a: (wrote.append((name, got := save(self, df, name, *a), got.count())), got)[1])
    random.seed(5)
    part = "".join(random.choices("ab\u00e9\U0001f600", k=60))
    t = part + "a" * 70 + part[:40] + "".join(random.choices("ab", k=50)) + part
    g = global_text.GlobalText(spark.createDataFrame([(i + 1, t[i : i + 23]) for i in range(0, len(t), 23)], "start long, body string"))
    x = K.symbols_of(t)
    s = K.Suffixes(x, np.array([0, len(x)]))
    assert [r["pos"] - 1 for r in g.ranks.orderBy("rank").collect()] == s.order.tolist()
    assert sorted(r["rank"] for r in g.ranks.collect()) == list(range(len(t)))
    assert all(n <= -(-len(t) // 16) for name, _, n in wrote if name == "ranked") and len([1 for w in wrote if w[0] == "ranked"]) == len(g.levels) > 2
    phi, v = s.phi(), s.plcp(s.phi())
    own = [i for i in range(len(t)) if phi[i] < len(t) and (not i or not phi[i] or t[i - 1] != t[phi[i] - 1])]
    assert sorted(map(tuple, g.irreducible().collect())) == [(i + 1, phi[i] + 1, v[i]) for i in own]
    wrote.clear()
    ij = [(a, b) for a in range(0, len(t), 3) for b in range(0, len(t), 7) if a != b]
    got = {(r["i"] - 1, r["j"] - 1): r["n"] for r in g.common(spark.createDataFrame([(a + 1, b + 1) for a, b in ij], "i long, j long")).collect()}
    assert got == dict(zip(ij, s.common(*np.array(ij).T).tolist()))
    assert len([1 for w in wrote if w[0] == "compared"]) == (1 if most == 0 else 2) and "agreeing" in {w[0] for w in wrote}


def test_ranks_of_an_empty_text(spark):
    g = GlobalText(spark.createDataFrame([(1, "")], "start long, body string"))
    assert not g.ranks.count() and not g.factors(2).count() and not g.unidirectional(2).count()
