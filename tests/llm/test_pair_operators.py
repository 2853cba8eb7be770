"""Decontamination, embeddings, Jaccard join and the pipeline: brute force and corner cases."""

import random
import re
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_text_operators import LOW, WORD, docs_of, edge_docs

from textfactor.llm import decontaminate, jaccard, vectors
from textfactor.llm.components import LocalUnion, connected_components
from textfactor.llm.scratch import Scratch


def components(ids, pairs):
    up = {i: i for i in ids}

    def find(x):
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    for a, b in pairs:
        a, b = find(a), find(b)
        if a != b:
            up[max(a, b)] = min(a, b)
    return {i: find(i) for i in ids}


def test_components(spark):
    random.seed(1)
    edges = [(random.randint(0, 300), random.randint(0, 300)) for _ in range(170)] + [(k, k + 1) for k in range(400, 460)] + [(500, k) for k in range(501, 560)]
    got = {r["node"]: r["root"] for r in connected_components(spark.createDataFrame(edges, "u long, v long"), Scratch(spark, "t")).collect()}
    want = components({x for e in edges for x in e}, edges)
    assert all(got.get(k, k) == v for k, v in want.items())
    u = LocalUnion(600)
    u.add(np.array([a for a, _ in edges]), np.array([b for _, b in edges]))
    assert all(u.label[k] == v for k, v in want.items())
    assert connected_components(spark.createDataFrame([], "u long, v long"), Scratch(spark, "t")).count() == 0


# ---- op 8
def bags(t, k=5):
    w = re.findall(r"[a-z0-9\u0080-\U0010ffff]+", t.translate(LOW))
    return [tuple(w[i : i + k]) for i in range(len(w) - k + 1)] if len(w) >= k else [tuple(w)] if w else []


def best_window(h, item):
    m = min(len(item), len(h))
    c, best = Counter(item), 0.0
    for p in range(len(h) - m + 1):
        both = sum((Counter(h[p : p + m]) & c).values())
        best = max(best, both / (len(item) + m - both))
    return best


def test_decontamination(spark):
    random.seed(7)
    vocab = [f"w{i}" for i in range(60)]
    items = {i: " ".join(random.choices(vocab, k=random.choice([3, 12, 30, 45]))) for i in range(8)}
    items[8], items[9] = None, items[0]
    docs = {}
    for d in range(60):
        w = random.choices(vocab, k=random.randint(0, 80))
        if d % 2:
            q = items[random.randint(0, 7)].split()
            for _ in range(random.choice([0, 0, 1, 2])):
                q[random.randrange(len(q))] = "edit"
            w[random.randint(0, len(w)) : 0] = q
        docs[d] = ", ".join(w).upper() if d % 3 == 0 else " ".join(w)
    docs[60] = items[0]
    df = spark.createDataFrame([(d, t, "e") for d, t in docs.items()], "doc_id long, text string, item_id string")
    bench = spark.createDataFrame(list(items.items()), "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]): r["similarity"] for r in decontaminate.find_items(df, bench).collect()}
    want = {(d, i): s for d, t in docs.items() for i, x in items.items() if x and (h := bags(t)) and (s := best_window(h, bags(x))) >= 0.8 - 1e-12}
    assert set(got) == set(want) and all(abs(got[k] - want[k]) < 1e-9 for k in want) and len(want) > 10
    assert decontaminate.find_items(df, bench.limit(0)).count() == 0
    assert decontaminate.find_items(edge_docs(spark).limit(0), bench).count() == 0
    assert decontaminate.find_items(edge_docs(spark), spark.createDataFrame([(1, "same text here")], bench.schema)).count() == 2


def test_index_covers_the_radius():
    index = decontaminate.ItemIndex([0, 1], ["a b c d e f g h i j k l", "m n o p q r s t u v w x"])
    rng = np.random.default_rng(1)
    m = index.sizes[0]
    for _ in range(200):
        flips = rng.choice(64, rng.integers(0, decontaminate.RADIUS + 1), replace=False)
        x = int(index.prints[0])
        for b in flips.tolist():
            x ^= 1 << b
        win, item = index.candidates(np.array([x], np.uint64), m)
        assert 0 in item.tolist()


def test_radius_recall():
    """Windows made from items by edits down to a similarity of 0.8: at least 0.98 of them are within the radius."""
    rng = np.random.default_rng(8)
    met = found = 0
    for _ in range(400):
        m = int(rng.integers(8, 80))
        h = rng.integers(1, 2**63, m).astype(np.uint64)
        w = h.copy()
        drop = int(m * 0.2 / 1.8)  # the rest has a similarity of 0.8 at least
        w[rng.choice(m, drop, replace=False)] = rng.integers(1, 2**63, drop).astype(np.uint64)
        a, b = (decontaminate.fingerprints(x, np.zeros(1, np.int64), m)[0] for x in (h, w))
        met += 1
        found += int(np.bitwise_count(a ^ b)) <= decontaminate.RADIUS
    assert found >= 0.98 * met


def test_decontamination_query(spark, sf):
    got = {(r["doc_id"], r["item_id"]) for r in decontaminate.op8_decontamination(spark, sf).collect()}
    items = {r["item_id"]: bags(r["text"]) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()}
    where = defaultdict(set)
    for i, h in items.items():
        for x in h:
            where[x].add(i)
    want = set()
    for d, t in docs_of(spark, sf).items():
        h = bags(t)
        want |= {(d, i) for i in {i for x in h for i in where.get(x, ())} if best_window(h, items[i]) >= 0.8}
    assert got == want


# ---- op 9
def brute_vectors(rows, cosine=0.9):
    ok = {i: np.array(v, float) for i, v in rows if v and all(x is not None and np.isfinite(x) for x in v) and any(v)}
    ids = list(ok)
    pairs = [(a, b) for n, a in enumerate(ids) for b in ids[:n] if len(ok[a]) == len(ok[b]) and ok[a] @ ok[b] / np.sqrt((ok[a] @ ok[a]) * (ok[b] @ ok[b])) >= cosine]
    links = Counter(x for p in pairs for x in p)
    return links, components([i for i, _ in rows], pairs)


@pytest.mark.parametrize("cell", [40, 6000])
def test_vectors(spark, monkeypatch, cell):
    monkeypatch.setattr(vectors, "CELL", cell)
    monkeypatch.setattr(vectors, "SLICE", 50)
    monkeypatch.setattr(vectors, "MET", 70)
    rng = np.random.default_rng(3)
    centers = rng.normal(size=(12, 8))
    rows = [(i, (centers[i % 12] + rng.normal(size=8) * rng.choice([0.05, 0.2, 0.6])).tolist()) for i in range(200)]
    rows += [(200 + i, rows[0][1]) for i in range(20)] + [(300, None), (301, [0.0] * 8), (302, [float("nan")] * 8), (303, [None, *[1.0] * 7]), (304, []), (305, [1.0, 0.0]), (306, [2.0, 0.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("node", F.lit("x"))
    links, comp = brute_vectors(rows)
    for r in vectors.link_vectors(df).collect():
        assert r["n_links"] == links[r["vec_id"]] and r["component_id"] == comp[r["vec_id"]] and r["kept"] == (comp[r["vec_id"]] == r["vec_id"]), r
    assert vectors.link_vectors(df.limit(0)).count() == 0


def test_vectors_query(spark, sf):
    rows = [(r["vec_id"], list(r["embedding"])) for r in spark.read.parquet(f"{sf}/embeddings.parquet").collect()]
    links, comp = brute_vectors(rows)
    got = vectors.op9_embedding_near_dedup(spark, sf).collect()
    assert len(got) == len(rows) and all(r["n_links"] == links[r["vec_id"]] and r["component_id"] == comp[r["vec_id"]] for r in got)


# ---- op 10
def sets_of(docs, k):
    out = {}
    for d, t in docs.items():
        w = WORD.findall((t or "").translate(LOW))
        out[d] = frozenset(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if len(w) >= k else frozenset([tuple(w)] if w else [])
    return out


def brute_jaccard(docs, rule):
    s = sets_of(docs, rule.k)
    ids = [d for d in s if s[d]]
    pairs = [(a, b) for n, a in enumerate(ids) for b in ids[:n] if rule.den * len(s[a] & s[b]) >= rule.num * len(s[a] | s[b])]
    return s, components(s, pairs)


@pytest.mark.parametrize("rule", [jaccard.Rule(3, 90, 100), jaccard.Rule(5, 80, 100), jaccard.Rule(1, 50, 100)])
@pytest.mark.parametrize("block, spread", [(7, 64), (3, 0), (512, 64)])
def test_jaccard(spark, monkeypatch, rule, block, spread):
    monkeypatch.setattr(jaccard, "BLOCK", block)
    monkeypatch.setattr(jaccard, "SPREAD", spread)
    monkeypatch.setattr(jaccard, "CHUNK", 300)
    random.seed(rule.num)
    vocab = [f"w{i}" for i in range(200)]
    docs = {}
    for g in range(12):
        base = random.choices(vocab, k=random.choice([2, 9, 12, 20, 60, 150]))
        for c in range(random.choice([1, 2, 5, 25])):
            w = list(base)
            for _ in range(random.choice([0, 0, 1, 1, 2, 4])):
                w[random.randrange(len(w))] = random.choice(vocab)
            docs[len(docs)] = " ".join(w + random.choices(vocab, k=random.choice([0, 0, 1])))
    docs[len(docs)], docs[len(docs)] = None, " "
    s, comp = brute_jaccard(docs, rule)
    df = spark.createDataFrame([(d, t, "e") for d, t in docs.items()], "doc_id long, text string, node string").repartition(3)
    got = jaccard.link_documents(df, rule).collect()
    assert {r["id"]: (r["n_shingles"], r["component_id"]) for r in got} == {d: (len(s[d]), comp[d]) for d in docs}


def test_jaccard_corner_cases(spark):
    got = jaccard.link_documents(edge_docs(spark)).collect()
    assert len(got) == 8 and sorted(r["component_id"] for r in got if r["id"] == 4) == [4, 4]
    assert [r["component_id"] for r in got if r["id"] is None] == [None]
    assert jaccard.link_documents(edge_docs(spark).limit(0)).count() == 0


def test_local_part_of_the_early_count():
    rng = np.random.default_rng(4)
    entries = sorted({(int(o), int(k)) for o, k in zip(rng.integers(0, 30, 300), rng.integers(0, 90, 300))})
    owner, key = np.array(entries).T
    own, hubs, sent, out = jaccard.shared_here(owner, key.astype(np.uint64), 30)
    holders = defaultdict(list)
    for o, k in entries:
        holders[k].append(o)
    assert own.tolist() == [sum(len(holders[k]) > 1 for p, k in entries if p == o) for o in range(30)]
    assert sorted(out.tolist()) == sorted(holders) and sent.sum() == len(holders)
    at = 0
    for o in range(30):
        keys = out[at : at + sent[o]].tolist()
        assert all(o in holders[k] for k in keys) and [len(holders[k]) > 1 for k in keys] == [x < hubs[o] for x in range(sent[o])]
        at += sent[o]


def test_early_count_keeps_every_link():
    random.seed(5)
    for rule in (jaccard.Rule(3, 90, 100), jaccard.Rule(5, 80, 100), jaccard.Rule(1, 50, 100)):
        for _ in range(4000):
            a = set(random.sample(range(400), random.randint(1, 120)))
            b = set(random.sample(sorted(a), max(1, len(a) - random.randint(0, 12)))) | {random.randint(0, 400) for _ in range(random.randint(0, 9))}
            if a != b and rule.den * len(a & b) >= rule.num * len(a | b):
                first = [set(sorted(x)[: rule.prefix(len(x))]) for x in (a, b)]
                assert not rule.alone(len(a)) and not rule.alone(len(b))
                assert len(first[0] & first[1]) >= max(rule.ask(len(a)), rule.ask(len(b)))


def test_jaccard_query(spark, sf):
    docs = docs_of(spark, sf)
    s, comp = brute_jaccard(docs, jaccard.Rule(3, 90, 100))
    got = jaccard.op10_ngram_jaccard_join(spark, sf).collect()
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in got} == {d: (len(s[d]), comp[d]) for d in docs}


# ---- pipeline
def test_pipeline(spark, sf):
    import corpus_pipeline as p
    from test_text_operators import brute_lines

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    stage = dict(p.STAGES)
    good = stage["quality classifier"](spark, docs, sf).cache()
    assert good.columns == docs.columns and 0 < good.count() <= docs.count()
    lines = stage["line dedup"](spark, good, sf).cache()
    assert {r["doc_id"]: r["text"] for r in lines.collect()} == brute_lines({r["doc_id"]: r["text"] for r in good.collect()})
    near = stage["n-gram Jaccard join"](spark, lines, sf).cache()
    _, comp = brute_jaccard({r["doc_id"]: r["text"] for r in lines.collect()}, jaccard.Rule(5, 80, 100))
    assert {r["doc_id"] for r in near.collect()} == {d for d, c in comp.items() if c == d}
    clean = stage["benchmark decontamination"](spark, near, sf).cache()
    assert clean.columns == docs.columns
    last = stage["BPE encoding and decoding"](spark, clean, sf)
    assert last.count() == clean.count() and last.where("n_tokens <> size(token_ids)").count() == 0
    assert p.run(spark, sf).select("doc_id").exceptAll(last.select("doc_id")).count() == 0


def test_near_dedup_corner_cases(spark, sf):
    import corpus_pipeline as p

    words = [f"w{i}" for i in range(40)]
    base, near, other = " ".join(words), " ".join(words[:-1] + ["x"]), " ".join(reversed(words))
    rows = [
        (7, base), (7, base), (9, base), (3, near), (3, other), (None, near), (None, "alone here with five words"),
        (11, None), (11, None), (12, ""), (13, " \n"), (None, None), (20, "two two"), (21, "two two"),
    ]
    docs = spark.createDataFrame([(i, t, "x", 1, "a") for i, t in rows], "doc_id long, text string, text_hash string, stays int, component string")
    near_dedup = dict(p.STAGES)["n-gram Jaccard join"]
    got = near_dedup(spark, docs, sf)
    assert got.columns == docs.columns
    want = [(3, near), (3, other), (None, "alone here with five words"), (11, None), (11, None), (12, ""), (13, " \n"), (None, None), (20, "two two")]
    assert sorted(((r["doc_id"], r["text"]) for r in got.collect()), key=str) == sorted(want, key=str)
    twice = near_dedup(spark, docs.where("doc_id = 7"), sf).collect()
    assert [(r["doc_id"], r["text"]) for r in twice] == [(7, base)]
    assert near_dedup(spark, docs.limit(0), sf).count() == 0


def test_pipeline_stages_on_corner_cases(spark, sf):
    import corpus_pipeline as p

    docs = edge_docs(spark)
    for name, stage in p.STAGES:
        for d in (docs, docs.limit(0)):
            out = stage(spark, d, sf)
            assert out.count() <= d.count() and (name == p.STAGES[-1][0] or out.columns == d.columns), name
