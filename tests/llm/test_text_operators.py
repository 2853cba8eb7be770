"""Chat formatting, secrets, sharding, BPE, quality, lines, language model: brute force and corner cases."""

import hashlib
import json
import math
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from textfactor.llm import bpe, chat, hmm, linededup, quality, secrets, sharding
from textfactor.llm.automaton import Nfa, combined

LOW = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})
WORD = re.compile(r"[^\x20\x09-\x0D]+")
DOCS = "doc_id long, text string, extra string"


def docs_of(spark, sf):
    return {r["doc_id"]: r["text"] or "" for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()}


def edge_docs(spark, schema="doc_id long, text string, id string, score string, row long"):
    """Nulls, an empty and a very long text, repeated rows, and columns named like internal ones."""
    long_text = "lorem ipsum dolor " * 20_000 + "é" * 1000
    rows = [(1, None), (2, ""), (3, long_text), (4, "same text here"), (4, "same text here"), (None, "no id"), (5, "\n\n \t\n"), (6, "x")]
    return spark.createDataFrame([(a, b, "i", "s", 7) for a, b in rows], schema)


# ---- op 1
def test_chat_roundtrip(spark):
    nasty = ["<|im_end|>", "<\\|im_end|>", "<\\\\|", "<|", "|>", "\n", "<|im_start|>assistant\nx", "", "a<b|c", "%0A%25", "é\U0001f600"]
    random.seed(0)
    rows = [(c, t, random.choice(["user", "assistant", "sys\ntem%", None]), random.choice([*nasty, "".join(random.choices(nasty, k=4)), None])) for c in range(25) for t in range(random.randint(1, 9))]
    rows += [(99, None, "user", "first"), (99, 1, "user", "same"), (99, 1, "user", "same"), (None, 1, "assistant", "n")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("turns", F.lit(1)).withColumn("blocks", F.lit(2))
    got = {r["conv_id"]: r for r in chat.digest(chat.format_chats(df)).collect()}
    want = defaultdict(list)
    for c, t, r, x in rows:
        want[c].append((t is not None, t or 0, r or "", x or ""))
    assert set(got) == set(want)
    for c, turns in want.items():
        turns.sort()
        text = "".join(f"{r}\n{x}\n" for *_, r, x in turns)
        loss = "".join(x for *_, r, x in turns if r == "assistant")
        g = got[c]
        assert g["n_turns"] == len(turns) and g["turns_sha256"] == hashlib.sha256(text.encode()).hexdigest()
        assert g["loss_chars"] == len(loss) and g["loss_sha256"] == hashlib.sha256(loss.encode()).hexdigest()
    assert chat.digest(chat.format_chats(df.limit(0))).count() == 0
    blocks = chat.format_chats(spark.createDataFrame([(1, 0, "user", "a"), (1, 1, "user", "b"), (1, 2, "assistant", "c")], df.select("conv_id", "turn", "role", "text").schema)).first()
    assert blocks["n_blocks"] == 2 and blocks["formatted"].count("<|im_start|>") == 2


# ---- op 2
ASSIGN = re.compile(r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.A)


def brute_spans(t):
    out = [(m.start(), 0, "assign", m.end()) for m in ASSIGN.finditer(t) if len(m[2]) >= 6]
    out += [(m.start(), 1, "access", m.end()) for m in re.finditer(r"AKIA[A-Z0-9]+", t) if len(m[0]) >= 20]
    out += [(m.start(), 2, "hex", m.end()) for m in re.finditer(r"[0-9a-f]+", t) if len(m[0]) >= 24]
    return [(k, s, e) for s, _, k, e in sorted(out)]


def test_secrets_against_regex():
    sc = secrets.scanner(secrets.BASE_RULES + secrets.MORE_RULES)
    random.seed(1)
    parts = ["token", "secret", "Password", "api_key", "apikey", "=", ":", " ", "'", '"', "abc123", "AKIA", "ABCDEFGHIJKLMNOP0", "deadbeef", "0123456789abcdef", "é", "\n", "ghp_", "=="]
    for _ in range(4000):
        t = "".join(random.choices(parts, k=random.randint(0, 25)))
        assert [x for x in sc.spans(t) if x[0] in ("assign", "access", "hex")] == brute_spans(t)
    assert ("private_key", 0, 31) in sc.spans("-----BEGIN RSA PRIVATE KEY-----")


def test_automaton_is_minimal():
    table, masks, start = combined([Nfa("ab+c"), Nfa("(?:ab|ab)b*c")])
    assert len(table) == 4 and masks.max() == 3 and start == 0
    with pytest.raises(ValueError):
        Nfa("a*")


def test_secrets_query(spark, sf):
    got = {r["doc_id"]: r for r in secrets.op2_secret_scans(spark, sf).collect()}
    for d, t in docs_of(spark, sf).items():
        line = ",".join(f"{k}:{s}:{e}" for k, s, e in brute_spans(t))
        assert got[d]["base_sha256"] == hashlib.sha256(line.encode()).hexdigest()
        assert got[d]["n_hex"] == sum(k == "hex" for k, *_ in brute_spans(t))
    assert secrets.scan_secrets(edge_docs(spark)).count() == 8 and secrets.scan_secrets(edge_docs(spark).limit(0)).count() == 0
    assert secrets.redact("a token=abcdef b", [{"start": 2, "end": 14}]) == "a [secret] b"


# ---- op 3
def test_shards(spark, sf):
    for df in (spark.read.parquet(f"{sf}/documents.parquet"), edge_docs(spark)):
        rows = sharding.shard_by_bytes(df, 8).collect()
        assert sorted((str(r["doc_id"]), r["size"], r["text_crc32"]) for r in rows) == sorted(
            (str(r["doc_id"]), len((r["text"] or "").encode()) + 16, zlib.crc32((r["text"] or "").encode())) for r in df.collect()
        )
        by = defaultdict(list)
        for r in rows:
            by[r["shard"]].append(r["slot"])
        assert all(sorted(v) == list(range(len(v))) for v in by.values())
        sums = [sum(r["size"] for r in rows if r["shard"] == s) for s in range(8)]
        assert max(sums) - min(sums) <= 2 * max(r["size"] for r in rows)
    assert sharding.shard_by_bytes(edge_docs(spark).limit(0)).count() == 0


def test_hot_key_is_subdivided(spark):
    df = spark.range(3000).select(F.col("id").alias("doc_id"), F.when(F.col("id") < 1500, F.lit("x" * 50)).otherwise(F.concat(F.lit("y"), F.col("id"))).alias("text"))
    rows = sharding.shard_by_bytes(df, 10, ranges=64, sample=512).groupBy("shard").agg(F.sum("size").alias("b")).collect()
    assert len(rows) == 10 and max(r["b"] for r in rows) - min(r["b"] for r in rows) <= 140


# ---- op 4
def test_bpe_equals_library(spark, sf):
    from tokenizers import Tokenizer

    vocab, ranks = bpe._vocab_paths()
    lib = Tokenizer.from_file(vocab)
    got = {r["doc_id"]: r for r in bpe.encode_texts(spark.read.parquet(f"{sf}/documents.parquet")).collect()}
    for d, t in docs_of(spark, sf).items():
        ids = lib.encode(t, add_special_tokens=False).ids
        assert got[d]["token_ids"] == ids and got[d]["n_tokens"] == len(ids)
        assert got[d]["decoded_sha256"] == hashlib.sha256(lib.decode(ids, skip_special_tokens=False).encode()).hexdigest()
    assert bpe.encode_texts(edge_docs(spark)).count() == 8 and bpe.encode_texts(edge_docs(spark).limit(0)).count() == 0


def test_joins_are_repaired(monkeypatch):
    from tokenizers import Tokenizer

    vocab, ranks = bpe._vocab_paths()
    lib, e = Tokenizer.from_file(vocab), bpe.encoder(vocab, ranks)
    random.seed(3)
    parts = ["a", "é", " ", "\n", "  ", "'s", "'ll", "the", "<|endoftext|>", "<|endof", "text|>", "123", "!!", "　", "\t", "\r\n", "日本", "🙂", "x" * 40]

    def everywhere(self, data):
        return [0, *(i for i in range(1, len(data)) if data[i] & 0xC0 != 0x80 and random.random() < 0.15), len(data)]

    monkeypatch.setattr(bpe.ChunkEncoder, "cuts", everywhere)
    for _ in range(800):
        t = "".join(random.choices(parts, k=random.randint(0, 60)))
        assert e.encode(t) == lib.encode(t, add_special_tokens=False).ids


def test_short_texts_share_chunks():
    from tokenizers import Tokenizer

    lib, e = Tokenizer.from_file(bpe._vocab_paths()[0]), bpe.ChunkEncoder(*bpe._vocab_paths())
    random.seed(6)
    words = lambda n: " ".join("".join(random.choices("abcdeé", k=random.randint(1, 9))) for _ in range(n))
    passage = words(450)
    one, two = words(40) + " " + passage, words(70) + " " + passage
    assert 2000 < len(one.encode()) < 4096 and e.encode(one) == lib.encode(one, add_special_tokens=False).ids
    kept = set(e.store)
    assert kept and e.encode(one) == lib.encode(one, add_special_tokens=False).ids and set(e.store) == kept
    assert e.encode(two) == lib.encode(two, add_special_tokens=False).ids
    assert any(two.encode()[a:b] in kept for a, b in zip(e.cuts(two.encode()), e.cuts(two.encode())[1:]))
    assert e.encode("") == [] and e.encode("ab") == lib.encode("ab", add_special_tokens=False).ids and b"ab" in e.store


# ---- op 5
def test_quality(spark, sf):
    sf = "/root/testdata/sf0.01"
    s = quality.op5_quality_classifier(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").where("held_out").collect()
    assert np.mean([r["predicted"] == r["quality"] for r in s]) >= 0.95
    assert all(0 <= r["score"] <= 1 for r in s)
    labels = spark.createDataFrame([(4, 1), (3, 0), (6, 1), (6, None)], "doc_id long, quality int")
    m = quality.fit(edge_docs(spark), labels)
    assert quality.score(edge_docs(spark), m, score_col="q").count() == 8
    none = quality.fit(edge_docs(spark), labels.limit(0))
    assert {round(r["q"], 6) for r in quality.score(edge_docs(spark), none, score_col="q").collect()} == {0.5}


# ---- op 6
def brute_lines(docs, min_chars=40, min_docs=5):
    held = defaultdict(set)
    key = lambda x: x.strip(" \t\n\r\x0b\x0c").translate(LOW)
    for d, t in docs.items():
        for x in t.split("\n"):
            if len(key(x)) >= min_chars:
                held[key(x)].add(d)
    gone = lambda d, x: len(held.get(key(x), ())) >= min_docs and max(held[key(x)]) != d
    return {d: "\n".join(x for x in t.split("\n") if not gone(d, x)) for d, t in docs.items()}


@pytest.mark.parametrize("by_join", [False, True])
def test_lines(spark, by_join):
    random.seed(5)
    lines = ["short", "A" * 39, "a" * 40, " " + "B" * 40 + "\t", "b" * 40, "é" * 40, "É" * 40, "common line of text that is long enough to count", ""]
    docs = {i: "\n".join(random.choices(lines, k=random.randint(0, 8))) for i in range(40)}
    df = spark.createDataFrame([(d, t, "e") for d, t in docs.items()], DOCS).repartition(3)
    out = linededup.dedup_lines(df, broadcast_keys=0 if by_join else 100, n_lines="total", n_dropped="gone")
    got = {r["doc_id"]: r for r in out.collect()}
    want = brute_lines(docs)
    assert {d: r["text"] for d, r in got.items()} == want
    assert all(r["total"] == docs[d].count("\n") + 1 for d, r in got.items()) and out.columns == [*df.columns, "total", "gone"]
    assert linededup.dedup_lines(edge_docs(spark)).count() == 8 and linededup.dedup_lines(edge_docs(spark).limit(0)).count() == 0


def test_runs_are_compacted(spark):
    from textfactor.llm.scratch import Scratch

    store = linededup.RunStore(spark, Scratch(spark, "runs"), fanout=2)
    fresh = [store.add(spark.createDataFrame([(h, 0, d) for h in range(d, d + 3)], "h1 long, h2 long, doc long")).count() for d in range(5)]
    assert fresh == [3, 1, 1, 1, 1] and [len(x) for x in store.levels] == [1, 0, 1]
    assert {r["h1"]: r["top"] for r in store.repeated(3).collect()} == {2: 2, 3: 3, 4: 4}


# ---- op 7
def brute_forward(model, cls):
    a = model.start * model.emit[:, cls[0]]
    for c in cls[1:]:
        a = (a @ model.move) * model.emit[:, c]
    return math.log10(a.sum())


def test_forward_is_exact():
    m = hmm.Hmm.initial(np.random.default_rng(0).integers(1, 50, hmm.CLASSES).astype(float), 3)
    m.move = np.array([[0.7, 0.2, 0.1], [0.3, 0.3, 0.4], [0.25, 0.5, 0.25]])
    cls, first = np.array([5, 9, 0, 7, 0, 1, 2, 3, 4, 0]), np.array([0, 3, 5, 10])
    got = m.log10(cls, first)
    assert np.allclose(got, [brute_forward(m, cls[a:b]) for a, b in zip(first[:-1], first[1:])])


def test_lm(spark, sf):
    docs = docs_of(spark, sf)
    toks = {d: [*WORD.findall(t.translate(LOW)), "\n"] for d, t in docs.items()}
    train = {d for d in docs if zlib.crc32(str(d).encode()) % 10}
    c = Counter(w for d in train for w in toks[d])
    n, v = sum(c.values()), len(c)
    rows = hmm.op7_lm_scoring(spark, sf).collect()
    for r in rows:
        t = toks[r["doc_id"]]
        assert r["n_tokens"] == len(t) and r["n_known"] == sum(c[w] > 0 for w in t) and r["train_tokens"] == n
        assert math.isclose(r["base_score"], sum(math.log10((c[w] + 0.1) / (n + 0.1 * (v + 1))) for w in t), rel_tol=1e-9)
    held = [r for r in rows if r["held_out"]]
    assert sum(r["score"] for r in held) > sum(r["base_score"] for r in held)
    small = hmm.score_texts(spark.read.parquet(f"{sf}/documents.parquet"), F.col("doc_id") >= 0, rounds=1, head=100)
    assert small.where("n_known <> n_tokens").count() == 0


def test_baum_welch_rises(spark, sf):
    seqs = hmm._class_sequences(spark.read.parquet(f"{sf}/documents.parquet").select("text")).cache()
    _, trace = hmm.baum_welch(seqs, np.ones(hmm.CLASSES), rounds=4, states=3)
    assert all(b > a for a, b in zip(trace, trace[1:]))


def test_lm_corner_cases(spark):
    out = hmm.score_texts(edge_docs(spark), F.lit(True), rounds=1).collect()
    assert len(out) == 8 and all(math.isfinite(r["score"]) and r["score"] < 0 for r in out)
    none = hmm.score_texts(edge_docs(spark), F.lit(False), rounds=1).collect()
    assert {r["train_tokens"] for r in none} == {0} and {r["n_known"] for r in none} == {0}
    assert hmm.score_texts(edge_docs(spark).limit(0), F.lit(True), rounds=1).count() == 0


def test_registered_oracles():
    from textfactor.llm import queries

    assert set(queries.oracle_sql()) <= set(queries.queries()) and len(queries.queries()) == 10
    json.dumps(list(queries.queries()))


def test_batches_meet_sorted_runs_in_place(spark):
    from textfactor.llm.scratch import Scratch, ordered_scans

    store = linededup.RunStore(spark, Scratch(spark, "runs"), fanout=3)
    lines = spark.range(400).select(F.col("id").alias("h1"), (F.col("id") % 7).alias("h2"), (F.col("id") * 3 % 1009).alias("doc")).repartition(3)
    for k in range(2):
        store.add(lines.where(F.col("doc") % 2 == k))
    batch = store._sorted(lines.groupBy("h1", "h2").agg(F.count("*").alias("n"), F.max("doc").alias("top")), "batch")
    with ordered_scans(spark):
        plan = store.marked(batch)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("SortMergeJoin") == 2 and "Exchange" not in plan and "Sort [" not in plan
    assert store.marked(batch).where("not known").count() == 0 and store.keys().count() == 400


def test_quality_gradients():
    """The gradients of the softmax over an average against differences of the loss."""
    from textfactor.llm import quality

    rng = np.random.default_rng(5)
    rows, out, x = rng.normal(size=(6, 4)), rng.normal(size=(2, 4)), rng.dirichlet(np.ones(6))
    for y in (0, 1):
        loss, at_out, at_hidden = quality.loss_and_gradients(rows, out, y, x)
        for i in range(2):
            for j in range(4):
                moved = out.copy()
                moved[i, j] += 1e-6
                assert abs((quality.loss_and_gradients(rows, moved, y, x)[0] - loss) / 1e-6 - at_out[i, j]) < 1e-4
        for i in range(6):
            for j in range(4):
                moved = rows.copy()
                moved[i, j] += 1e-6
                assert abs((quality.loss_and_gradients(moved, out, y, x)[0] - loss) / 1e-6 - x[i] * at_hidden[j]) < 1e-4


def test_packed_counts():
    rng = np.random.default_rng(1)
    for top in (2, 300, 70_000, 5_000_000_000):
        c = np.where(rng.random(quality.BUCKETS) < 0.01, rng.integers(1, top, quality.BUCKETS), 0)
        c[0] = top
        at, share = quality.unpack(*quality.pack(c))
        assert at.tolist() == np.flatnonzero(c).tolist() and np.allclose(share, c[at] / c.sum(), rtol=1e-5)
    at, share = quality.unpack(*quality.pack(np.eye(1, quality.BUCKETS, 0, dtype=np.int64)[0]))
    assert at.tolist() == [0] and share.tolist() == [1.0]


def test_quality_scores_by_brute_force(spark, sf):
    """Scores from the learned weights, feature by feature in plain Python."""
    from textfactor.llm import quality
    from textfactor.llm.textscan import Words

    m64 = 2**64 - 1

    def mix(x, seed):
        x = (x + 0x9E3779B97F4A7C15 * (seed + 1)) & m64
        x = ((x ^ (x >> 30)) * 0xBF58476D1CE4E5B9) & m64
        x = ((x ^ (x >> 27)) * 0x94D049BB133111EB) & m64
        return x ^ (x >> 31)

    def gram(raw, n):
        code = int.from_bytes(raw, "little")
        code = (code * 0x9E3779B1) % 2**32
        code ^= code >> 15
        code = (code * (2 * n + 0x85EBCA6B)) % 2**32
        return (code >> 8) % (quality.BUCKETS - 1) + 1

    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    model = quality.fit(docs, spark.read.parquet(f"{sf}/labels.parquet"))
    some = {r["doc_id"]: r["text"] or "" for r in docs.orderBy("doc_id").limit(25).collect()} | {-1: "", -2: "a a a b", -3: "x"}
    df = spark.createDataFrame(list(some.items()), "doc_id long, text string")
    got = {r["doc_id"]: r["score"] for r in quality.score(df, model).collect()}
    for d, t in some.items():
        words = [int(h) for h in Words(pa.array([t])).hash]
        raw = t.encode()
        buckets = [0] + [h % (quality.BUCKETS - 1) + 1 for h in words]
        for a, b in zip(words, words[1:]):
            buckets.append((int(quality._SAME) if a == b else mix((a * 0xD6E8FEB86659FD93 + b) & m64, 21)) % (quality.BUCKETS - 1) + 1)
        buckets += [gram(raw[i : i + n], n) for n in quality.GRAMS for i in range(len(raw) - n + 1)]
        z = sum(float(model.weight[b]) for b in buckets) / len(buckets)
        assert abs(got[d] - 1 / (1 + np.exp(-min(50, max(-50, z))))) < 1e-6, d


def test_lm_score_by_brute_force(spark, monkeypatch):
    """The whole score: forward recursion over the classes of the words, and each word's share of its class; rare words joined."""
    from textfactor.llm.textscan import Words

    learned, fit = [], hmm.baum_welch
    monkeypatch.setattr(hmm, "baum_welch", lambda *a: learned.append(fit(*a)) or learned[-1])
    random.seed(6)
    words = [random.choice("kqxz") + random.choice(["ing", "ed", "ion", "o", "a"]) for _ in range(30)]
    docs = {i: " ".join(random.choices(words, k=random.randint(0, 25))) for i in range(40)} | {50: None, 51: "", 52: "new ing"}
    df = spark.createDataFrame(list(docs.items()), "doc_id long, text string")
    got = {r["doc_id"]: r for r in hmm.score_texts(df, F.col("doc_id") < 30, rounds=2, head=5).collect()}
    model = learned[0][0]
    end = object()
    tokens = {d: [*(t or "").split(), end] for d, t in docs.items()}
    cls = {w: int(hmm._classes(Words(pa.array([w]), tail=hmm.TAIL))[0]) for t in tokens.values() for w in t if w is not end} | {end: 0}
    n = Counter(w for d, t in tokens.items() if d < 30 for w in t)
    in_class, kinds = Counter(), Counter()
    for w, k in n.items():
        in_class[cls[w]] += k
        kinds[cls[w]] += 1
    for d, t in tokens.items():
        share = sum(math.log10((n[w] + 0.1) / (in_class[cls[w]] + 0.1 * (kinds[cls[w]] + 1))) for w in t)
        state, log = model.start * model.emit[:, cls[t[0]]], 0.0
        for w in t[1:]:
            log += math.log10(state.sum())
            state = (state / state.sum()) @ model.move * model.emit[:, cls[w]]
        assert abs(got[d]["score"] - (share + log + math.log10(state.sum()))) < 1e-3 * len(t), d
