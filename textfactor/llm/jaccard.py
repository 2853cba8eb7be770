"""N-gram Jaccard join by vertical partitioning of the global n-gram order.

*Early count.* Two sets that link share at least ``need`` shingles, so they share the ``early`` smallest ones of these within
the first ``prefix`` shingles of either, in the order of the hashes. Exact counts of who shares which of these first
shingles leave the documents that can have a partner at all.

*Order and fragments.* Of the sets that are left, every shingle's exact number of sets is counted, and shingles of one set
drop out. The global order is by classes of this number, rare ones first, then by hash. ``FRAGMENTS`` pivots cut it where the
shingles' occurrences halve, quarter and so on.

*Candidates.* In this order two sets that link share one of the first ``shared - need + 1`` of their shared shingles. The sets
that have such a shingle in common are its list; equal lists count once.

*Overlaps.* Sets with overlapping lists go to one block; over ``BLOCK`` sets are salted over several. In
a block the overlaps of all pairs are counted fragment by fragment and summed per pair; what leaves it are the links that
join its sets, fewer than its sets. Lists that lie in several blocks, and are not one component by then, have their pairs
of blocks compared alike. Before that, while such lists are spread over many blocks, their sets are dealt to blocks anew.

So no step makes a row for a pair: a set is sent once to its block and once for each pair of blocks that stays open, which for a
list of G sets is G / BLOCK at most. Equal sets are one node from the start, so copies are never expanded. A node is the
64-bit hash of its set (about n**2 / 2**65 pairs of n different sets collide), overlaps compare 57 bits of the shingles' hashes.

Defined cases: a text without words, or null, has an empty set and links with nothing; one with fewer than k words is one
shingle; a null id never is a component's id unless all ids are null; rows that repeat are copies; an empty table gives no
row; other columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from textfactor.llm.components import LocalUnion, connected_components
from textfactor.llm.scratch import Scratch, small_side
from textfactor.llm.textscan import Words, distinct_by_row, mix, pieces, shingles

CHUNK = 2_000_000
FRAGMENTS = 8
BLOCK = 512
SPREAD = 64
ROUNDS = 4
HOPS = 2
CLASS_BITS = 57


@dataclass(frozen=True)
class Rule:
    """Sets link when ``den`` * |both| >= ``num`` * |either|; shingles have ``k`` words."""

    k: int = 5
    num: int = 80
    den: int = 100

    def need(self, n: int) -> int:
        """The least number of shingles that a set of n shares with a partner; also the least size of a partner."""
        return -(-n * self.num // self.den)

    def alone(self, n: int) -> bool:
        """Whether a set of n links with equal sets only: sets that link differ in (den - num) / num of the smaller at most."""
        return n * (self.den - self.num) < self.num

    def early(self, n: int) -> int:
        return max(1, min(n // 10, self.need(n)))

    def prefix(self, n: int) -> int:
        return min(n, n - self.need(n) + self.early(n))

    def ask(self, n: int) -> int:
        """How many of its first shingles a set of n shares with a partner of any size."""
        return self.early(self.need(n))

    def need_of_n(self) -> Column:
        return F.expr(f"cast((n * {self.num} + {self.den - 1}) div {self.den} as int)")


def _set_hash(v: np.ndarray) -> int:
    with np.errstate(over="ignore"):
        return int(mix(np.array([mix(v, 9).sum(dtype=np.uint64) + np.uint64(len(v))], np.uint64), 10).view(np.int64)[0])


def _sets(column, rule: Rule):
    h, _, bounds = shingles(Words(column), rule.k)
    return distinct_by_row(h, bounds)


def _lists(values: list[np.ndarray] | np.ndarray, counts: np.ndarray) -> pa.ListArray:
    off = np.concatenate([[0], np.cumsum(counts)]).astype(np.int32)
    flat = np.concatenate(values) if isinstance(values, list) and values else values if len(values) else np.zeros(0, np.int64)
    return pa.ListArray.from_arrays(pa.array(off), pa.array(flat.view(np.int64)))


def shared_here(owner: np.ndarray, key: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Local part of the early count: of the (owner, key) entries of n owners, what has to be told to others.

    Returns ``own`` (for each owner, its keys that another owner has too), ``hubs`` and ``sent`` (numbers of keys that it sends,
    hubs first), and the keys sent. A key of several owners is sent once, as a hub that is counted already; so no key is sent
    more than once from here, however common.
    """
    order = np.lexsort((owner, key))
    k, o = key[order], owner[order]
    start = np.flatnonzero(np.concatenate([[True], k[1:] != k[:-1]])) if len(k) else np.zeros(0, np.int64)
    many = np.diff(np.append(start, len(k))) > 1
    own = np.bincount(o[np.repeat(many, np.diff(np.append(start, len(k))))], minlength=n)
    k, o, plain = k[start], o[start], ~many
    order = np.lexsort((plain, o))
    return own, np.bincount(o[many], minlength=n), np.bincount(o, minlength=n), k[order]


def describe(rows: DataFrame, rule: Rule) -> DataFrame:
    """``row, id, n, node, text_hash, ask, own, hubs, keys`` of ``rows(id, text, text_hash)``."""
    kind = rows.schema["id"].dataType.simpleString()
    names = ["row", "id", "n", "node", "text_hash", "ask", "own", "hubs", "keys"]

    def flush(ids, hashes, ns, nodes, keys, at):
        node = np.array([0 if x is None else x for x in nodes], np.int64)
        first = np.zeros(len(node), bool)
        first[np.unique(node, return_index=True)[1]] = True
        size = np.array([len(x) if f else 0 for x, f in zip(keys, first)])
        flat = np.concatenate([x for x, f in zip(keys, first) if f] or [np.zeros(0, np.uint64)])
        own, hubs, sent, out = shared_here(np.repeat(np.arange(len(node)), size), flat, len(node))
        yield pa.RecordBatch.from_arrays(
            [
                pa.array(at + np.arange(len(node))),
                pa.chunked_array(ids).combine_chunks() if len(ids) > 1 else ids[0],
                pa.array(ns),
                pa.array(nodes, pa.int64()),
                pa.chunked_array(hashes).combine_chunks() if len(hashes) > 1 else hashes[0],
                pa.array([rule.ask(n) for n in ns], pa.int64()),
                pa.array(own),
                pa.array(hubs),
                _lists(out, sent),
            ],
            names,
        )

    def run(batches):
        at, held = TaskContext.get().partitionId() << 36, 0
        ids, hashes, ns, nodes, keys = [], [], [], [], []
        for b in (p for batch in batches for p in pieces(batch, 1)):
            v, bounds = _sets(b.column(1), rule)
            ids.append(b.column(0)), hashes.append(b.column(2))
            for u, w in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
                n = w - u
                ns.append(n)
                nodes.append(_set_hash(v[u:w]) if n else None)
                keys.append(v[u : u + rule.prefix(n)].copy() if n and not rule.alone(n) else v[:0])
                held += len(keys[-1])
            if held >= CHUNK or len(ns) >= CHUNK:
                yield from flush(ids, hashes, ns, nodes, keys, at)
                at, held = at + len(ns), 0
                ids, hashes, ns, nodes, keys = [], [], [], [], []
        if ns:
            yield from flush(ids, hashes, ns, nodes, keys, at)

    return rows.mapInArrow(
        run, f"row long, id {kind}, n long, node long, text_hash long, ask long, own long, hubs long, keys array<long>"
    )


def possible(keyed: DataFrame) -> DataFrame:
    """``text_hash``, one for every node that shares enough of its first shingles with other nodes."""
    entries = keyed.where(F.size("keys") > 0).select("row", "node", "hubs", F.posexplode("keys").alias("pos", "key"))
    entries = entries.select("key", "node", "row", (F.col("pos") < F.col("hubs")).alias("hub"))
    by = Window.partitionBy("key")
    met = entries.withColumn("a", F.min("node").over(by)).withColumn("b", F.max("node").over(by)).where("a < b and not hub")
    met = met.groupBy("row").agg(F.count("*").alias("met"))
    enough = keyed.drop("keys").join(met, "row", "left").where(F.col("own") + F.coalesce("met", F.lit(0)) >= F.col("ask"))
    return enough.where("n > 0").groupBy("node").agg(F.min("text_hash").alias("text_hash")).select("text_hash").distinct()


def sets_of(rows: DataFrame, wanted: DataFrame, rule: Rule) -> DataFrame:
    """``node, n, sh`` of the texts whose hash is wanted, read from the texts again."""

    def run(batches):
        for b in (p for batch in batches for p in pieces(batch, 0)):
            v, bounds = _sets(b.column(0), rule)
            n = np.diff(bounds)
            node = [_set_hash(v[u:w]) for u, w in zip(bounds[:-1].tolist(), bounds[1:].tolist())]
            first = np.zeros(len(node), bool)
            first[np.unique(np.array(node, np.int64), return_index=True)[1]] = True
            first &= n > 0
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.array(node, np.int64)[first]), pa.array(n[first]), _lists(v[np.repeat(first, n)], n[first])], ["node", "n", "sh"]
            )

    found = rows.join(small_side(wanted), "text_hash", "left_semi").select("text").mapInArrow(run, "node long, n long, sh array<long>")
    return found.groupBy("node").agg(F.any_value("n").alias("n"), F.any_value("sh").alias("sh"))


def in_order(full: DataFrame, rule: Rule) -> DataFrame:
    """``node, n, arr``: the shared shingles of every set as places in the global order, sorted; sets with too few of them go."""
    entries = full.select("node", "n", F.explode("sh").alias("sh"))
    times = entries.groupBy("sh").agg(F.count("*").alias("c")).where("c > 1")
    place = F.shiftleft(F.least(F.floor(F.log2("c") * 2), F.lit(63)), CLASS_BITS).bitwiseOR(F.shiftrightunsigned("sh", 64 - CLASS_BITS))
    placed = entries.join(times.select("sh", place.alias("place")), "sh").select("node", "n", "place")
    return placed.groupBy("node", "n").agg(F.array_sort(F.collect_list("place")).alias("arr")).where(F.size("arr") >= rule.need_of_n())


def pivots_of(ordered: DataFrame) -> np.ndarray:
    """Places that cut the order into ``FRAGMENTS`` of about equal occurrences; in a class of frequency hashes are uniform."""
    mass = ordered.select(F.explode("arr").alias("p")).groupBy(F.shiftright("p", CLASS_BITS).alias("c")).agg(F.count("*").alias("n")).collect()
    mass = sorted((r["c"], r["n"]) for r in mass)  # at most 64 classes
    total, done, out = sum(n for _, n in mass), 0, []
    for c, n in mass:
        for k in range(1, FRAGMENTS):
            if done < total * k / FRAGMENTS <= done + n:
                out.append((c << CLASS_BITS) + int((total * k / FRAGMENTS - done) / n * (1 << CLASS_BITS)))
        done += n
    return np.array([min(x, 2**63 - 1) for x in out], np.int64)


def lists_of(ordered: DataFrame, rule: Rule) -> DataFrame:
    """``list, node, c``: the sets, c of them, that share a shingle of their prefix; of equal lists one."""
    first = F.size("arr") - rule.need_of_n() + 1
    keys = ordered.select("node", F.explode(F.slice("arr", F.lit(1), first.cast("int"))).alias("list"))
    marks = [F.bit_xor(F.xxhash64(F.lit(s), "node")).alias(f"x{s}") for s in (1, 2)]
    lists = keys.groupBy("list").agg(F.count("*").alias("c"), *marks).where("c > 1")
    lists = lists.groupBy("c", "x1", "x2").agg(F.min("list").alias("list")).select("list", "c")
    return keys.join(lists, "list")


def homes(members: DataFrame, turn: int) -> DataFrame:
    """``node, block``. Sets whose lists overlap meet: each takes the longest list that it comes to over ``HOPS`` sets between. The
    sets of a list so taken are salted over blocks of about ``BLOCK``."""
    best = members.groupBy("node").agg(F.max(F.struct("c", "list")).alias("b"))
    for _ in range(HOPS):
        lists = members.select("node", "list").join(best, "node").groupBy("list").agg(F.max("b").alias("b"))
        best = members.select("node", "list").join(lists, "list").groupBy("node").agg(F.max("b").alias("b"))
    best = best.select("node", F.col("b.list").alias("list"))
    sizes = best.groupBy("list").agg(F.ceil(F.count("*") / BLOCK).alias("parts"))
    salt = F.pmod(F.xxhash64(F.lit(turn), "node"), F.col("parts"))
    return best.join(sizes, "list").select("node", F.xxhash64("list", salt).alias("block"))


def add_overlaps(both: np.ndarray, at: np.ndarray, values: np.ndarray, width: int = 4096) -> None:
    """Add to ``both`` the pairwise overlaps of the sets of one fragment, given as entries (set, value)."""
    order = np.argsort(values, kind="stable")
    v, at = values[order], at[order]
    new = np.concatenate([[True], v[1:] != v[:-1]]) if len(v) else np.zeros(0, bool)
    col = np.cumsum(new) - 1
    keep = np.bincount(col)[col] > 1 if len(v) else new
    if not keep.any():
        return
    at, col = at[keep], col[keep]
    col = np.cumsum(np.concatenate([[True], col[1:] != col[:-1]])) - 1
    used, row = np.unique(at, return_inverse=True)
    for a in range(0, int(col[-1]) + 1, width):
        u, w = np.searchsorted(col, [a, a + width])
        part = np.zeros((len(used), min(width, int(col[-1]) + 1 - a)), np.float32)
        part[row[u:w], col[u:w] - a] = 1
        both[np.ix_(used, used)] += (part @ part.T).astype(np.int32)


class _Group:
    """The sets that meet in one task of ``block_links``: sizes, roots and overlaps so far."""

    def __init__(self):
        self.index, self.n, self.root, self.both = {}, [], [], np.zeros((0, 0), np.int32)

    def add(self, node, n, root, counts, values):
        at = np.empty(len(node), np.int64)
        for i, x in enumerate(node.tolist()):
            if x not in self.index:
                self.index[x] = len(self.index)
                self.n.append(int(n[i])), self.root.append(int(root[i]))
            at[i] = self.index[x]
        if len(self.index) > len(self.both):
            wider = np.zeros((len(self.index),) * 2, np.int32)
            wider[: len(self.both), : len(self.both)] = self.both
            self.both = wider
        if len(self.index) > 1:
            add_overlaps(self.both, np.repeat(at, counts), values)

    def links(self, rule: Rule) -> tuple[np.ndarray, np.ndarray]:
        if len(self.index) < 2:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        roots, at = np.unique(np.array(self.root, np.int64), return_inverse=True)
        n, union = np.array(self.n, np.int64), LocalUnion(len(roots))
        for a in range(0, len(n), 64):
            both = self.both[a : a + 64].astype(np.int64)
            r, c = np.nonzero(rule.den * both >= rule.num * (n[a : a + 64, None] + n[None, :] - both))
            union.add(at[r + a], at[c])
        far = union.label != np.arange(len(roots))
        return roots[far], roots[union.label[far]]


def block_links(places: DataFrame, ordered: DataFrame, pivots: np.ndarray, rule: Rule) -> DataFrame:
    """``u, v``: links that join the roots of ``places(i, j, node, root)``, from all pairs of sets that meet in a pair of blocks.

    The sets of a task come fragment by fragment, so it holds one fragment of them and the overlaps of its pairs.
    """

    def cut(batches):
        for batch in batches:
            for b in (batch.slice(a, 64) for a in range(0, batch.num_rows, 64)):
                arr = b.column(5)
                flat, off = arr.flatten().to_numpy(), arr.offsets.to_numpy() - arr.offsets[0].as_py()
                rows = [flat[u:w] for u, w in zip(off[:-1].tolist(), off[1:].tolist())]
                edge = np.array([np.concatenate([[0], np.searchsorted(x, pivots), [len(x)]]) for x in rows])
                parts = edge.shape[1] - 1
                heads = [pa.array(np.repeat(b.column(c).to_numpy(), parts)) for c in range(5)]
                size = np.diff(edge, axis=1).ravel()
                yield pa.RecordBatch.from_arrays([*heads, pa.array(np.tile(np.arange(parts), len(rows))), _lists(flat, size)], names)

    names = ["i", "j", "node", "root", "n", "part", "sh"]
    kinds = ", ".join(f"{c} long" for c in names[:-1]) + ", sh array<long>"
    rows = places.join(ordered, "node").select("i", "j", "node", "root", "n", "arr").mapInArrow(cut, kinds)
    rows = rows.repartition("i", "j").sortWithinPartitions("i", "j", "part")

    def run(batches):
        group, now, held = _Group(), None, []

        def settle():
            if held:
                cols = [np.concatenate(x) for x in zip(*held)]
                group.add(*cols)
                held.clear()

        for b in batches:
            i, j, node, root, n, part = (b.column(c).to_numpy() for c in range(6))
            sh = b.column(6)
            flat, off = sh.flatten().to_numpy(), sh.offsets.to_numpy()
            off = off - off[0]
            change = np.concatenate([[True], (i[1:] != i[:-1]) | (j[1:] != j[:-1]) | (part[1:] != part[:-1])])
            cuts = np.append(np.flatnonzero(change), len(i)).tolist()
            us, vs = [], []
            for a, e in zip(cuts[:-1], cuts[1:]):
                key = (int(i[a]), int(j[a]), int(part[a]))
                if key != now:
                    settle()
                    if now is not None and key[:2] != now[:2]:
                        u, v = group.links(rule)
                        us.append(u), vs.append(v)
                        group = _Group()
                    now = key
                held.append((node[a:e], n[a:e], root[a:e], np.diff(off[a : e + 1]), flat[off[a] : off[e]]))
            if us:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(us)), pa.array(np.concatenate(vs))], ["u", "v"])
        settle()
        u, v = group.links(rule)
        yield pa.RecordBatch.from_arrays([pa.array(u), pa.array(v)], ["u", "v"])

    return rows.mapInArrow(run, "u long, v long")


def _rooted(nodes: DataFrame, roots: DataFrame) -> DataFrame:
    return nodes.join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))


def _open(members: DataFrame, home: DataFrame, roots: DataFrame) -> DataFrame:
    """``list, node, c, block, root`` of the lists that lie in several blocks and are not one component."""
    known = _rooted(members.join(home, "node"), roots)
    spread = known.groupBy("list").agg(
        F.min("root").alias("r"), F.max("root").alias("s"), F.min("block").alias("a"), F.max("block").alias("b")
    )
    return known.join(spread.where("r < s and a < b").select("list"), "list", "left_semi")


def _block_pairs(still: DataFrame) -> DataFrame:
    """``i, j``: pairs of blocks that an open list lies in, but for blocks that are of one and the same component in it."""
    sides = still.groupBy("list", "block").agg(F.min("root").alias("r"), F.max("root").alias("s"))
    a, b = (sides.select("list", *(F.col(c).alias(c + x) for c in ("block", "r", "s"))) for x in "12")
    both = a.join(b, "list").where("block1 < block2 and not (r1 = s1 and r2 = s2 and r1 = r2)")
    return both.select(F.col("block1").alias("i"), F.col("block2").alias("j")).distinct()


def _links(ordered: DataFrame, rule: Rule, scratch: Scratch) -> DataFrame:
    """``node, root`` of all sets that link with another."""
    pivots = pivots_of(ordered)
    members = scratch.save(lists_of(ordered, rule), "members")
    edges = roots = None
    still = members
    for turn in range(ROUNDS):
        home = homes(still, turn)
        rooted = home.withColumn("root", F.col("node")) if roots is None else _rooted(home, roots)
        home = scratch.save(rooted, "homes")
        found = block_links(home.select(F.col("block").alias("i"), F.col("block").alias("j"), "node", "root"), ordered, pivots, rule)
        edges = scratch.save(found if edges is None else edges.unionByName(found), "links")
        roots = scratch.save(connected_components(edges, scratch), "roots")
        still = scratch.save(_open(still.select("list", "node", "c"), home.select("node", "block"), roots), "open")
        lists = still.groupBy("list").agg(F.countDistinct("block").alias("b"), F.count("*").alias("n"))
        work, rows = lists.agg(F.coalesce(F.sum(F.col("b") * F.col("b")), F.lit(0)), F.coalesce(F.sum("n"), F.lit(0))).first()
        if work <= SPREAD * rows:
            break
    if not rows:
        return roots
    pairs = scratch.save(_block_pairs(still), "block-pairs")
    inside = still.select("node", "root", "block").distinct()
    places = inside.join(pairs, F.col("block") == F.col("i")).unionByName(inside.join(pairs, F.col("block") == F.col("j")))
    found = block_links(places.select("i", "j", "node", "root"), ordered, pivots, rule)
    return connected_components(scratch.save(edges.unionByName(found), "links"), scratch)


def link_documents(docs: DataFrame, rule: Rule = Rule(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``row, id, text_hash, n_shingles, component, component_id`` for every row.

    ``component`` is the same for all rows that links connect, null without words; ``component_id`` is the smallest id among them.
    """
    scratch = Scratch(docs.sparkSession, "jaccard")
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), F.xxhash64(F.col(text_col)).alias("text_hash"))
    keyed = scratch.save(describe(rows, rule), "keyed")
    wanted = scratch.save(possible(keyed), "wanted")
    scratch.sweep()
    full = scratch.save(sets_of(rows, wanted, rule), "full")
    ordered = scratch.save(in_order(full, rule), "ordered")
    scratch.drop(full)
    scratch.sweep()
    roots = scratch.save(_links(ordered, rule, scratch), "components")
    scratch.drop(ordered)

    sets = keyed.select("row", "id", "text_hash", F.col("n").alias("n_shingles"), "node")
    own = sets.where(F.col("node").isNotNull()).groupBy("node").agg(F.min("id").alias("least"))
    own = own.join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    best = own.groupBy("root").agg(F.min("least").alias("component_id"))
    named = own.join(best, "root").select("node", F.col("root").alias("component"), "component_id")
    out = sets.where(F.col("node").isNotNull()).join(named, "node").drop("node")
    empty = sets.where(F.col("node").isNull()).withColumn("component", F.lit(None).cast("long")).withColumn("component_id", F.col("id"))
    return out.unionByName(empty.drop("node")).select("row", "id", "text_hash", "n_shingles", "component", F.coalesce("component_id", "id").alias("component_id"))


def op10_ngram_jaccard_join(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    out = link_documents(docs, Rule(k=3, num=90, den=100))
    return out.select(F.col("id").alias("doc_id"), "n_shingles", "component_id")
