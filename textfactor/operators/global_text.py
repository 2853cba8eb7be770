"""One long text, whose positions are spread over the cluster: suffix ranks, neighbours, common prefixes and factors.

Everything is a range sort, an equi-join on positions or ranks, or a per-partition scan. What must cross partition borders
(counts, last values) is one row per partition, taken to the driver and handed back. Positions are 1-based.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textfactor.functions import kernels as K
from textfactor.operators import order, windows
from textfactor.plans.scratch import Scratch

CELL = 1 << 14
PACK = 1 << 14
LARGE = 1 << 16


def _codes(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)


def alphabet(blocks: DataFrame) -> list[int]:
    """The distinct symbols in order; at most the number of code points."""

    def run(it):
        seen = np.zeros(0x110000, bool)
        for b in it:
            for body in b.column(0).to_pylist():
                seen[np.frombuffer(body.encode("utf-32-le", "surrogatepass"), np.uint32)] = True
        yield pa.RecordBatch.from_arrays([pa.array(np.flatnonzero(seen))], ["sym"])

    return sorted(r["sym"] for r in blocks.select("body").mapInArrow(run, "sym long").distinct().collect())


def packed_symbols(blocks: DataFrame, symbols: list[int]) -> tuple[DataFrame, int, int]:
    """``pos, sym, key``: every position with its next ``width`` symbols in one integer; also ``width`` and bits per symbol.

    The text is dealt to cells of a grid; a cell also gets the head of the next one.
    """
    bits = max(1, (len(symbols)).bit_length())
    width = max(1, 62 // bits)
    kinds = np.array(symbols, np.int64)

    def cells(it):
        for b in it:
            out = ([], [], [])
            for start, body in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                at, n = start - 1, len(body)
                for cell in range(at // CELL, (at + n - 1) // CELL + 1 if n else at // CELL):
                    low, high = max(at, cell * CELL), min(at + n, (cell + 1) * CELL)
                    piece = body[low - at : high - at]
                    out[0].append(cell), out[1].append(low - cell * CELL), out[2].append(piece)
                    if cell and low - cell * CELL < width:
                        out[0].append(cell - 1), out[1].append(low - cell * CELL + CELL), out[2].append(piece[: width - (low - cell * CELL)])
            yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.string())], ["cell", "off", "piece"])

    def pack(key, pdf):
        pdf = pdf.sort_values("off")
        sym = _codes("".join(pdf["piece"]))
        code = np.searchsorted(kinds, sym) + 1
        n = int(min(CELL, len(sym)))
        k = np.zeros(n, np.int64)
        for j in range(width):
            k <<= bits
            m = min(n, len(code) - j)
            if m > 0:
                k[:m] |= code[j : j + m]
        import pandas as pd

        return pd.DataFrame({"pos": key[0] * CELL + np.arange(n) + 1, "sym": sym[:n], "key": k})

    dealt = blocks.select("start", "body").mapInArrow(cells, "cell long, off long, piece string")
    return dealt.groupBy("cell").applyInPandas(pack, "pos long, sym long, key long"), width, bits


def _sorted_scan(df: DataFrame, keys: list[str], schema: str, scan) -> DataFrame:
    """``scan(part, batches)`` over range partitions sorted by ``keys``; equal keys share a partition."""

    def run(it):
        yield from scan(TaskContext.get().partitionId(), it)

    return df.repartitionByRange(*keys).sortWithinPartitions(*keys).mapInArrow(run, schema)


class GlobalText:
    """Arrays of one text given as blocks ``(start, body)``; tables are made when first asked for.

    ``levels[k]``: ``pos, rank, alone`` of the positions that doubling round k worked on, those whose rank was not unique before. A
    position that a level lacks had a unique rank already; so a level is written once and holds what changed only.
    """

    def __init__(self, blocks: DataFrame):
        self.scratch = Scratch(blocks.sparkSession, "global")
        self.blocks = self.scratch.save(blocks.select("start", "body"), "blocks")
        self.kinds = alphabet(self.blocks)
        table, self.width, self.bits = packed_symbols(self.blocks, self.kinds)
        self.symbols = self.scratch.save(table, "symbols")
        self.n = self.blocks.agg(F.max(F.col("start") + F.length("body") - 1)).first()[0] or 0
        self.levels = order.levels(self.symbols, self.n, self.width, self.scratch)
        self.ranks = self._unique()
        self.made: dict[str, DataFrame] = {}

    def _once(self, name: str, make) -> DataFrame:
        """A table that several results start from, written when first asked for."""
        if name not in self.made:
            self.made[name] = self.scratch.save(make(), name)
        return self.made[name]

    def _unique(self) -> DataFrame:
        """``pos, rank`` of all positions, each from the round that made its rank unique."""
        out = None
        for level in self.levels:
            mine = level.where("alone").select("pos", "rank")
            out = mine if out is None else out.unionByName(mine)
        return out

    def _texts(self) -> DataFrame:
        return self._once("texts", lambda: windows.text_parts(self.blocks, self.kinds, self.n))

    def common(self, pairs: DataFrame) -> DataFrame:
        """``i, j, n`` of ``pairs(i, j)``: the length of the common prefix of the suffixes at two different positions i and j."""
        return self._common(windows.dealt(pairs, self.n))

    def _common(self, dealt: DataFrame) -> DataFrame:
        tables, out, rest = windows.compare(dealt, self._texts(), self.kinds, self.n, self.scratch)
        long = None
        if rest is not None:
            long, done = self._common_by_levels(rest)
            out = out.unionByName(done)
        out = self.scratch.save(out, "common")
        for x in [*tables, *([long] if long is not None else [])]:
            self.scratch.drop(x)
        return out

    def _common_by_levels(self, now: DataFrame) -> tuple[DataFrame, DataFrame]:
        """``i, j, n`` of pairs that agree on their first ``n`` symbols, from the ranks of all rounds, and the table that it reads."""
        last = None
        for k in range(len(self.levels) - 1, -1, -1):
            level = self.levels[k].select("pos", "rank")
            a = level.select(F.col("pos").alias("x"), F.col("rank").alias("ra"))
            b = level.select(F.col("pos").alias("y"), F.col("rank").alias("rb"))
            now = now.withColumn("x", F.col("i") + F.col("n")).withColumn("y", F.col("j") + F.col("n")).join(a, "x", "left").join(b, "y", "left")
            more = F.when(F.col("ra") == F.col("rb"), self.width << k).otherwise(0)
            now = self.scratch.save(now.select("i", "j", (F.col("n") + more).alias("n")), "agreeing")
            if last is not None:
                self.scratch.drop(last)
            last = now
        keys = self.symbols.select(F.col("pos").alias("x"), F.col("key").alias("ka"))
        keys2 = keys.select(F.col("x").alias("y"), F.col("ka").alias("kb"))
        now = now.withColumn("x", F.col("i") + F.col("n")).withColumn("y", F.col("j") + F.col("n")).join(keys, "x", "left").join(keys2, "y", "left")
        same = sum((F.when(F.shiftright("ka", self.bits * j) == F.shiftright("kb", self.bits * j), 1).otherwise(0) for j in range(1, self.width)), F.lit(0))
        more = F.when(F.col("ka").isNull() | F.col("kb").isNull(), 0).otherwise(same)
        return last, now.select("i", "j", (F.col("n") + more).cast("long").alias("n"))

    def suffix_array(self) -> DataFrame:
        """``rank, pos``; the sentinel, rank 1, is left out."""
        return self.ranks.select((F.col("rank") + 2).alias("rank"), "pos")

    def phi(self) -> DataFrame:
        """``pos, phi`` of all positions but the first in suffix order."""
        up = self.ranks.select((F.col("rank") + 1).alias("rank"), F.col("pos").alias("phi"))
        return self.ranks.join(up, "rank").select("pos", "phi")

    def irreducible(self) -> DataFrame:
        """``pos, phi, plcp`` where the symbols before position and neighbour differ, or one has none."""
        return self._once("irreducible", self._irreducible)

    def _irreducible(self) -> DataFrame:
        dealt = self.scratch.save(windows.neighbours(self.ranks, self._texts(), self.kinds, self.n), "neighbours")
        return self._common(dealt).select(F.col("i").alias("pos"), F.col("j").alias("phi"), F.col("n").alias("plcp"))

    def reach_steps(self) -> DataFrame:
        """``part, pos, reach`` in text order; ``part`` numbers the range partitions."""

        def scan(part, it):
            top = -1
            for b in it:
                pos, n = b.column(0).to_numpy(), b.column(1).to_numpy()
                reach = pos + n
                high = np.maximum.accumulate(np.append(top, reach))
                grow = (reach > high[:-1]) & (n > 0)
                top = int(high[-1])
                yield pa.RecordBatch.from_arrays([pa.array(np.full(grow.sum(), part, np.int32)), pa.array(pos[grow]), pa.array(reach[grow])], ["part", "pos", "reach"])

        rows = self.irreducible().select("pos", "plcp")
        got = self.scratch.save(_sorted_scan(rows, ["pos"], "part int, pos long, reach long", scan), "steps")
        return self._after(got, lambda before: F.col("reach") > before)

    def _after(self, steps: DataFrame, keep) -> DataFrame:
        tops = steps.groupBy("part").agg(F.max("reach").alias("top")).orderBy("part").collect()
        before, top = [], -1
        for r in tops:
            before.append((r["part"], top))
            top = max(top, r["top"])
        before = steps.sparkSession.createDataFrame(before, "part int, before long")
        return steps.join(F.broadcast(before), "part").where(keep(F.col("before"))).drop("before")

    def factors(self, min_len: int = 2) -> DataFrame:
        """``dst, len, src``: cut at islands, which no reach crosses, solve packs of islands, look the sources up."""
        steps = self.scratch.save(self.reach_steps(), "reach")
        names = ["part", "pos", "reach", "island", "begin"]

        def scan(part, it):
            last, n, row, open_row = None, 0, 0, 0
            for b in it:
                pos, reach = b.column(0).to_numpy(), b.column(1).to_numpy()
                if not len(pos):
                    continue
                before = np.append(last if last is not None else pos[0] + 1, reach[:-1])
                opens = pos >= before
                island = n + np.cumsum(opens)
                at = np.maximum.accumulate(np.where(opens, row + np.arange(len(pos)), -1))
                begin = np.where(at >= 0, at, open_row)
                n, last, row, open_row = int(island[-1]), int(reach[-1]), row + len(pos), int(begin[-1])
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(pos), part, np.int32)), *(pa.array(x.astype(np.int64)) for x in (pos, reach, island, begin))], names)

        tall = steps.where(F.col("reach") - F.col("pos") >= min_len).select("pos", "reach")
        got = self.scratch.save(_sorted_scan(tall, ["pos"], "part int, pos long, reach long, island long, begin long", scan), "islands")
        # packs of islands with about PACK steps; the first island of a partition may have begun before it
        base, rows, last, opened = [], 0, -1, 0
        ends = got.groupBy("part").agg(F.min("pos").alias("p"), F.max("reach").alias("q"), F.count("*").alias("n"), F.max(F.struct("island", "begin")).alias("k"))
        for r in ends.orderBy("part").collect():
            first = rows if r["p"] >= last else opened
            base.append((r["part"], rows, first))
            opened = rows + r["k"]["begin"] if r["k"]["island"] else first
            rows, last = rows + r["n"], r["q"]
        base = got.sparkSession.createDataFrame(base, "part int, rows long, first long")
        begun = F.when(F.col("island") == 0, F.col("first")).otherwise(F.col("rows") + F.col("begin"))
        steps = got.join(F.broadcast(base), "part").select(begun.alias("island"), "pos", "reach")
        packed, known = self._split_large(self.scratch.save(steps, "steps"), min_len)

        def solve(pdf):
            import pandas as pd

            pdf = pdf.sort_values("pos")
            d, size = K.rounds_on_steps(pdf["pos"].to_numpy(np.int64), pdf["reach"].to_numpy(np.int64), min_len)
            return pd.DataFrame({"dst": d, "len": size})

        refs = self.scratch.save(packed.groupBy("pack").applyInPandas(solve, "dst long, len long").unionByName(known), "refs")
        # the neighbours are needed at the starts of factors only, so the ranks of these are looked up first, not all neighbours made
        up = self.ranks.select((F.col("rank") + 1).alias("rank"), F.col("pos").alias("src"))
        return refs.join(self.ranks.withColumnRenamed("pos", "dst"), "dst").join(up, "rank").select("dst", "len", "src")

    def _split_large(self, steps: DataFrame, min_len: int) -> tuple[DataFrame, DataFrame]:
        """``pack, pos, reach`` in packs that a task solves, and the factors ``dst, len`` found on the way.

        The leftmost largest value of a segment is a factor and parts it in two; so islands of over ``LARGE`` steps are split until
        no segment has more, all of them at once in a round. A segment's largest value is one row of a grouped maximum.
        """
        sizes = steps.groupBy("island").agg(F.count("*").alias("n"))
        large = sizes.where(F.col("n") > LARGE).select("island")
        pack = F.floor(F.col("island") / PACK)
        known = steps.sparkSession.createDataFrame([], "dst long, len long")
        if not large.limit(1).count():
            return steps.select(pack.alias("pack"), "pos", "reach"), known
        small = steps.join(large, "island", "left_anti").select(pack.alias("pack"), "pos", "reach")
        # segments are named by negative numbers: their first step's place in the text, or their island's number
        first = -F.col("island") - 1
        now = self.scratch.save(steps.join(large, "island").select(first.alias("pack"), "pos", "reach"), "segments")
        for _ in range(64):
            best = now.groupBy("pack").agg(F.max(F.struct((F.col("reach") - F.col("pos")).alias("v"), (-F.col("pos")).alias("p"))).alias("b"))
            best = best.where(F.col("b.v") >= min_len).select("pack", (-F.col("b.p")).alias("d"), F.col("b.v").alias("len"))
            best = self.scratch.save(best, "largest")
            known = known.unionByName(best.select(F.col("d").alias("dst"), "len"))
            both = now.join(best.withColumn("e", F.col("d") + F.col("len")).drop("len"), "pack")
            right = (-F.col("e") - (1 << 48)).alias("pack")
            left = both.where("pos < d").select("pack", "pos", F.least("reach", "d").alias("reach"))
            # behind a factor a segment begins with what the last step before reaches
            begin = both.where("pos <= e").groupBy("e").agg(F.max("reach").alias("reach"), F.max("pos").alias("last")).where("last < e")
            parts = left.unionByName(both.where("pos >= e").select(right, "pos", "reach")).unionByName(begin.select(right, F.col("e").alias("pos"), "reach"))
            parts = self.scratch.save(parts.where(F.col("reach") - F.col("pos") >= min_len), "segments")
            large = parts.groupBy("pack").agg(F.count("*").alias("n")).where(F.col("n") > LARGE).select("pack")
            large = self.scratch.save(large, "large")
            small = small.unionByName(parts.join(large, "pack", "left_anti"))
            now = parts.join(large, "pack", "left_semi")
            if not large.limit(1).count():
                return small, known
        return small.unionByName(now), known

    def plcp(self) -> DataFrame:
        """``pos, plcp`` of all positions, filled from the last irreducible reach, by range partition."""

        def scan(part, it):
            top = -1
            for b in it:
                pos = b.column(0).to_numpy()
                reach = b.column(1).fill_null(-1).to_numpy()
                high = np.maximum.accumulate(np.append(top, reach))[1:]
                top = int(high[-1]) if len(high) else top
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(pos), part, np.int32)), pa.array(pos), pa.array(high)], ["part", "pos", "reach"])

        known = self.irreducible().select("pos", (F.col("pos") + F.col("plcp")).alias("reach"))
        rows = self.symbols.select("pos").join(known, "pos", "left")
        got = self.scratch.save(_sorted_scan(rows, ["pos"], "part int, pos long, reach long", scan), "plcp")
        tops, before, top = got.groupBy("part").agg(F.max("reach").alias("top")).orderBy("part").collect(), [], -1
        for r in tops:
            before.append((r["part"], top))
            top = max(top, r["top"])
        before = got.sparkSession.createDataFrame(before, "part int, before long")
        return got.join(F.broadcast(before), "part").select("pos", F.greatest(F.lit(0), F.greatest("reach", "before") - F.col("pos")).alias("plcp"))

    def _nearest_smaller(self, descending: bool) -> DataFrame:
        """``pos, src``: the nearest suffix before each one in suffix order (behind it, if descending) that starts earlier in the text.

        A partition keeps the stack of its suffixes that no later one undercuts. What it can't answer goes to the last partition before
        it that has a smaller start, found from the least starts, one number for each partition.
        """
        names = ["part", "pos", "src", "left"]

        def scan(part, it):
            stack = np.zeros(0, np.int64)
            for b in it:
                v = b.column(1).to_numpy()
                if not len(v):
                    continue
                near = K._nearest_smaller(v, np.zeros(len(v), np.int64))
                src = np.where(near >= 0, v[np.maximum(near, 0)], -1)
                open_ = np.flatnonzero(near < 0)
                k = np.searchsorted(stack, v[open_]) - 1
                src[open_] = np.where(k >= 0, stack[np.maximum(k, 0)] if len(stack) else -1, -1)
                low = np.minimum.accumulate(v[::-1])[::-1]
                stack = np.concatenate([stack[stack < low[0]], v[v == low]])
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(v), part, np.int32)), pa.array(v), pa.array(src, mask=src < 0), pa.array(np.zeros(len(v), bool))], names)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(stack), part, np.int32)), pa.array(stack), pa.array(stack), pa.array(np.ones(len(stack), bool))], names)

        rows = self.ranks.select((F.col("rank") * (-1 if descending else 1)).alias("order"), "pos")
        got = self.scratch.save(_sorted_scan(rows, ["order"], "part int, pos long, src long, left boolean", scan), "smaller")
        least = [(r["part"], r["m"]) for r in got.groupBy("part").agg(F.min("pos").alias("m")).orderBy("part").collect()]
        parts, lows = np.array([p for p, _ in least]), np.array([m for _, m in least], np.int64)

        def route(it):
            for b in it:
                part, v = b.column(0).to_numpy(), b.column(1).to_numpy()
                to = np.full(len(v), -1, np.int32)
                for p in np.unique(part):
                    k = int(np.searchsorted(parts, p))
                    # the last least start below v: the minima from the right, which ascend to the left
                    tail = np.minimum.accumulate(lows[:k][::-1])
                    at = np.searchsorted(-tail, -v[part == p], "right")
                    to[part == p] = np.where(at < k, parts[np.maximum(k - 1 - at, 0)] if k else -1, -1)
                yield pa.RecordBatch.from_arrays([pa.array(to), pa.array(v)], ["part", "pos"])

        asked = got.where("NOT left AND src IS NULL").select("part", "pos").mapInArrow(route, "part int, pos long").where("part >= 0")

        def answer(ask, stack):
            import pandas as pd

            top = np.sort(stack["pos"].to_numpy())
            k = np.searchsorted(top, ask["pos"].to_numpy()) - 1
            return pd.DataFrame({"pos": ask["pos"], "src": top[k] if len(top) else k})

        late = asked.groupBy("part").cogroup(got.where("left").select("part", "pos").groupBy("part")).applyInPandas(answer, "pos long, src long")
        sources = self.scratch.save(got.where("NOT left AND src IS NOT NULL").select("pos", "src").unionByName(late), "sources")
        self.scratch.drop(got)
        return sources

    def previous_factors(self) -> DataFrame:
        """``pos, lpf, src``: the longest factor at every position that occurs earlier, and its smaller nearest source.

        Only where a source does not follow the one of the position before, or the symbols before differ, prefixes are compared; the other
        lengths follow from the last of these.
        """
        sides = []
        sym = self.symbols.select("pos", "sym")
        for k, descending in ((1, False), (2, True)):
            near = self._nearest_smaller(descending)
            before = near.join(sym, "pos").select((F.col("pos") + 1).alias("pos"), (F.col("src") + 1).alias("next"), F.col("sym").alias("s1"))
            own = near.join(before, "pos", "left").join(sym.select((F.col("pos") + 1).alias("src"), F.col("sym").alias("s2")), "src", "left")
            fresh = own.where("next IS NULL OR next <> src OR s2 IS NULL OR s1 <> s2").select(F.col("pos").alias("i"), F.col("src").alias("j"))
            known = self.common(self.scratch.save(fresh, "pairs")).select(F.col("i").alias("pos"), (F.col("i") + F.col("n")).alias(f"reach{k}"))
            sides.append(near.withColumnRenamed("src", f"src{k}").join(known, "pos", "left"))
        rows = self.symbols.select("pos").join(sides[0], "pos", "left").join(sides[1], "pos", "left").select("pos", "src1", "reach1", "src2", "reach2")
        names = ["part", "pos", "src1", "reach1", "src2", "reach2"]

        def scan(part, it):
            last = [-1, -1]
            for b in it:
                out = [pa.array(np.full(b.num_rows, part, np.int32)), b.column(0)]
                for k in (0, 1):
                    src, reach = b.column(1 + 2 * k), b.column(2 + 2 * k).fill_null(-1).to_numpy()
                    known = np.maximum.accumulate(np.where(reach >= 0, np.arange(len(reach)), -1))
                    filled = np.where(known >= 0, reach[np.maximum(known, 0)], last[k])
                    last[k] = int(filled[-1]) if len(filled) else last[k]
                    out += [src, pa.array(filled, mask=filled < 0)]
                yield pa.RecordBatch.from_arrays(out, names)

        got = self.scratch.save(_sorted_scan(rows, ["pos"], "part int, pos long, src1 long, reach1 long, src2 long, reach2 long", scan), "reaches")
        ends = got.groupBy("part").agg(F.max_by("reach1", "pos").alias("a"), F.max_by("reach2", "pos").alias("b")).orderBy("part").collect()
        carry, a, b = [], None, None
        for r in ends:
            carry.append((r["part"], a, b))
            a, b = (r["a"] if r["a"] is not None else a), (r["b"] if r["b"] is not None else b)
        carry = got.sparkSession.createDataFrame(carry, "part int, a long, b long")
        size = lambda k, c: F.when(F.col(f"src{k}").isNull(), 0).otherwise(F.coalesce(f"reach{k}", c) - F.col("pos"))
        both = got.join(F.broadcast(carry), "part").select("pos", "src1", "src2", size(1, "a").alias("n1"), size(2, "b").alias("n2"))
        second = (F.col("n2") > F.col("n1")) | ((F.col("n2") == F.col("n1")) & F.col("src2").isNotNull() & (F.col("src1").isNull() | (F.col("src2") < F.col("src1"))))
        lpf = F.greatest("n1", "n2")
        return both.select("pos", lpf.alias("lpf"), F.when(lpf > 0, F.when(second, F.col("src2")).otherwise(F.col("src1"))).alias("src"))

    def previous(self) -> DataFrame:
        """``previous_factors``, written once."""
        return self._once("previous", self.previous_factors)

    def unidirectional(self, min_len: int = 2) -> DataFrame:
        """``dst, len, src`` of the greedy parse with earlier sources.

        In every cell all positions know the phrase start at which their path leaves it; few such starts differ. On these the
        path from the first position is marked by doubling, and each cell then follows its own part of it.
        """
        import pandas as pd

        take = F.when(F.col("lpf") >= min_len, F.col("lpf")).otherwise(1)
        steps = self.scratch.save(self.previous().select(F.expr(f"(pos - 1) div {CELL}").alias("cell"), "pos", take.alias("n"), "src"), "steps")

        def leaves(pdf):
            """Positions in order, their next phrase starts, and where the path from each leaves the cell."""
            pdf = pdf.sort_values("pos")
            pos, low = pdf["pos"].to_numpy(), int(pdf["pos"].min())
            nxt = pos + pdf["n"].to_numpy()
            end, leave = low + len(pos), nxt.copy()
            todo = np.flatnonzero(leave < end)
            while len(todo):
                leave[todo] = leave[leave[todo] - low]
                todo = todo[leave[todo] < end]
            return pdf, low, nxt, leave

        def exits(key, pdf):
            return pd.DataFrame({"pos": np.unique(leaves(pdf)[3])})

        nodes = steps.select("cell", "pos", "n").groupBy("cell").applyInPandas(exits, "pos long").distinct()
        nodes = nodes.unionByName(steps.sparkSession.range(1).select(F.lit(1).cast("long").alias("pos"))).distinct()
        nodes = self.scratch.save(nodes.select(F.expr(f"(pos - 1) div {CELL}").alias("cell"), "pos"), "nodes")

        def hop(key, mine, pdf):
            if not len(mine) or not len(pdf):
                return pd.DataFrame({"a": [], "b": []}, dtype="int64")
            _, low, _, leave = leaves(pdf)
            at = mine["pos"].to_numpy()
            at = at[at < low + len(leave)]  # a path may leave at the end of the text
            return pd.DataFrame({"a": at, "b": leave[at - low]})

        jump = self.scratch.save(nodes.groupBy("cell").cogroup(steps.select("cell", "pos", "n").groupBy("cell")).applyInPandas(hop, "a long, b long"), "jump")
        marked = self.scratch.save(jump.where("a = 1").select("a"), "marked")
        for k in range(64):
            more = marked.join(jump, "a").select(F.col("b").alias("a"))
            old, marked = marked, self.scratch.save(marked.unionByName(more).distinct(), "marked")
            self.scratch.drop(old)
            if marked.count() < 1 << (k + 1):
                break
            far = jump.select(F.col("a").alias("b"), F.col("b").alias("c"))
            old, jump = jump, self.scratch.save(jump.join(far, "b").select("a", F.col("c").alias("b")), "jump")
            self.scratch.drop(old)

        def follow(key, mine, pdf):
            if not len(mine) or not len(pdf):
                return pd.DataFrame({"dst": [], "len": [], "src": []})
            pdf, low, nxt, _ = leaves(pdf)
            i, at, end = int(mine["pos"].min()), [], low + len(pdf)
            hops = nxt.tolist()
            while i < end:
                at.append(i - low)
                i = hops[i - low]
            return pdf.iloc[at].rename(columns={"pos": "dst", "n": "len"})[["dst", "len", "src"]]

        entry = marked.select(F.expr(f"(a - 1) div {CELL}").alias("cell"), F.col("a").alias("pos"))
        phrases = entry.groupBy("cell").cogroup(steps.groupBy("cell")).applyInPandas(follow, "dst long, len long, src double")
        return phrases.where(F.col("len") >= min_len).select("dst", "len", F.col("src").cast("long").alias("src"))
