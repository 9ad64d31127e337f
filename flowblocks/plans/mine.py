"""Exact level-wise mining of dense blocks, with every optimisation as a switch.

A block is (o, d, t_lo, t_hi) with sorted region arrays. Each level extends every block by one neighbouring region on
either side or one slot at either end, keeps one of equal candidates, adds the slab's hot cells to the parent's count
and admits those with cnt / card >= s_r (integers only). Every level is a table, written once.

The indexes (packed hot masks by origin, by destination and by slot, prefix sums by first region) are small tables
keyed by the added region or slot and joined by broadcast; their cells are counted first, and beyond MAX_INDEX of them
slabs are counted by shuffled joins with the hot cells, and the prefix bound is left out: the result is the same.
"""
from __future__ import annotations

import time
from dataclasses import dataclass, field
from fractions import Fraction

import numpy as np
from py4j.protocol import Py4JJavaError
from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from ..durable import durable
from ..operators.graph import Graph

MODES = ("plain", "memo", "memo_skip", "memo_skip_nbr", "full", "packed")
KEY, SLAB = ["o", "d", "t_lo", "t_hi"], ["so", "sd", "slo", "shi"]
#: Longs of an index at most (64 MB); neighbour pairs that a plan constant may hold; slots of a mask word.
MAX_INDEX, MAX_ADJACENT, WORD = 1 << 23, 1 << 16, 62


@dataclass
class Domain:
    """Only these origins, destinations and slots; None is no limit."""

    origins: list[int] | None = None
    destinations: list[int] | None = None
    t_lo: int | None = None
    t_hi: int | None = None

    def filter(self, cells: DataFrame) -> DataFrame:
        for col, allowed in (("o", self.origins), ("d", self.destinations)):
            cells = cells if allowed is None else cells.where(F.col(col).isin(allowed))
        cells = cells if self.t_lo is None else cells.where(F.col("t") >= self.t_lo)
        return cells if self.t_hi is None else cells.where(F.col("t") <= self.t_hi)

    def unconnected(self, graph: Graph) -> list[str]:
        """Sides whose allowed regions do not hang together; blocks then stay within their parts."""
        return [side for side, verts in (("origins", self.origins), ("destinations", self.destinations)) if verts is not None and not graph.is_connected(verts)]


@dataclass
class Mined:
    df: DataFrame
    stats: list[dict] = field(default_factory=list)
    notes: list[str] = field(default_factory=list)


def ints(values, kind=np.int32) -> Column:
    return F.lit(np.asarray(values, kind)) if len(values) else F.array().cast("array<int>" if kind is np.int32 else "array<bigint>")


class Index:
    """What counting and pruning look up, made once from the hot cells."""

    def __init__(self, hot: DataFrame, graph: Graph, slots: int, packed: bool = True):
        n = self.n = graph.n
        self.hot, self.graph, self.slots, self.spark = hot, graph, slots, hot.sparkSession
        self.words, self.sets = -(-slots // WORD), -(-n // WORD)
        self.fits = n * n * self.words <= MAX_INDEX and slots * n * self.sets <= MAX_INDEX
        near = [graph.neighbours(v) for v in range(n)]
        self.starts = np.cumsum([0, *map(len, near)])
        self.small = self.starts[-1] <= MAX_ADJACENT
        self.flat = [w for x in near for w in x]
        if packed and self.fits:
            w = F.floor(F.col("t") / WORD).cast("int")
            rows = hot.groupBy("o", "d", w.alias("w")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("bigint"), F.pmod("t", F.lit(WORD)))).alias("m")).toPandas()
            self.masks = np.zeros((n, n, self.words), np.int64)
            self.masks[rows.o, rows.d, rows.w] = rows.m
            self.by = {"o": self._table(self.masks.reshape(n, -1)), "d": self._table(self.masks.transpose(1, 0, 2).reshape(n, -1)), "t": self._table(self._by_slot())}

    def _table(self, rows: np.ndarray, name: str = "m") -> DataFrame:
        import pyarrow as pa

        flat = pa.ListArray.from_arrays(pa.array(np.arange(len(rows) + 1, dtype=np.int32) * rows.shape[1]), pa.array(rows.reshape(-1)))
        return self.spark.createDataFrame(pa.table({"i": pa.array(np.arange(len(rows), dtype=np.int32)), name: flat}))

    def cube(self) -> np.ndarray:
        """Hot cells as a (n, n, slots) array of zeros and ones."""
        t = np.arange(self.slots)
        return self.masks[:, :, t // WORD] >> (t % WORD) & 1

    def _by_slot(self) -> np.ndarray:
        cube, out = self.cube(), np.zeros((self.slots, self.n, self.sets), np.int64)
        for d in range(self.n):
            out[:, :, d // WORD] |= cube[:, d, :].T << (d % WORD)
        return out.reshape(self.slots, -1)

    def neighbours(self, v: Column) -> Column:
        return F.slice(ints(self.flat), F.get(ints(self.starts), v) + 1, F.get(ints(self.starts), v + 1) - F.get(ints(self.starts), v))

    def edges(self) -> DataFrame:
        import pyarrow as pa

        u = np.repeat(np.arange(self.n, dtype=np.int32), np.diff(self.starts))
        return F.broadcast(self.spark.createDataFrame(pa.table({"_m": u, "r": np.asarray(self.flat, np.int32)})))

    def window(self, lo: Column, hi: Column, word: int) -> Column:
        """The bits of slots lo..hi in one mask word."""
        a, b = F.greatest(lo - word * WORD, F.lit(0)), F.least(hi - word * WORD, F.lit(WORD - 1))
        one = F.lit(1).cast("bigint")
        bits = F.call_function("shiftleft", F.call_function("shiftleft", one, F.greatest(b - a + 1, F.lit(0)).cast("int")) - 1, a.cast("int"))
        return F.when(b >= a, bits).otherwise(F.lit(0).cast("bigint"))

    def in_row(self, m: Column, side: Column, lo: Column, hi: Column) -> Column:
        """Hot cells between one region, whose row of masks is m, and a side, in slots lo..hi."""
        zero = F.lit(0).cast("bigint")
        windows = [self.window(lo, hi, w) for w in range(self.words)]
        one = lambda x: sum((F.bit_count(F.get(m, x * self.words + w).bitwiseAND(bits)) for w, bits in enumerate(windows)), zero)
        return F.aggregate(side, zero, lambda a, x: a + one(x))

    def in_slot(self, m: Column, o: Column, d: Column) -> Column:
        """Hot cells between two sides in the slot whose sets are m."""
        zero = F.lit(0).cast("bigint")
        bit = lambda x, y: F.call_function("shiftright", F.get(m, x * self.sets + F.floor(y / WORD).cast("int")), F.pmod(y, F.lit(WORD)).cast("int")).bitwiseAND(F.lit(1).cast("bigint"))
        return F.aggregate(o, zero, lambda a, x: a + F.aggregate(d, zero, lambda b, y: b + bit(x, y)))

    def slab(self, cands: DataFrame, dim: str) -> DataFrame:
        """Candidates of one dimension with the slab's hot cells n, from one row of the index."""
        at = "slo" if dim == "t" else "r"
        rows = cands.join(F.broadcast(self.by[dim].withColumnRenamed("i", at)), at)
        n = self.in_slot(F.col("m"), F.col("so"), F.col("sd")) if dim == "t" else self.in_row(F.col("m"), F.col("sd" if dim == "o" else "so"), F.col("slo"), F.col("shi"))
        return rows.withColumn("n", n).drop("m")

    def whole(self, blocks: DataFrame) -> DataFrame:
        """Blocks (key columns) with cnt, counted from nothing: by rows of the index where it fits, else cell by cell."""
        if not self.fits:
            n = probe(blocks.select(F.col("o").alias("so"), F.col("d").alias("sd"), F.col("t_lo").alias("slo"), F.col("t_hi").alias("shi")).distinct(), self.hot)
            return blocks.join(n.toDF(*KEY, "cnt"), KEY)
        rows = blocks.select(*KEY, F.explode("o").alias("r")).join(F.broadcast(self.by["o"].withColumnRenamed("i", "r")), "r")
        return rows.withColumn("n", self.in_row(F.col("m"), F.col("d"), F.col("t_lo"), F.col("t_hi"))).groupBy(*KEY).agg(F.sum("n").alias("cnt"))

    def overlaps(self, zero_for: str) -> DataFrame:
        """i, partners: destinations of an origin or origins of a destination, all slots together."""
        any_ = (self.masks != 0).any(2)
        rows = any_ if zero_for == "o" else any_.T
        import pyarrow as pa

        return self.spark.createDataFrame(pa.table({"r": pa.array(np.arange(self.n, dtype=np.int32)), "partners": pa.array([np.flatnonzero(x).astype(np.int32) for x in rows], pa.list_(pa.int32()))}))

    def prefix(self) -> np.ndarray:
        """(n+1, n+1, slots+1) summed counts over depth-first region numbers."""
        ids = self.graph.dfs_ids()
        back = np.argsort([ids[v] for v in range(self.n)])
        out = np.zeros((self.n + 1, self.n + 1, self.slots + 1), np.int64)
        out[1:, 1:, 1:] = self.cube()[back][:, back].cumsum(0).cumsum(1).cumsum(2)
        return out

    def bounder(self):
        """A function that adds ub, the hot cells in the id box of the slab, or None where the sums would not fit."""
        n, s = self.n, self.slots
        if not self.fits or (n + 1) ** 2 * (s + 1) > MAX_INDEX:
            return None
        sums, ids = durable(self._table(self.prefix().reshape(n + 1, -1), "p")), self.graph.dfs_ids()
        num = ints([ids[v] for v in range(n)])
        edge = lambda f, c: f(F.transform(F.col(c), lambda r: F.get(num, r)))

        def add(cands: DataFrame) -> DataFrame:
            rows = cands.withColumn("i0", edge(F.array_min, "so")).withColumn("i1", edge(F.array_max, "so") + 1)
            rows = rows.withColumn("j0", edge(F.array_min, "sd")).withColumn("j1", edge(F.array_max, "sd") + 1)
            for x in ("0", "1"):
                rows = rows.join(F.broadcast(sums.select(F.col("i").alias(f"i{x}"), F.col("p").alias(f"p{x}"))), f"i{x}")
            at = lambda p, j, k: F.get(F.col(p), (F.col(j) * (s + 1) + k).cast("int"))
            face = lambda p: at(p, "j1", F.col("shi") + 1) - at(p, "j0", F.col("shi") + 1) - at(p, "j1", F.col("slo")) + at(p, "j0", F.col("slo"))
            return rows.withColumn("ub", face("p1") - face("p0")).drop("i0", "i1", "j0", "j1", "p0", "p1")

        return add


def figures(seen: Observation) -> dict:
    """What was observed; nothing where the planner found the frame empty and left the observation out."""
    try:
        return {k: v or 0 for k, v in seen.get.items()}
    except Py4JJavaError:
        return {}


def seed(hot: DataFrame) -> DataFrame:
    return hot.select(F.array("o").alias("o"), F.array("d").alias("d"), F.col("t").alias("t_lo"), F.col("t").alias("t_hi"), F.lit(1).cast("bigint").alias("cnt"), F.lit(1).cast("bigint").alias("card"))


def extend(front: DataFrame, ix: Index, bounds, one_step: bool, domain: Domain | None = None) -> dict[str, DataFrame]:
    """Candidates by dimension with their slab and parent count; equal ones may come from several parents."""
    bo, bd, bt = bounds or (None, None, None)
    dom = domain or Domain()
    lo_end, hi_end = dom.t_lo or 0, ix.slots - 1 if dom.t_hi is None else dom.t_hi

    def side(col: str, limit, allowed):
        rows = front if limit is None else front.where(F.size(col) < limit)
        taken = F.concat("o", "d")
        if one_step and ix.small:
            rows = rows.withColumn("r", F.explode(F.array_except(F.array_distinct(F.flatten(F.transform(col, ix.neighbours))), taken)))
        else:
            rows = rows.withColumn("_m", F.explode(col)).join(ix.edges(), "_m").drop("_m").where(~F.array_contains(taken, F.col("r")))
        return rows if allowed is None else rows.where(F.col("r").isin(allowed))

    add = lambda c: F.array_sort(F.array_append(c, F.col("r")))
    one, card = F.array("r"), F.size("o").cast("bigint") * F.size("d") * (F.col("t_hi") - F.col("t_lo") + 1)
    kept = lambda c: F.col(c)
    out = {
        "o": side("o", bo, dom.origins).select(add("o").alias("o"), "d", "t_lo", "t_hi", "cnt", one.alias("so"), kept("d").alias("sd"), kept("t_lo").alias("slo"), kept("t_hi").alias("shi"), F.lit("o").alias("dim"), "r"),
        "d": side("d", bd, dom.destinations).select("o", add("d").alias("d"), "t_lo", "t_hi", "cnt", kept("o").alias("so"), one.alias("sd"), kept("t_lo").alias("slo"), kept("t_hi").alias("shi"), F.lit("d").alias("dim"), "r"),
    }
    longer = front if bt is None else front.where(F.col("t_hi") - F.col("t_lo") + 1 < bt)
    ends = F.explode(F.filter(F.array(F.col("t_lo") - 1, F.col("t_hi") + 1), lambda x: (x >= lo_end) & (x <= hi_end)))
    longer = longer.withColumn("slo", ends)
    out["t"] = longer.select("o", "d", F.least("t_lo", "slo").alias("t_lo"), F.greatest("t_hi", "slo").alias("t_hi"), "cnt", kept("o").alias("so"), kept("d").alias("sd"), "slo", kept("slo").alias("shi"), F.lit("t").alias("dim"), F.lit(-1).alias("r"))
    return {k: v.withColumn("card", card) for k, v in out.items()}


def together(parts) -> DataFrame:
    parts = list(parts)
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def probe(slabs: DataFrame, hot: DataFrame) -> DataFrame:
    """(so, sd, slo, shi, n): every atomic cell of every slab is looked up among the hot cells."""
    cells = slabs.withColumn("o", F.explode("so")).withColumn("d", F.explode("sd")).withColumn("t", F.explode(F.sequence("slo", "shi")))
    return cells.join(hot.withColumn("hit", F.lit(1)), ["o", "d", "t"], "left").groupBy(*SLAB).agg(F.count("hit").alias("n"))


def atoms(slabs: DataFrame):
    return F.sum(F.size("so").cast("bigint") * F.size("sd") * (F.col("shi") - F.col("slo") + 1))


def count(parts: dict[str, DataFrame], ix: Index, mode: str, memo: DataFrame | None, keep=None, bound=None):
    """(candidates with cnt, the memo after them, work counters). keep is a condition on the counted ones; bound, a function
    from the frame with ub to a condition, drops candidates ahead of counting."""
    rank = MODES.index(mode)
    if mode == "packed":  # a row of the index counts a slab in place, so the test comes before the shuffle
        counted = together(ix.slab(part, dim).withColumn("cnt", F.col("cnt") + F.col("n")) for dim, part in parts.items())
        seen = Observation()
        counted = counted.observe(seen, F.count(F.lit(1)).alias("generated"), atoms(counted).alias("probes"))
        return (counted if keep is None else counted.where(keep)).dropDuplicates(KEY), None, seen
    made, one = Observation(), Observation()
    cands = together(parts.values()).observe(made, F.count(F.lit(1)).alias("generated")).dropDuplicates(KEY)
    if rank >= 2 and ix.fits:
        for dim, side in (("o", "sd"), ("d", "so")):
            cands = cands.join(F.broadcast(ix.overlaps(dim).withColumnRenamed("partners", f"_{dim}")), "r", "left")
        none = lambda c, s: (F.col("dim") == c) & ~F.arrays_overlap(F.col(s), F.col(f"_{c}"))
        cands = cands.withColumn("zero", F.coalesce(none("o", "sd") | none("d", "so"), F.lit(False))).drop("_o", "_d")
    else:
        cands = cands.withColumn("zero", F.lit(False))
    work = {}
    cands = cands.observe(one, F.count(F.lit(1)).alias("distinct"), F.count_if("zero").alias("zero_skips"))
    if bound is not None:
        cands, pruned = bound(cands), Observation()
        cands = cands.observe(pruned, F.count_if(~F.col("_keep")).alias("bound_prunes")).where("_keep").drop("_keep")
    cands = durable(cands)
    work |= figures(made) | figures(one) | (figures(pruned) if bound is not None else {})
    slabs = cands.where("not zero").select(*SLAB).distinct()
    if rank == 0:
        n = durable(probe(slabs, ix.hot))
        work |= {"exact_counts": n.count(), "probes": n.agg(atoms(n)).first()[0] or 0}
    else:
        old = slabs.withColumn("n", F.lit(None).cast("bigint")) if memo is None else slabs.join(memo, SLAB, "left")
        old = durable(old)
        fresh = durable(probe(old.where("n is null").select(*SLAB), ix.hot))
        work |= {"memo_hits": old.where("n is not null").count(), "exact_counts": fresh.count(), "probes": fresh.agg(atoms(fresh)).first()[0] or 0}
        n = old.where("n is not null").unionByName(fresh)
    out = cands.join(n, SLAB, "left").withColumn("cnt", F.col("cnt") + F.coalesce("n", F.lit(0))).drop("n", "zero")
    if rank:
        out = durable(out)
        told = out.select(F.col("o").alias("so"), F.col("d").alias("sd"), F.col("t_lo").alias("slo"), F.col("t_hi").alias("shi"), F.col("cnt").alias("n")).unionByName(fresh).dropDuplicates(SLAB)
        told = durable(told if memo is None else told.join(memo, SLAB, "left_anti"))  # the memo only grows: what it holds stays as written
        memo = told if memo is None else memo.unionByName(told)
    return out if keep is None else out.where(keep), memo, work


def dense(ratio: Fraction, cnt: str = "cnt") -> Column:
    return F.col(cnt) * ratio.denominator >= F.col("card") * ratio.numerator


def enumerate_blocks(hot: DataFrame, graph: Graph, slots: int, s_r, mode: str = "packed", bounds=(3, 3, 3), domain: Domain | None = None, max_level: int | None = None, max_blocks: int = 50_000_000, timeout_s: float | None = None) -> Mined:
    """All dense blocks; bounds None is unbounded on a side. More than max_blocks at a level, or more seconds than
    timeout_s between levels, is an error, never a cut."""
    ratio = Fraction(str(s_r))
    if not 0 < ratio <= 1 or mode not in MODES:
        raise ValueError("s_r must be in (0, 1] and mode one of " + ", ".join(MODES))
    start, notes = time.time(), [f"the allowed {side} are not connected" for side in (domain.unconnected(graph) if domain else [])]
    ix = Index(durable(hot), graph, slots, mode not in ("plain", "memo"))
    counting = "memo_skip_nbr" if mode == "packed" and not ix.fits else mode
    bounder = ix.bounder() if mode == "full" else None
    bound = bounder and (lambda c: bounder(c).withColumn("_keep", F.col("zero") | ((F.col("cnt") + F.col("ub")) * ratio.denominator >= F.col("card") * ratio.numerator)).drop("ub"))
    if counting != mode or mode == "full" and bound is None:
        notes.append("the index would not fit; counted by joins")
    cols = [*KEY, "cnt", "card"]
    front, levels, stats, memo, level = durable(seed(ix.hot)), [], [], None, 3
    while (size := front.count()) and (max_level is None or level <= max_level):
        if size > max_blocks:
            raise RuntimeError(f"level {level} has {size} blocks; bound the sizes or raise s_r")
        if timeout_s is not None and time.time() - start > timeout_s:
            raise TimeoutError(f"level {level} reached after {time.time() - start:.0f} s")
        levels.append(front.select(F.lit(level).alias("level"), *cols))
        began = time.time()
        counted, memo, work = count(extend(front, ix, bounds, MODES.index(counting) >= 3, domain), ix, counting, memo, dense(ratio), bound)
        made = time.time()
        front = durable(counted.select(cols))
        stats.append({"level": level, "patterns": size, "generate_s": made - began, "count_s": time.time() - made, **(work if isinstance(work, dict) else figures(work))})
        level += 1
    out = levels[0] if levels else seed(ix.hot).select(F.lit(3).alias("level"), *cols)
    return Mined(together([out, *levels[1:]]), stats, notes)


def exact_shape(hot, graph, slots, s_r, shape, mode="packed") -> DataFrame:
    """Dense blocks of exactly this shape that the definition reaches."""
    so, sd, st = shape
    found = enumerate_blocks(hot, graph, slots, s_r, mode, shape).df
    return found.where((F.size("o") == so) & (F.size("d") == sd) & (F.col("t_hi") - F.col("t_lo") + 1 == st))


def flat(blocks: DataFrame) -> DataFrame:
    """Sets as comma strings, for output."""
    text = lambda c: F.array_join(F.transform(c, lambda x: x.cast("string")), ",").alias(c)
    return blocks.select(*[text(c) if c in ("o", "d") else c for c in blocks.columns])


def below(blocks: DataFrame) -> DataFrame:
    """Every one-step specialization of every block, with the block it comes from (b_o, b_d, b_lo, b_hi)."""
    b = blocks.select(*KEY, *[F.col(a).alias(z) for a, z in zip(KEY, ("b_o", "b_d", "b_lo", "b_hi"))])
    from_ = ["b_o", "b_d", "b_lo", "b_hi"]
    drop = lambda c: F.explode(F.transform(c, lambda x: F.array_remove(F.col(c), x))).alias(c)
    longer = b.where("t_hi > t_lo")
    return together([
        b.where(F.size("o") > 1).select(drop("o"), "d", "t_lo", "t_hi", *from_), b.where(F.size("d") > 1).select("o", drop("d"), "t_lo", "t_hi", *from_),
        longer.select("o", "d", (F.col("t_lo") + 1).alias("t_lo"), "t_hi", *from_), longer.select("o", "d", "t_lo", (F.col("t_hi") - 1).alias("t_hi"), *from_),
    ])


def maximal(blocks: DataFrame) -> DataFrame:
    """Blocks without a dense one-step extension among the given ones."""
    return blocks.join(below(blocks).select(*KEY).distinct(), KEY, "left_anti").select(blocks.columns)


def steps(blocks: DataFrame) -> DataFrame:
    """(o, d, t_lo, t_hi, b_o, b_d, b_lo, b_hi): pairs of given blocks of which the second generalizes the first by one step."""
    return below(blocks).join(blocks.select(*KEY), KEY)


def is_generalization(big: list[Column], small: list[Column]) -> Column:
    """Whether block big (o, d, t_lo, t_hi) holds block small."""
    inside = F.size(F.array_except(small[0], big[0])) + F.size(F.array_except(small[1], big[1])) == 0
    return inside & (big[2] <= small[2]) & (big[3] >= small[3])


def unsupported(blocks: DataFrame) -> DataFrame:
    """Blocks above level 3 without a dense one-step specialization among the given ones: none, in a right result."""
    held = steps(blocks).select(*[F.col(z).alias(a) for a, z in zip(KEY, ("b_o", "b_d", "b_lo", "b_hi"))]).distinct()
    return blocks.where("level > 3").join(held, KEY, "left_anti")
