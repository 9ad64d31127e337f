"""Embedding near-duplicates (operator 4) by NN-descent.

A neighbour graph starts from orders by random sign codes, where each vector meets the next SPAN of its label (across the
edges of batches and partitions too) and keeps the best KEPT of each order; then rounds of descent compare the neighbours
and reverse neighbours of every vector with one another, of which at least one is new, and every list takes what is better
than its last. Rounds go on until no component changes and fewer than DELTA of the list entries do.

Pairs at the threshold join components before any list is cut. A list has the LIST best of a vector's own component, as ways
on, and the LIST best outside it: one that is saturated with vectors of its own component is so enlarged to the whole
component, which is compared exactly. The number of orders follows the largest label: a lone pair at the threshold
is missed by all of them with a probability of MISS at most, whatever the size. Links are counted in tiles of TILE vectors
without a row for each pair; vectors within half the threshold's angle of their component's centre link with each other for
sure, so only the others meet all tiles.

Exact copies are one vector with a weight from the start. Null, zero, ragged or non-finite vectors and null labels link
with nothing; vectors of different lengths link with nothing; equal rows of an id count once, an id with several vectors has
the links of all of them; ties keep the smaller id; other columns are not read; an empty table gives an empty table.
"""
from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import Scratch, components

THRESHOLD, TABLES, SPAN, LIST, KEPT, TILE = 0.93, 16, 6, 10, 2, 512
MISS, DELTA, SALT = 0.01, 0.1, 32
#: Vectors of a component that one code of an order shows from the second turn on.
SHOWN = 2


def turns(largest: int, threshold: float) -> tuple[int, int]:
    """(turns of TABLES orders, bits of a code) for the vectors of the largest label. Two vectors at the threshold agree in a
    bit with probability p and stand within SPAN of each other once they agree in log2(largest / SPAN) bits."""
    p, depth = 1 - math.acos(threshold) / math.pi, max(1.0, math.log2(max(2, largest) / SPAN))
    tables = math.log(MISS) / math.log1p(-(p**depth))
    return max(1, math.ceil(tables / TABLES)), min(62, math.ceil(depth) + 8)


def unit_vectors(rows: DataFrame) -> DataFrame:
    """id, label, unit (array<double>) and dim of the vectors that can link."""
    v = F.transform("embedding", lambda x: x.cast("double"))
    v = rows.select(F.col("vec_id").alias("id"), "label", v.alias("v")).where("label is not null and v is not null and size(v) > 0")
    v = v.where(~F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))))
    v = v.withColumn("top", F.array_max(F.transform("v", lambda x: F.abs(x)))).where("top > 0")
    v = v.withColumn("v", F.transform("v", lambda x: x / F.col("top")))
    norm = F.sqrt(F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x))
    return v.withColumn("norm", norm).select("id", "label", F.transform("v", lambda x: x / F.col("norm")).alias("unit"))


def padded(column) -> tuple[np.ndarray, np.ndarray]:
    """(vectors padded with zeros to the longest, their dimensions) of an Arrow list column."""
    dim = column.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
    m = np.zeros((len(dim), int(dim.max(initial=0))))
    m[np.arange(m.shape[1]) < dim[:, None]] = column.flatten().to_numpy(zero_copy_only=False)
    return m, dim


def first_edges(vec: DataFrame, parts: int, turn: int, bits: int, threshold: float) -> DataFrame:
    """Pairs (u, v, s) that meet in the orders of this turn: those at the threshold, and the KEPT best of each vector in each
    order; vec is (id, label, unit, component)."""

    def codes(batches):
        import pyarrow as pa

        planes: dict[int, np.ndarray] = {}
        for b in batches:
            m, dim = padded(b.column(2))
            out = np.zeros((len(dim), TABLES), np.int64)
            for d in np.unique(dim).tolist():
                p = planes.setdefault(d, np.random.default_rng([d, turn]).standard_normal((d, TABLES * bits)))
                at = np.flatnonzero(dim == d)
                out[at] = (m[at, :d] @ p > 0).reshape(len(at), TABLES, bits) @ (1 << np.arange(bits, dtype=np.int64)[::-1])
            ids = b.column(0).to_numpy(zero_copy_only=False).astype(np.uint64)
            for t in range(TABLES):
                mixed = (ids + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15 + 2 * (t + turn * TABLES))  # another order within a component each time
                mixed = ((mixed ^ (mixed >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)).view(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(dim), t, np.int32)), pa.array(out[:, t]), b.column(3), pa.array(mixed), b.column(0), b.column(1), b.column(2)], NAMES)

    def shown(b):
        """Rows to compare: from the second turn on, SHOWN of a component under one code."""
        t, code, comp, label = (b.column(i).to_numpy(zero_copy_only=False) for i in (0, 1, 2, 5))
        again = np.zeros(len(t), bool)
        if turn and len(t) > SHOWN:
            again[SHOWN:] = (t[SHOWN:] == t[:-SHOWN]) & (label[SHOWN:] == label[:-SHOWN]) & (code[SHOWN:] == code[:-SHOWN]) & (comp[SHOWN:] == comp[:-SHOWN])
        return b.take(np.flatnonzero(~again)) if again.any() else b

    def pairs(b, old: int):
        """Edges of neighbouring rows; pairs of the first `old` rows among themselves are known already."""
        import pyarrow as pa

        t, comp, ids, label = (b.column(i).to_numpy(zero_copy_only=False) for i in (0, 2, 4, 5))
        m, dim = padded(b.column(6))
        a, z, s = [], [], []
        for o in range(1, SPAN + 1):
            x = np.flatnonzero((t[:-o] == t[o:]) & (label[:-o] == label[o:]) & (dim[:-o] == dim[o:]) & (ids[:-o] != ids[o:]))
            x = x[x + o >= old]
            x = x[comp[x] != comp[x + o]] if turn else x
            a.append(x)
            z.append(x + o)
            s.append(np.einsum("ij,ij->i", m[x], m[x + o]))
        a, z, s = (np.concatenate(k) if k else np.zeros(0, np.int64) for k in (a, z, s))
        ends, both = np.concatenate([a, z]), np.concatenate([s, s])
        order = np.lexsort((-both, ends))
        place = np.arange(len(order)) - np.searchsorted(ends[order], ends[order])
        best = np.zeros(len(both), bool)
        best[order] = place < KEPT
        keep = best[: len(a)] | best[len(a) :] | (s >= threshold)
        return pa.RecordBatch.from_arrays([pa.array(ids[a[keep]]), pa.array(ids[z[keep]]), pa.array(s[keep].astype(np.float64))], ["u", "v", "s"])

    def near(batches):
        import pyarrow as pa

        last = None
        for b in batches:
            b = shown(b)
            if last is not None:
                b = pa.Table.from_batches([last, b]).combine_chunks().to_batches()[0] if b.num_rows else last
            yield pairs(b, 0 if last is None else last.num_rows)
            last = b.slice(max(0, b.num_rows - SPAN))

    def rims(batches):
        """The first and the last SPAN rows of a partition, each under the edge that it touches."""
        import pyarrow as pa
        from pyspark import TaskContext

        part, first, last = TaskContext.get().partitionId(), None, None
        for b in batches:
            b = shown(b)
            if not b.num_rows:
                continue
            join = lambda x, y: y if x is None else pa.Table.from_batches([x, y]).combine_chunks().to_batches()[0]
            first = first if first is not None and first.num_rows >= SPAN else join(first, b).slice(0, SPAN)
            last = join(last, b)
            last = last.slice(max(0, last.num_rows - SPAN))
        for rows, edge in ((first, part), (last, part + 1)):
            if rows is not None:
                yield pa.RecordBatch.from_arrays([*rows.columns, pa.array(np.full(rows.num_rows, edge, np.int32)), pa.array(np.full(rows.num_rows, part, np.int32)), pa.array(np.arange(rows.num_rows, dtype=np.int32))], [*NAMES, "edge", "part", "at"])

    def across(table):
        import pyarrow as pa

        table = table.sort_by([("part", "ascending"), ("at", "ascending")]).combine_chunks()
        parts = table.column("part").to_numpy()
        return pa.Table.from_batches([pairs(table.select(NAMES).to_batches()[0], int((parts == parts[0]).sum()))]) if len(set(parts.tolist())) > 1 else pa.table({"u": pa.array([], pa.int64()), "v": pa.array([], pa.int64()), "s": pa.array([], pa.float64())})

    order, rows = ["t", "label", "code", "component", "mixed"], f"t int, code bigint, component bigint, mixed bigint, id bigint, label {vec.schema['label'].dataType.simpleString()}, unit array<double>"
    sorted_ = vec.select("id", "label", "unit", "component").mapInArrow(codes, rows).repartitionByRange(parts, *order).sortWithinPartitions(*order)
    edges = "u bigint, v bigint, s double"
    seam = sorted_.mapInArrow(rims, f"{rows}, edge int, part int, at int").groupBy("edge").applyInArrow(across, edges)
    return sorted_.mapInArrow(near, edges).union(seam)


NAMES = ["t", "code", "component", "mixed", "id", "label", "unit"]


def shorten(edges: DataFrame, comp: DataFrame) -> DataFrame:
    """The lists (u, v, s, fresh): the LIST best of each u inside its component and the LIST best outside, both directions."""
    both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v"), "s", "fresh"))
    both = placed(both.groupBy("u", "v").agg(F.max("s").alias("s"), F.min("fresh").alias("fresh")), comp).withColumn("own", F.col("cu") == F.col("cv"))
    return both.withColumn("r", F.row_number().over(Window.partitionBy("u", "own").orderBy(F.desc("s"), "v"))).where(F.col("r") <= LIST).select("u", "v", "s", "fresh")


def placed(pairs: DataFrame, comp: DataFrame) -> DataFrame:
    """pairs with the components cu and cv of their ends; an id without one is its own."""
    for end in ("u", "v"):
        pairs = pairs.join(comp.select(F.col("id").alias(end), F.col("component").alias(f"_{end}")), end, "left").withColumn(f"c{end}", F.coalesce(f"_{end}", end)).drop(f"_{end}")
    return pairs


def merged(disk: Scratch, comp: DataFrame, links: DataFrame, turn: int) -> DataFrame | None:
    """comp after these links (u, v), joined by component and not by member; None where they join nothing new."""
    across = disk.keep(f"across-{turn}", placed(links, comp).where("cu <> cv").select("u", "v", "cu", "cv"))
    if not across.limit(1).count():
        return None
    moved = components(across.select(F.col("cu").alias("u"), F.col("cv").alias("v")).distinct()).select(F.col("id").alias("component"), F.col("component").alias("to"))
    ends = across.select(F.col("u").alias("id"), F.col("cu").alias("component")).union(across.select("v", "cv"))
    return disk.keep(f"components-{turn}", comp.union(ends).distinct().join(moved, "component", "left").select("id", F.coalesce("to", "component").alias("component")))


def refine(lists: DataFrame, vec: DataFrame, threshold: float) -> DataFrame:
    """Edges among the neighbours and reverse neighbours of each vector, one of a pair new at least, that are at the
    threshold or better than the last entry of one of their ends."""

    def local(batches):
        import pyarrow as pa

        for b in batches:
            u, v, s = [], [], []
            for around in b.column(0):
                x = around.values
                ids, fresh, last = (x.field(k).to_numpy(zero_copy_only=False) for k in ("id", "fresh", "last"))
                m, dim = padded(x.field("unit"))
                c = m @ m.T
                ok = ((c >= threshold) | (c > np.minimum(last[:, None], last))) & (fresh[:, None] | fresh) & (dim[:, None] == dim) & (ids[:, None] < ids)
                i, j = np.nonzero(ok)
                u.append(ids[i])
                v.append(ids[j])
                s.append(c[i, j])
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(k) if k else np.zeros(0), t) for k, t in ((u, pa.int64()), (v, pa.int64()), (s, pa.float64()))], ["u", "v", "s"])

    back = lists.withColumn("r", F.row_number().over(Window.partitionBy("v").orderBy(F.desc("fresh"), F.xxhash64("u")))).where(F.col("r") <= LIST).select(F.col("v").alias("a"), F.col("u").alias("id"), "fresh")
    fans = lists.select(F.col("u").alias("a"), F.col("v").alias("id"), "fresh").union(back).groupBy("a", "id").agg(F.max("fresh").alias("fresh"))
    live = fans.groupBy("a").agg(F.max("fresh").alias("f"), F.count("*").alias("k")).where("f and k > 1").select("a")
    last = lists.groupBy("u").agg(F.count("*").alias("k"), F.min("s").alias("s")).select(F.col("u").alias("id"), F.when(F.col("k") < LIST, -2.0).otherwise(F.col("s")).alias("last"))
    near = fans.join(live, "a").join(vec.join(last, "id"), "id")
    return near.groupBy("a").agg(F.collect_list(F.struct("id", "fresh", "last", "unit")).alias("around")).select("around").mapInArrow(local, "u bigint, v bigint, s double")


def cored(member: DataFrame, threshold: float) -> DataFrame:
    """member with core: whether it lies so near the centre of its component that all such members link; only components
    beyond one tile have a core."""

    def sums(batches):
        import pyarrow as pa

        for b in batches:
            comp, w = b.column(0).to_numpy(zero_copy_only=False), b.column(2).to_numpy(zero_copy_only=False)
            m, dim = padded(b.column(1))
            keys, at = np.unique(np.stack([comp, dim]), axis=1, return_inverse=True)
            total = np.zeros((keys.shape[1], m.shape[1]))
            np.add.at(total, at.reshape(-1), m * w[:, None])
            yield pa.RecordBatch.from_arrays([pa.array(keys[0]), pa.array([x[:d] for x, d in zip(total, keys[1])], pa.list_(pa.float64()))], ["component", "part"])

    big = member.groupBy("component").agg(F.count("*").alias("m")).where(F.col("m") > TILE).select("component")
    of = member.join(big, "component", "left_semi")
    total = of.select("component", "unit", F.col("w").cast("double")).mapInArrow(sums, "component bigint, part array<double>")
    total = total.select("component", F.size("part").alias("dim"), F.posexplode("part").alias("at", "x")).groupBy("component", "dim", "at").agg(F.sum("x").alias("x"))
    centre = total.groupBy("component", "dim").agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "x"))), lambda p: p["x"]).alias("c"))
    centre = centre.withColumn("norm", F.sqrt(F.aggregate("c", F.lit(0.0), lambda a, x: a + x * x)))
    dot = F.aggregate(F.zip_with("unit", "c", lambda x, y: x * y), F.lit(0.0), lambda a, x: a + x)
    least = math.cos(math.acos(threshold) / 2) + 1e-9
    return member.withColumn("dim", F.size("unit")).join(centre, ["component", "dim"], "left").withColumn("core", F.coalesce(dot >= F.col("norm") * least, F.lit(False))).drop("c", "norm")


def count_links(member: DataFrame, threshold: float) -> DataFrame:
    """id, n_links (sum of the weights linked with) within components: core members link with each other unseen; the others
    meet every tile, in blocks of TILE by TILE vectors. Each hot component is looked up under SALT keys."""
    member = cored(member, threshold)
    core = member.where("core").groupBy("component", "dim").agg(F.sum("w").alias("all_core"))
    sized = member.groupBy("component").agg(F.count_if("core").alias("m1"), F.count_if(~F.col("core")).alias("m0"))
    sized = sized.select("component", F.ceil(F.col("m0") / TILE).cast("int").alias("t0"), F.ceil(F.col("m1") / TILE).cast("int").alias("t1"))
    many = sized.where("t0 + t1 > 1").select("*", F.explode(F.sequence(F.lit(0), F.lit(SALT - 1))).alias("salt"))
    dealt = member.withColumn("salt", F.pmod(F.xxhash64(F.lit("salt"), "id"), F.lit(SALT)).cast("int")).join(many, ["component", "salt"], "left")
    # tiles of the others are 0 .. t0 - 1, those of the core follow
    t0, t1 = F.coalesce("t0", F.lit(1)), F.coalesce("t1", F.lit(0))
    own = F.when(F.col("core"), t0 + F.pmod(F.xxhash64("id"), F.greatest(t1, F.lit(1)))).otherwise(F.pmod(F.xxhash64("id"), F.greatest(t0, F.lit(1)))).cast("int")
    dealt = dealt.withColumn("tile", own).withColumn("meets", F.when(F.col("core"), t0).otherwise(t0 + t1).cast("int")).where("meets > 0")
    spread = dealt.select("id", "unit", "w", "component", "tile", F.explode(F.sequence(F.lit(0), F.col("meets") - 1)).alias("with"))
    spread = spread.select("id", "unit", "w", "component", "tile", F.least("tile", "with").alias("x"), F.greatest("tile", "with").alias("y"))

    def tile(key, pdf):
        import pandas as pd

        x, y = key[1], key[2]
        found = []
        for _, g in pdf.groupby(pdf.unit.map(len)):
            a, b = g[g.tile == x], g[g.tile == y]
            if not len(a) or not len(b):
                continue
            c = np.stack(a.unit) @ np.stack(b.unit).T >= threshold
            if x == y:
                np.fill_diagonal(c, False)
            found.append(pd.DataFrame({"id": a.id.to_numpy(), "n": c @ b.w.to_numpy()}))
            if x != y:
                found.append(pd.DataFrame({"id": b.id.to_numpy(), "n": a.w.to_numpy() @ c}))
        return pd.concat(found) if found else pd.DataFrame({"id": pd.Series(dtype="int64"), "n": pd.Series(dtype="int64")})

    seen = spread.groupBy("component", "x", "y").applyInPandas(tile, "id bigint, n bigint")
    sure = member.where("core").join(core, ["component", "dim"]).select("id", (F.col("all_core") - F.col("w")).alias("n"))
    return seen.union(sure).groupBy("id").agg(F.sum("n").alias("n_links"))


def copies(vec: DataFrame) -> DataFrame:
    """label, unit, id (the smallest), w: one row for each different vector of a label; repeated rows of an id count once."""
    return vec.dropDuplicates(["id", "label", "unit"]).groupBy("label", "unit").agg(F.min("id").alias("id"), F.count("*").alias("w"))


def near_duplicates(rows: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """vec_id, n_links, component_id, kept."""
    disk = Scratch(rows.sparkSession)
    all_ = disk.keep("units", unit_vectors(rows))
    vec = disk.keep("vectors", copies(all_))
    parts = max(1, int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    largest = vec.groupBy("label").count().agg(F.max("count")).first()[0] or 0
    least, bits = turns(largest, threshold)
    new = F.lit(True).alias("fresh")
    edges = disk.keep("edges-0", first_edges(vec.withColumn("component", F.col("id")), parts, 0, bits, threshold))
    comp = components(edges.where(F.col("s") >= threshold))
    lists = disk.keep("lists-0", shorten(edges.select("*", new), comp))
    turn, changed = 0, True
    while changed or turn < least:
        turn += 1
        found = refine(lists, vec.select("id", "unit"), threshold)
        if turn < least or changed:
            shown = vec.join(comp, "id", "left").select("id", "label", "unit", F.coalesce("component", "id").alias("component"))
            found = found.union(first_edges(shown, parts, turn, bits, threshold))
        found = disk.keep(f"edges-{turn}", found)
        more = merged(disk, comp, found.where(F.col("s") >= threshold), turn)
        comp = comp if more is None else more
        lists_now = disk.keep(f"lists-{turn}", shorten(lists.select("u", "v", "s", F.lit(False).alias("fresh")).union(found.select("*", new)), comp))
        size = lists_now.agg(F.count("*").alias("n"), F.count_if("fresh").alias("fresh")).first()
        changed = more is not None or size.fresh > DELTA * size.n
        lists = lists_now
        disk.drop(f"edges-{turn - 1}", f"lists-{turn - 1}")
    links = disk.keep("links", count_links(comp.join(vec, "id"), threshold))
    linked = comp.join(links, "id", "left")
    # every different vector that has a copy or a link; its copies, found under SALT keys, share its result
    own = vec.join(linked, "id", "left").where("w > 1 or component is not null").select("label", "unit", F.coalesce("component", "id").alias("component"), (F.coalesce("n_links", F.lit(0)) + F.col("w") - 1).alias("n_links"))
    own = own.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALT - 1))))
    mine = all_.withColumn("salt", F.pmod(F.xxhash64("id"), F.lit(SALT)).cast("int")).join(own, ["label", "unit", "salt"]).select(F.col("id").alias("vec_id"), "component", "n_links")
    mine = mine.groupBy("vec_id").agg(F.min("component").alias("component"), F.max("n_links").alias("n_links"))
    out = rows.select("vec_id").join(mine, "vec_id", "left")
    out = disk.keep("rows", out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("bigint").alias("n_links"), F.coalesce("component", "vec_id").alias("component_id"), (F.coalesce("component", "vec_id") == F.col("vec_id")).alias("kept")))
    disk.drop("units", "vectors", "links", f"edges-{turn}", f"lists-{turn}")
    return out


def audit_recall(rows: DataFrame, found: DataFrame, threshold: float = THRESHOLD) -> tuple[int, int]:
    """(links by brute force, links found), each counted from both ends. Every label is compared whole, in tiles of TILE
    vectors on the executors, so the work grows with the square of a label: for audits, not for queries."""
    disk = Scratch(rows.sparkSession)
    vec = disk.keep("vectors", copies(unit_vectors(rows)))
    n = count_links(vec.withColumn("component", F.col("label").cast("bigint")), threshold)
    own = vec.join(n, "id", "left").select(F.col("w").alias("w"), (F.coalesce("n_links", F.lit(0)) + F.col("w") - 1).alias("n_links"))
    truth = own.agg(F.sum(F.col("w") * F.col("n_links"))).first()[0] or 0
    return int(truth), int(found.agg(F.sum("n_links")).first()[0] or 0)
