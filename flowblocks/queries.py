"""Registered queries of the block miner and the SQL that states the same."""
from __future__ import annotations

from pyspark.sql import functions as F

from . import costs
from .durable import durable
from .functions import slots as S
from .operators import cells as C
from .operators import flow, graph, regions
from .plans import approx, mine, rank
from .sources import files, trips
from .streaming import cells as stream

NETS = {"freight": (25, 12), "zones": (100, 12), "clicks": (25, 48), "returns": (25, 27)}
_LINES = "from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join supplier on l_suppkey = s_suppkey"
_HOPS = "select o, d, ts, pax from (select k o, lead(k) over (partition by user_id order by ts, event_id) d, ts, round(value * 100)::bigint pax from (select *, cast(json_extract_string(props, '$.k') as int) // 4 k from events))"
TRIPS_SQL = {
    "freight": f"select s_nationkey o, c_nationkey d, month(o_orderdate) - 1 t, l_quantity::bigint pax {_LINES}",
    "zones": f"select (s_nationkey * 4 + s_suppkey % 4)::int o, (c_nationkey * 4 + c_custkey % 4)::int d, month(o_orderdate) - 1 t, l_quantity::bigint pax {_LINES}",
    "returns": f"select s_nationkey o, c_nationkey d, (dayofyear(o_orderdate) - 1) // 14 t, 50 + (l_orderkey * 7 + l_linenumber * 13) % 151 pax {_LINES} where l_returnflag = 'R'",
    "clicks": f"select o, d, hour(ts) * 2 + minute(ts) // 30 t, pax from ({_HOPS})",
}
GRID = "n as (select n_nationkey v, n_regionkey c, row_number() over (partition by n_regionkey order by n_nationkey) r from nation), e as (select a.v u, b.v w from n a join n b on (a.c = b.c and abs(a.r - b.r) = 1) or (a.r = b.r and abs(a.c - b.c) = 1))"
DENSE = "e as (select a.n_nationkey u, b.n_nationkey w from nation a join nation b on a.n_nationkey <> b.n_nationkey and abs(a.n_regionkey - b.n_regionkey) <= 1)"
PATH = "e as (select a.i::int u, b.i::int w from range(25) a(i) join range(25) b(i) on abs(a.i - b.i) = 1)"
SEEN_PATH = "n as (select distinct (cast(json_extract_string(props, '$.k') as int) // 4)::int v from events), e as (select a.v u, b.v w from n a join n b on abs(a.v - b.v) = 1)"
SQUARE = "e as (select a.i::int u, b.i::int w from range(100) a(i) join range(100) b(i) on (a.i // 10 = b.i // 10 and abs(a.i - b.i) = 1) or abs(a.i - b.i) = 10)"
EDGES = {"freight": GRID, "returns": DENSE, "clicks": PATH, "zones": SQUARE}


def cells_sql(net: str, where: str = "true") -> str:
    return f"select o::int o, d::int d, t::int t, sum(pax)::bigint flow from ({TRIPS_SQL[net]}) where o <> d and pax > 0 and d is not null and {where} group by 1, 2, 3"


def hot_sql(net: str, share: tuple[int, int], where: str = "true", of: str | None = None) -> str:
    """cells and hot; with `of`, hot cells by the threshold of the cells that `of` names, then where."""
    a, b = share
    least = f"(select min(flow) from (select flow, row_number() over (order by flow desc) k from every) where k <= greatest(1, {a} * (select count(*) from every) // {b}))"
    local, after = (where, "true") if of is None else ("true", where)
    return f"every as ({cells_sql(net, local)}), cells as (select * from every where {after}), hot as (select o, d, t from cells where flow >= {least})"


def levels_sql(net, share, ratio, bounds, rank_k=None, max_level=None, where="true", of=None, sides=("true", "true"), slots=None) -> str:
    """One common table for each level, counted from scratch against the hot cells; the rank_k best of a level instead of a
    ratio. `where` limits the cells, `sides` the regions u that may join, `slots` the first and last slot."""
    (n, last_slot), (bo, bd, bt), (first, last) = NETS[net], bounds, slots or (0, NETS[net][1] - 1)
    kind = "bigint" if n <= 62 else "hugeint"
    bit = lambda c: f"(1::{kind} << {c}::int)"
    size = lambda m: f"bit_count({m})"
    has = lambda m, c: f"(({m} >> {c}::int) & 1 = 1)"
    ctes = [hot_sql(net, share, where, of), EDGES[net], f"adj as (select u::int u, bit_or({bit('w')}) m from e group by u)", f"l3 as (select {bit('o')} om, {bit('d')} dm, t lo, t hi, 1::bigint cnt, 1::bigint card from hot)"]
    deepest = max_level or bo + bd + bt
    for k in range(4, deepest + 1):
        ctes.append(
            f"c{k} as (select om | {bit('u')} om, dm, lo, hi from l{k - 1}, adj where m & om <> 0 and not {has('(om | dm)', 'u')} and {size('om')} < {bo} and {sides[0]} union select om, dm | {bit('u')}, lo, hi from l{k - 1}, adj where m & dm <> 0 and not {has('(om | dm)', 'u')} and {size('dm')} < {bd} and {sides[1]}"
            f" union select om, dm, lo - 1, hi from l{k - 1} where lo > {first} and hi - lo + 1 < {bt} union select om, dm, lo, hi + 1 from l{k - 1} where hi < {last} and hi - lo + 1 < {bt})"
        )
        card = f"any_value({size('om')})::bigint * any_value({size('dm')})::bigint * any_value(hi - lo + 1)"
        body = f"select om, dm, lo, hi, count(*)::bigint cnt, ({card})::bigint card from c{k} join hot on {has('om', 'o')} and {has('dm', 'd')} and t between lo and hi group by om, dm, lo, hi"
        if rank_k:
            ctes.append(f"l{k} as (select * from ({body}) order by cnt desc, {members('om', n)}, {members('dm', n)}, lo, hi limit {rank_k})")
        else:
            ctes.append(f"l{k} as ({body} having count(*) * {ratio[1]} >= {card} * {ratio[0]})")
    every = " union all ".join(f"select {k} as level, * from l{k}" for k in range(3, deepest + 1))
    text = lambda m: f"array_to_string({members(m, n)}, ',')"
    return "with " + ", ".join(ctes) + f", blocks as ({every}), named as (select level::int as level, {text('om')} o, {text('dm')} d, lo::int t_lo, hi::int t_hi, cnt, card from blocks) "


def members(mask: str, n: int) -> str:
    return f"list_filter(range({n}), lambda i: ({mask} >> i::int) & 1 = 1)"


def net(spark, sf_dir, name):
    """(cells as a table, graph, slots)."""
    n, slots = NETS[name]
    g = {"freight": lambda: graph.from_edges(graph.grid_edges(spark, sf_dir), n), "returns": lambda: graph.from_edges(graph.dense_edges(spark, sf_dir), n), "clicks": lambda: graph.path(n), "zones": lambda: graph.square(10)}[name]()
    return durable(C.aggregate(getattr(trips, name)(spark, sf_dir))), g, slots


def mined(name, s_a, s_r, bounds, mode="packed", domain=None, shape=None, scope="local", max_level=None):
    """scope: whether the threshold of a limited domain comes from its own cells ('local') or from all ('global')."""

    def run(spark, sf_dir):
        cells, g, slots = net(spark, sf_dir, name)
        hot = C.hot(domain.filter(cells), s_a) if domain and scope == "local" else C.hot(cells, s_a)
        hot = domain.filter(hot) if domain and scope == "global" else hot
        if shape:
            return mine.flat(mine.exact_shape(hot, g, slots, s_r, shape, mode))
        return mine.flat(mine.enumerate_blocks(hot, g, slots, s_r, mode, bounds, domain, max_level).df)

    return run


QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def add(name, fn, sql=None):
    QUERIES[name] = fn
    if sql:
        ORACLES[name] = sql


# cells and slots
for _n in NETS:
    add(f"cells_{_n}", lambda s, d, n=_n: C.aggregate(getattr(trips, n)(s, d)), cells_sql(_n))
    add(f"hot_{_n}", lambda s, d, n=_n: C.hot(durable(C.aggregate(getattr(trips, n)(s, d))), "0.05"), f"with {hot_sql(_n, (1, 20))} select * from hot")
BOUNDS = [6 * 3600, 7 * 3600, 8 * 3600, 9 * 3600, 12 * 3600, 16 * 3600, 17 * 3600, 18 * 3600, 22 * 3600]
_CLICK_CELLS = "select o::int o, d::int d, ({t})::int t, sum(pax)::bigint flow from ({h}) where o <> d and pax > 0 and d is not null group by 1, 2, 3"
_SECOND = "(hour(ts) * 3600 + minute(ts) * 60 + second(ts))"
add("cells_custom_slots", lambda s, d: C.aggregate(trips.clicks(s, d, bounds=BOUNDS)), _CLICK_CELLS.format(h=_HOPS, t=" + ".join(f"({_SECOND} >= {b})::int" for b in BOUNDS)))
add("cells_clicks_classed", lambda s, d: C.aggregate(trips.clicks(s, d, weekday_classes=True)), _CLICK_CELLS.format(h=_HOPS, t="hour(ts) * 2 + minute(ts) // 30 + case when dayofweek(ts) in (0, 6) then 49 else 0 end"))


def cells_equi_depth(spark, sf_dir):
    return C.aggregate(trips.clicks(spark, sf_dir, bounds=S.equi_depth_bounds(trips.hops(spark, sf_dir), 8)))


_Q = ", ".join(f"{i / 8}" for i in range(1, 8))
add("cells_equi_depth", cells_equi_depth, _CLICK_CELLS.format(h=_HOPS, t=f"(select len(list_filter(q, lambda x: {_SECOND} >= ceil(x))) from (select quantile_cont({_SECOND}, [{_Q}]) q from events))"))
add("cells_quad", lambda s, d: C.aggregate(trips.freight_quads(s, d), "start_end"), f"select s_nationkey::int o, c_nationkey::int d, (month(o_orderdate) - 1)::int t, (month(l_shipdate) - 1)::int t_end, sum(l_quantity::bigint)::bigint flow {_LINES} where s_nationkey <> c_nationkey and l_quantity > 0 group by 1, 2, 3, 4")
_COUNTED = cells_sql("clicks").replace("sum(pax)", "count(*)")
add("hot_clicks_ties", lambda s, d: C.hot(durable(C.aggregate(trips.clicks(s, d, flow="trips"))), "0.1"), f"with c as ({_COUNTED}) select o, d, t from c where flow >= (select min(flow) from (select flow, row_number() over (order by flow desc) k from c) where k <= greatest(1, (select count(*) from c) // 10))")

# graphs and regions
add("graph_grid_edges", graph.grid_edges, f"with {GRID} select u, w v from e")
add("graph_dense_edges", graph.dense_edges, f"with {DENSE} select u, w v from e")
add("graph_path_edges", lambda s, d: graph.path_edges(trips.events(s, d).select("k")), f"with {SEEN_PATH} select u, w v from e")
HOLES = [0, 1, 2, 6, 7, 12, 18, 19, 23, 24]


def graph_components(spark, sf_dir):
    """Parts of the freight grid that is left of some of its regions."""
    g = graph.from_edges(graph.induced(graph.grid_edges(spark, sf_dir), HOLES), 25)
    return graph.component_rows(spark, g).where(F.col("v").isin(HOLES))


_H = ", ".join(map(str, HOLES))
add("graph_components", graph_components, "with recursive " + GRID + f", k as (select u, w from e where u in ({_H}) and w in ({_H})), reach as (select v, v here from n where v in ({_H}) union select v, w from reach join k on u = here) select v, min(here)::int component from reach group by v")


def nearest_region(spark, sf_dir):
    p = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding", "label")
    return regions.nearest(p, durable(regions.centres(p, "label", "embedding")), "vec_id", "embedding")


add("nearest_region", nearest_region, "with c as (select label r, list(x order by i) c from (select label, i, round(avg(x::double), 6) x from (select label, unnest(embedding) x, generate_subscripts(embedding, 1) i from embeddings where label is not null) group by label, i) group by label), s as (select vec_id, r, round(list_sum(list_transform(list_zip(embedding, c), lambda z: (z[1]::double - z[2]) * (z[1]::double - z[2]))), 6) d from embeddings, c where embedding is not null) select vec_id, arg_min(r, (d, r)) r from s group by vec_id")
add("kmeans_regions", lambda s, d: regions.cluster(s.read.parquet(f"{d}/embeddings.parquet"), "vec_id", "embedding", 10))


# indexes
def _hot(spark, sf_dir, name="freight", s_a="0.05"):
    cells, g, slots = net(spark, sf_dir, name)
    return durable(C.hot(cells, s_a)), g, slots


def dests_srcs(spark, sf_dir):
    hot = _hot(spark, sf_dir)[0]
    side = lambda k, a, b: hot.groupBy(F.col(a).alias("r")).agg(F.array_join(F.array_sort(F.collect_set(F.col(b))), ",").alias("partners")).select(F.lit(k).alias("kind"), "r", "partners")
    return side("dests", "o", "d").unionByName(side("srcs", "d", "o"))


add("dests_srcs", dests_srcs, f"with {hot_sql('freight', (1, 20))} select 'dests' kind, o r, array_to_string(list_sort(list(distinct d)), ',') partners from hot group by o union all select 'srcs', d, array_to_string(list_sort(list(distinct o)), ',') from hot group by d")


def packed_rows(spark, sf_dir):
    hot, g, slots = _hot(spark, sf_dir)
    by = mine.Index(hot, g, slots).by["o"]
    return by.select(F.col("i").alias("o"), F.posexplode("m").alias("d", "mask")).where("mask <> 0")


def prefix_sums(spark, sf_dir):
    """The sums over depth-first numbers, read back by region: hot cells among the regions up to both in the order, to a slot."""
    hot, g, slots = _hot(spark, sf_dir)
    ix, ids = mine.Index(hot, g, slots), g.dfs_ids()
    n, s = g.n, slots
    sums = ix._table(ix.prefix().reshape(n + 1, -1), "p").select("i", F.posexplode("p").alias("at", "val"))
    return sums.select("i", F.floor(F.col("at") / (s + 1)).cast("int").alias("j"), (F.col("at") % (s + 1)).alias("k"), "val").where("i > 0 and j > 0 and k > 0")


def prefix_bound_check(spark, sf_dir):
    """For every candidate of level 4: its slab's hot cells, and whether the bound is below them."""
    hot, g, slots = _hot(spark, sf_dir)
    ix = mine.Index(hot, g, slots)
    parts = mine.extend(mine.seed(hot), ix, (2, 2, 2), True)
    rows = mine.together(ix.slab(ix.bounder()(p), dim) for dim, p in parts.items()).dropDuplicates(mine.KEY)
    return mine.flat(rows.select("o", "d", "t_lo", "t_hi", F.col("n").alias("slab"), (F.col("ub") < F.col("n")).alias("below")))


_DFS = graph.square(5).dfs_ids()  # the freight grid: column n_regionkey, row the rank within it
add("packed_rows", packed_rows, f"with {hot_sql('freight', (1, 20))} select o, d, sum(1::bigint << t)::bigint mask from hot group by o, d")
add("prefix_sums", prefix_sums)
_F222 = levels_sql("freight", (1, 20), (1, 2), (2, 2, 2))
_CANDS = f"{_F222}, q as (select om, dm, lo, hi, (select count(*) from hot where (om >> o) & 1 = 1 and (dm >> d) & 1 = 1 and t between lo and hi) cnt from c4) "
add("prefix_bound_check", prefix_bound_check, f"{_CANDS} select array_to_string({members('om', 25)}, ',') o, array_to_string({members('dm', 25)}, ',') d, lo::int t_lo, hi::int t_hi, (cnt - 1)::bigint slab, false below from q")


def level4_candidates(spark, sf_dir):
    hot, g, slots = _hot(spark, sf_dir)
    ix = mine.Index(hot, g, slots)
    parts = mine.extend(mine.seed(hot), ix, (2, 2, 2), True)
    rows = mine.together(ix.slab(p, dim) for dim, p in parts.items()).dropDuplicates(mine.KEY)
    return mine.flat(rows.select("o", "d", "t_lo", "t_hi", (F.col("cnt") + F.col("n")).alias("cnt"), "card"))


add("level4_candidates", level4_candidates, f"{_CANDS} select array_to_string({members('om', 25)}, ',') o, array_to_string({members('dm', 25)}, ',') d, lo::int t_lo, hi::int t_hi, cnt::bigint cnt, 2::bigint card from q")
for _l in (4, 5):
    add(f"level{_l}_dense", lambda s, d, m=_l: mined("freight", "0.05", "0.5", (2, 2, 2), max_level=m)(s, d).where(F.col("level") == m), _F222 + f"select * from named where level = {_l}")

# exact mining
_ALL = "select * from named"
for _m in mine.MODES:
    add(f"mine_freight_{_m}", mined("freight", "0.05", "0.5", (2, 2, 2), _m), _F222 + _ALL)
add("mine_freight_333", mined("freight", "0.05", "0.5", (3, 3, 3)), levels_sql("freight", (1, 20), (1, 2), (3, 3, 3)) + _ALL)
add("mine_freight_sr06", mined("freight", "0.05", "0.6", (3, 3, 3)), levels_sql("freight", (1, 20), (3, 5), (3, 3, 3)) + _ALL)
add("mine_clicks", mined("clicks", "0.05", "0.5", (3, 3, 3)), levels_sql("clicks", (1, 20), (1, 2), (3, 3, 3)) + _ALL)
add("mine_returns", mined("returns", "0.01", "0.5", (2, 2, 2)), levels_sql("returns", (1, 100), (1, 2), (2, 2, 2)) + _ALL)
add("mine_zones_222", mined("zones", "0.01", "0.5", (2, 2, 2)), levels_sql("zones", (1, 100), (1, 2), (2, 2, 2)) + _ALL)
for _i, _side in enumerate("odt"):
    for _b in (1, 3):
        _bounds = tuple(_b if j == _i else 2 for j in range(3))
        add(f"bounded_{_side}{_b}", mined("freight", "0.05", "0.5", _bounds), levels_sql("freight", (1, 20), (1, 2), _bounds) + _ALL)
add("mine_counts_by_level", lambda s, d: mined("freight", "0.05", "0.5", (3, 3, 3))(s, d).groupBy("level").agg(F.count("*").alias("patterns")), levels_sql("freight", (1, 20), (1, 2), (3, 3, 3)) + "select level, count(*) patterns from named group by level")
GRID_SA, GRID_SR = [("0.01", (1, 100)), ("0.02", (1, 50)), ("0.05", (1, 20))], [("0.4", (2, 5)), ("0.5", (1, 2)), ("0.6", (3, 5))]


def mine_grid_sa_sr(spark, sf_dir):
    """Numbers of blocks over thresholds of heat and of density."""
    cells, g, slots = net(spark, sf_dir, "freight")
    rows = []
    for s_a, _ in GRID_SA:
        hot = durable(C.hot(cells, s_a))
        for s_r, _ in GRID_SR:
            n = mine.enumerate_blocks(hot, g, slots, s_r, bounds=(2, 2, 2)).df
            rows.append(n.agg(F.count("*").alias("patterns")).select(F.lit(s_a).alias("s_a"), F.lit(s_r).alias("s_r"), "patterns"))
    return mine.together(rows)


add("mine_grid_sa_sr", mine_grid_sa_sr, " union all ".join(f"select '{a}' s_a, '{r}' s_r, count(*) patterns from ({levels_sql('freight', x, y, (2, 2, 2))} {_ALL})" for a, x in GRID_SA for r, y in GRID_SR))
add("exact_shape_222", mined("freight", "0.1", "0.5", None, shape=(2, 2, 2)), levels_sql("freight", (1, 10), (1, 2), (2, 2, 2)) + "select level, o, d, t_lo, t_hi, cnt, card from named where level = 6")

# limits
_DOM = mine.Domain([0, 1, 5, 6, 10], None, 2, 8)
_DOM_SQL = {"where": "o in (0, 1, 5, 6, 10) and t between 2 and 8", "sides": ("u in (0, 1, 5, 6, 10)", "true"), "slots": (2, 8)}
add("constrained_local", mined("freight", "0.1", "0.5", (2, 2, 2), domain=_DOM), levels_sql("freight", (1, 10), (1, 2), (2, 2, 2), **_DOM_SQL) + _ALL)
add("constrained_global", mined("freight", "0.1", "0.5", (2, 2, 2), domain=_DOM, scope="global"), levels_sql("freight", (1, 10), (1, 2), (2, 2, 2), of="all", **_DOM_SQL) + _ALL)
add("constrained_bounded", mined("freight", "0.1", "0.5", (3, 1, 2), domain=_DOM), levels_sql("freight", (1, 10), (1, 2), (3, 1, 2), **_DOM_SQL) + _ALL)


# ranking
def ranked(mode, k=100, max_level=7, **kw):
    def run(spark, sf_dir):
        hot, g, slots = _hot(spark, sf_dir, s_a="0.1")
        return mine.flat(rank.enumerate_top(hot, g, slots, k, max_level, mode, **kw)[0])

    return run


_RANK = lambda k, last, bounds=(99, 99, 99), **kw: levels_sql("freight", (1, 10), None, bounds, rank_k=k, max_level=last, **kw)
for _k, _m in (("naive", "plain"), ("opt", "full"), ("threshold", "threshold")):
    add(f"rank_{_k}", ranked(_m), _RANK(100, 7) + _ALL)
add("rank_bounded", ranked("threshold", 60, 6, bounds=(2, 2, 2)), _RANK(60, 6, (2, 2, 2)) + _ALL)
add("rank_fraction", ranked("full", None, 5, k_fraction=0.1))
add("rank_per_level_top", lambda s, d: rank.top_per_level(mine.enumerate_blocks(*_hot(s, d), "0.5", bounds=(2, 2, 2)).df, 20).transform(mine.flat), _F222 + f", p as (select *, row_number() over (partition by level order by cnt desc, string_split(o, ',')::int[], string_split(d, ',')::int[], t_lo, t_hi)::int place from named) select * from p where place <= 20")
_FRACTION = _RANK("(select greatest(1, ceil(0.1 * count(*))::bigint) from c{k})", 5)
ORACLES["rank_fraction"] = _FRACTION.replace("c{k}", "c4", 1).replace("c{k}", "c5", 1) + _ALL


# approximations
def _mix(x: str) -> str:
    y = lambda e: f"((({e}) & {approx.BITS}) * 1103515245 + 12345) & {approx.BITS}"
    once = lambda e: f"xor({y(e)}, ({y(e)}) >> 15)"
    return once(once(x))


def hash_sql(*args) -> str:
    return f"list_reduce([0::bigint, {', '.join(f'({a})::bigint' for a in args)}], lambda s, x: {_mix('s + x')})"


def pool_sql(name: str, salt: int, size: int) -> str:
    ctes = [f"{name}1 as (select distinct u seed_vertex, [u] path from e)"]
    for k in range(2, size + 1):
        ctes.append(f"{name}{k} as (select seed_vertex, list_append(path, arg_min(v, (place, h, v))) path from (select seed_vertex, path, place, w v, {hash_sql(salt, 'seed_vertex', 'u', 'w')} h from (select seed_vertex, path, unnest(path) m, generate_subscripts(path, 1) place from {name}{k - 1}) join e on u = m where not list_contains(path, w)) group by seed_vertex, path)")
    return ", ".join(ctes) + f", {name} as (select (row_number() over (order by seed_vertex) - 1)::int idx, seed_vertex, list_sort(path) members from {name}{size})"


_WINDOWS = "pt as (select i::int idx, i::int t_lo, (i + 1)::int t_hi from range(11) r(i))"
_POOLS = f"{hot_sql('freight', (1, 10))}, {GRID}, {pool_sql('po', 1, 2)}, {pool_sql('pd', 2, 2)}, {_WINDOWS}"
_VERIFY = "v as (select o, d, t_lo, t_hi, (select count(*) from hot where list_contains(c.o, hot.o) and list_contains(c.d, hot.d) and hot.t between t_lo and t_hi) cnt, 8::bigint card from (select distinct o, d, t_lo, t_hi from combos) c), found as (select array_to_string(o, ',') o, array_to_string(d, ',') d, t_lo, t_hi, cnt, card from v where 2 * cnt >= card)"
_DRAWS = f"tries as (select i, a, {hash_sql(7, 'i', 'a', 1)} % 25 io, {hash_sql(7, 'i', 'a', 2)} % 25 id, {hash_sql(7, 'i', 'a', 3)} % 11 it from range(1512) x(i), range(64) y(a)), fit as (select i, a, po.members o, pd.members d, pt.t_lo, pt.t_hi from tries join po on po.idx = io join pd on pd.idx = id join pt on pt.idx = it where not list_has_any(po.members, pd.members)), combos as (select * from fit qualify row_number() over (partition by i order by a) = 1)"
_BEST = "w as (select 'o' k, o v, count(*) n from hot group by o union all select 'd', d, count(*) from hot group by d union all select 't', t, count(*) from hot group by t), wo as (select idx, members, (select sum(n) from w where k = 'o' and list_contains(members, v)) n from po), wd as (select idx, members, (select sum(n) from w where k = 'd' and list_contains(members, v)) n from pd), wt as (select idx, t_lo, t_hi, (select sum(n) from w where k = 't' and v between t_lo and t_hi) n from pt), combos as (select wo.members o, wd.members d, t_lo, t_hi from wo, wd, wt where not list_has_any(wo.members, wd.members) order by wo.n * wd.n * wt.n desc, wo.idx, wd.idx, t_lo limit 137)"
SHAPE = (2, 2, 2)


def approximate(kind, **kw):
    def run(spark, sf_dir):
        hot, g, slots = _hot(spark, sf_dir, s_a="0.1")
        make = {"uniform": lambda: approx.uniform(hot, g, slots, "0.5", SHAPE, 1512, **kw)[0], "weighted": lambda: approx.weighted(hot, g, slots, "0.5", SHAPE, 137, **kw), "draw": lambda: approx.weighted_draw(hot, g, slots, "0.5", SHAPE, 1512, **kw), "truth": lambda: approx.ratio_truth(hot, g, slots, "0.5", SHAPE)}
        return mine.flat(make[kind]())

    return run


def approx_recall(spark, sf_dir):
    """For each method and truth: found, true and common blocks."""
    hot, g, slots = _hot(spark, sf_dir, s_a="0.1")
    truth = {"reachable": durable(mine.exact_shape(hot, g, slots, "0.5", SHAPE)), "ratio": durable(approx.ratio_truth(hot, g, slots, "0.5", SHAPE))}
    found = {"uniform": durable(approx.uniform(hot, g, slots, "0.5", SHAPE, 1512)[0]), "weighted": durable(approx.weighted(hot, g, slots, "0.5", SHAPE, 137))}
    return mine.together(approx.accuracy(f, t).select(F.lit(m).alias("method"), F.lit(k).alias("truth"), "*") for m, f in found.items() for k, t in truth.items())


def pool_ceiling(spark, sf_dir):
    hot, g, slots = _hot(spark, sf_dir, s_a="0.1")
    po, pd, _ = approx.pools(spark, g, slots, SHAPE)
    return mine.flat(approx.ceiling(mine.exact_shape(hot, g, slots, "0.5", SHAPE), po, pd).select(*mine.KEY))


_PAIRS = "pair as (select distinct list_sort([u, w]) s from e), combos as (select a.s o, b.s d, pt.t_lo, pt.t_hi from pair a, pair b, pt where not list_has_any(a.s, b.s))"
_FOUND = "select * from found"
add("region_pool_o", lambda s, d: approx.region_pool(s, net(s, d, "freight")[1], 3, 1).withColumn("members", F.array_join("members", ",")), f"with {GRID}, {pool_sql('po', 1, 3)} select idx, seed_vertex, array_to_string(members, ',') members from po")
add("region_pool_d", lambda s, d: approx.region_pool(s, net(s, d, "freight")[1], 4, 2).withColumn("members", F.array_join("members", ",")), f"with {GRID}, {pool_sql('pd', 2, 4)} select idx, seed_vertex, array_to_string(members, ',') members from pd")
_MONTHS = "t as (select distinct (month(o_orderdate) - 1)::int t from orders)"
add("window_pool", lambda s, d: approx.windows_of(trips.months(s, d), 2), f"with {_MONTHS} select (row_number() over (order by a.t) - 1)::int idx, a.t t_lo, b.t t_hi from t a join t b on b.t = a.t + 1")
add("approx_uniform", approximate("uniform"), f"with {_POOLS}, {_DRAWS}, {_VERIFY} {_FOUND}")
add("approx_weighted", approximate("weighted"), f"with {_POOLS}, {_BEST}, {_VERIFY} {_FOUND}")
add("approx_weighted_early_stop", approximate("weighted", early_stop=True), f"with {_POOLS}, {_BEST}, {_VERIFY} {_FOUND}")
add("approx_several_regions", approximate("uniform", per_seed=3))
add("approx_draw", approximate("draw"))
add("truth_ratio_222", approximate("truth"), f"with {_POOLS}, {_PAIRS}, {_VERIFY} {_FOUND}")
_EXACT = f"({levels_sql('freight', (1, 10), (1, 2), SHAPE)} select o, d, t_lo, t_hi from named where level = 6)"
_MADE = {"uniform": f"(with {_POOLS}, {_DRAWS}, {_VERIFY} select o, d, t_lo, t_hi from found)", "weighted": f"(with {_POOLS}, {_BEST}, {_VERIFY} select o, d, t_lo, t_hi from found)"}
_TRUE = {"reachable": _EXACT, "ratio": f"(with {_POOLS}, {_PAIRS}, {_VERIFY} select o, d, t_lo, t_hi from found)"}
add("approx_recall", approx_recall, " union all ".join(f"select '{m}' method, '{k}' truth, (select count(*) from {f} f) n_found, (select count(*) from {t} t) n_exact, (select count(*) from ({f} intersect {t})) n_common" for m, f in _MADE.items() for k, t in _TRUE.items()))
add("pool_ceiling", pool_ceiling, f"with {_POOLS}, x as {_EXACT} select o, d, t_lo, t_hi from x where o in (select array_to_string(members, ',') from po) and d in (select array_to_string(members, ',') from pd)")
add("approx_weights", lambda s, d: approx.weights(_hot(s, d, s_a="0.1")[0]), f"with {hot_sql('freight', (1, 10))} select 'o' kind, o v, count(*) w from hot group by 2 union all select 'd', d, count(*) from hot group by 2 union all select 't', t, count(*) from hot group by 2")

# flows
add("outflow", lambda s, d: flow.outflow(net(s, d, "freight")[0], [0, 5], 0, 2), f"select d, sum(flow)::bigint flow from ({cells_sql('freight')}) where o in (0, 5) and d not in (0, 5) and t between 0 and 2 group by d")
add("inflow", lambda s, d: flow.inflow(net(s, d, "freight")[0], [0, 5], 0, 2), f"select o, sum(flow)::bigint flow from ({cells_sql('freight')}) where d in (0, 5) and o not in (0, 5) and t between 0 and 2 group by o")
add("flow_cube", lambda s, d: flow.cube(net(s, d, "freight")[0]), f"select o, d, t, sum(flow)::bigint flow, grouping(o, d, t)::int gid from ({cells_sql('freight')}) group by cube (o, d, t)")
add("flow_rollup", lambda s, d: flow.rollup(net(s, d, "freight")[0]), f"select o, d, t, sum(flow)::bigint flow, grouping(o, d, t)::int gid from ({cells_sql('freight')}) group by rollup (o, d, t)")


def block_flow(spark, sf_dir):
    cells, g, slots = net(spark, sf_dir, "freight")
    return mine.flat(flow.block_flow(durable(mine.enumerate_blocks(C.hot(cells, "0.05"), g, slots, "0.5", bounds=(2, 2, 2)).df), cells))


_FLOW = "(select coalesce(sum(flow), 0) from cells c where list_contains(string_split(named.o, ','), c.o::varchar) and list_contains(string_split(named.d, ','), c.d::varchar) and c.t between t_lo and t_hi)::bigint flow"
add("block_flow", block_flow, _F222 + f"select *, {_FLOW} from named")


def popular(name, dom, s_a, bounds, top=10):
    """Where a fixed origin's trips of one daypart go: destination regions of its dense blocks by hot cells, then flow."""

    def run(spark, sf_dir):
        cells, g, slots = net(spark, sf_dir, name)
        own = durable(dom.filter(cells))
        found = durable(mine.enumerate_blocks(C.hot(own, s_a), g, slots, "0.5", bounds=bounds, domain=dom).df)
        return mine.flat(flow.popular(flow.block_flow(found, own), top))

    return run


def _popular_sql(name, share, bounds, dom, where, slots, top=10):
    side = lambda v: "true" if v is None else f"u in ({', '.join(map(str, v))})"
    base = levels_sql(name, share, (1, 2), bounds, where=where, slots=slots, sides=(side(dom.origins), side(dom.destinations)))
    return base + f", f as (select *, {_FLOW} from named) select level, o, d, t_lo, t_hi, cnt, card, flow from f order by cnt desc, flow desc, string_split(o, ',')::int[], string_split(d, ',')::int[], t_lo, t_hi limit {top}"


for _q, (_a, _b) in enumerate([(0, 2), (3, 5), (6, 8), (9, 11)]):
    _d = mine.Domain([0], None, _a, _b)
    add(f"usecase_freight_q{_q + 1}", popular("freight", _d, "0.3", (1, 3, 3)), _popular_sql("freight", (3, 10), (1, 3, 3), _d, f"o = 0 and t between {_a} and {_b}", (_a, _b)))
for _p, (_a, _b) in {"morning": (17, 18), "evening": (35, 36)}.items():
    _d = mine.Domain([12], None, _a, _b)
    add(f"usecase_clicks_{_p}", popular("clicks", _d, "0.3", (1, 3, 2)), _popular_sql("clicks", (3, 10), (1, 3, 2), _d, f"o = 12 and t between {_a} and {_b}", (_a, _b)))
_d = mine.Domain(None, [12], 17, 18)
add("usecase_outage", popular("clicks", _d, "0.3", (3, 1, 2)), _popular_sql("clicks", (3, 10), (3, 1, 2), _d, "d = 12 and t between 17 and 18", (17, 18)))


# relations of blocks
def _blocks(spark, sf_dir):
    hot, g, slots = _hot(spark, sf_dir)
    return durable(mine.enumerate_blocks(hot, g, slots, "0.5", bounds=(2, 2, 2)).df)


_ABOVE = "b.level = a.level + 1 and a.om & b.om = a.om and a.dm & b.dm = a.dm and a.lo >= b.lo and a.hi <= b.hi"
_M = lambda x: f"array_to_string({members(x, 25)}, ',')"
add("maximal_blocks", lambda s, d: mine.flat(mine.maximal(_blocks(s, d))), _F222 + f"select level::int as level, {_M('om')} o, {_M('dm')} d, lo::int t_lo, hi::int t_hi, cnt, card from blocks a where not exists (select 1 from blocks b where {_ABOVE})")
add("block_steps", lambda s, d: mine.steps(_blocks(s, d)).select(*[(F.array_join(F.transform(c, lambda x: x.cast("string")), ",") if c in ("o", "d", "b_o", "b_d") else F.col(c)).alias(c) for c in ("o", "d", "t_lo", "t_hi", "b_o", "b_d", "b_lo", "b_hi")]), _F222 + f"select {_M('a.om')} o, {_M('a.dm')} d, a.lo::int t_lo, a.hi::int t_hi, {_M('b.om')} b_o, {_M('b.dm')} b_d, b.lo::int b_lo, b.hi::int b_hi from blocks a join blocks b on {_ABOVE}")
add("unsupported_blocks", lambda s, d: mine.flat(mine.unsupported(_blocks(s, d))), _F222 + "select * from named where false")


# measures
def work_counters(spark, sf_dir):
    """What each mode generates, keeps, skips, looks up and counts at each level."""
    hot, g, slots = _hot(spark, sf_dir)
    names = ("generated", "distinct", "zero_skips", "bound_prunes", "memo_hits", "exact_counts", "probes")
    rows = [(m, x["level"], x["patterns"], *(int(x.get(c) or 0) for c in names)) for m in mine.MODES for x in mine.enumerate_blocks(hot, g, slots, "0.5", m, (2, 2, 2)).stats]
    return spark.createDataFrame(rows, "mode string, level int, patterns bigint, " + ", ".join(f"{c} bigint" for c in names))


def cost_breakdown(spark, sf_dir):
    """Share of the time that making candidates and counting them takes, in thousandths, by mode."""
    hot, g, slots = _hot(spark, sf_dir)
    rows = []
    for m in ("plain", "memo_skip_nbr", "full", "packed"):
        st = mine.enumerate_blocks(hot, g, slots, "0.5", m, (2, 2, 2)).stats
        a, b = (sum(x[k] for x in st) for k in ("generate_s", "count_s"))
        rows.append((m, int(1000 * a / (a + b)), int(1000 * b / (a + b))))
    return spark.createDataFrame(rows, "mode string, prepare_permille bigint, admit_permille bigint")


def cost_formulas(spark, sf_dir):
    """Worst cases for the freight network as its tables have it: nations of customers, months of orders, an order a trip."""
    return costs.rows(trips.sizes(spark, sf_dir))


add("work_counters", work_counters)
add("cost_breakdown", cost_breakdown)
_C = lambda n, k: f"(factorial(({n})::int) / factorial(({k})::int) / factorial(({n} - {k})::int))"
_S = "z as (select (select count(distinct c_nationkey) from customer)::int n, count(distinct month(o_orderdate))::int s, count(*) trips from orders)"
_SUM = f"(select sum({_C('n', 'i')} * {_C('(n - i)', 'j')}) from range(1, 4) a(i), range(1, 4) b(j) where i + j <= n)"
add("cost_formulas", cost_formulas, f"with {_S} select 'levelwise' formula, ((3::bigint**n - 2 * 2::bigint**n + 1) * (s * (s + 1) // 2))::bigint steps from z union all select 'bounded', ({_SUM} * (greatest(s, 0) + greatest(s - 1, 0) + greatest(s - 2, 0)))::bigint from z union all select 'partners', (2 * n * (n - 1))::bigint from z union all select 'prefix', ((n + 1) * (n + 1) * (s + 1))::bigint from z union all select 'pool', (4 * n)::bigint from z union all select 'sampling', (64 * trips)::bigint from z union all select 'combinations', (n * n * greatest(0, s - 3))::bigint from z")


# files
def files_round_trip(spark, sf_dir):
    """Edges through CSV and JSON, blocks through Parquet by level, and mined again from what was read."""
    import uuid

    from .durable import shared_folder

    at = f"{shared_folder(spark)}/files-{uuid.uuid4().hex}"
    edges = graph.grid_edges(spark, sf_dir)
    edges.write.option("header", True).csv(f"{at}/csv")
    edges.write.json(f"{at}/json")
    both = files.read(spark, f"{at}/csv", files.EDGES, "csv").intersect(files.read(spark, f"{at}/json", files.EDGES, "json"))
    cells, _, slots = net(spark, sf_dir, "freight")
    found = mine.enumerate_blocks(C.hot(cells, "0.05"), graph.from_edges(both, 25), slots, "0.5", bounds=(2, 2, 2)).df
    files.write_blocks(found, f"{at}/blocks")
    return mine.flat(files.read_blocks(spark, f"{at}/blocks"))


add("files_round_trip", files_round_trip, _F222 + _ALL)

# streams
_STAMP = "yyyy-MM-dd HH:mm:ss"


def _stream_trips(spark, sf_dir):
    rows = trips.hops(spark, sf_dir).where("o <> d and pax > 0").withColumn("ts", F.col("ts").cast("timestamp"))
    return stream.replay(rows, 4)


def _stamped(df):
    return df.withColumn("start", F.date_format("start", _STAMP))


_HOP_ROWS = f"(select * from ({_HOPS}) where o <> d and pax > 0 and d is not null)"
add("stream_cells_tumbling", lambda s, d: _stamped(stream.run(stream.tumbling(_stream_trips(s, d)))[0]), f"select strftime(time_bucket(interval '30 minutes', ts), '%Y-%m-%d %H:%M:%S') start, o::int o, d::int d, sum(pax)::bigint flow from {_HOP_ROWS} group by 1, 2, 3")
add("stream_cells_sliding", lambda s, d: _stamped(stream.run(stream.sliding(_stream_trips(s, d)))[0]), f"select strftime(time_bucket(interval '30 minutes', ts) - interval (30 * k) minutes, '%Y-%m-%d %H:%M:%S') start, o::int o, d::int d, sum(pax)::bigint flow from {_HOP_ROWS}, range(4) r(k) group by 1, 2, 3")
_EV = "(select *, (cast(json_extract_string(props, '$.k') as int) // 4)::int k from events)"
add("stream_sessions", lambda s, d: _stamped(stream.run(stream.sessions(stream.replay(trips.events(s, d), 4)))[0]).where("user_id is not null"), f"with x as (select *, case when ts <= lag(ts) over (partition by user_id order by ts, event_id) + interval '30 minutes' then 0 else 1 end fresh from {_EV}), y as (select *, sum(fresh) over (partition by user_id order by ts, event_id rows unbounded preceding) no from x) select strftime(min(ts), '%Y-%m-%d %H:%M:%S') start, user_id, arg_min(k, (ts, event_id)) o, arg_max(k, (ts, event_id)) d, count(*) n from y group by user_id, no")
add("stream_hops", lambda s, d: stream.run(stream.hops(stream.replay(trips.events(s, d), 3)))[0].withColumn("ts", F.date_format("ts", _STAMP)), f"select o::int o, d::int d, strftime(ts, '%Y-%m-%d %H:%M:%S') ts, pax from ({_HOPS}) where d is not null")


def stream_incremental(spark, sf_dir):
    """Cells of the clicks network, kept by the batches of a stream."""
    rows = trips.hops(spark, sf_dir)
    rows = trips.valid(rows.withColumn("t", S.uniform(F.col("ts")))).withColumn("ts", F.col("ts").cast("timestamp"))
    store = stream.CellStore(spark)
    live = stream.replay(rows.select("ts", "o", "d", "t", "pax"), 3)
    q = live.where("o is not null").writeStream.foreachBatch(store.add).option("checkpointLocation", f"{stream.shared_folder(spark)}/log-{stream.uuid.uuid4().hex}").trigger(availableNow=True).start()
    q.awaitTermination()
    return store.now


add("stream_incremental", stream_incremental, cells_sql("clicks"))


def flagship(spark, sf_dir):
    return mined("freight", "0.05", "0.5", (2, 2, 2))(spark, sf_dir)
