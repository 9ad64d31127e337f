"""The hand-made map: A..E = 0..4, edges A-B, B-C, B-D, C-D, D-E; slots of half an hour."""
import itertools
import random

import pytest
from pyspark.sql import functions as F

from flowblocks import costs
from flowblocks.operators import cells, flow
from flowblocks.operators.graph import Graph, checked, square
from flowblocks.plans import approx, mine, rank

GRAPH = Graph(5, [(0, 1), (1, 2), (1, 3), (2, 3), (3, 4)])
CELL = "o int, d int, t int"


@pytest.fixture(scope="module")
def hot(spark):
    trips = spark.createDataFrame([(1, 3, 18, 2), (1, 3, 18, 1), (0, 3, 18, 4), (2, 3, 19, 1), (0, 4, 17, 1), (3, 0, 34, 1)], CELL + ", pax bigint")
    c = cells.aggregate(trips)
    assert c.where("o = 1").first().flow == 3
    return cells.hot(c, "0.5")


def rows(df):
    return {(tuple(r.o), tuple(r.d), r.t_lo, r.t_hi, r.cnt, r.card) for r in df.collect()}


def brute(sample, graph, slots, bounds, ratio=0.5):
    """{block: hot cells} of every dense block that dense blocks lead to."""
    inside = lambda b: sum(c in sample for c in itertools.product(b[0], b[1], range(b[2], b[3] + 1)))
    truth, front = {}, {((o,), (d,), t, t) for o, d, t in sample}
    while front:
        truth |= {b: inside(b) for b in front}
        nxt = set()
        for o, d, lo, hi in front:
            nxt |= {(tuple(sorted((*o, r))), d, lo, hi) for v in o for r in graph.adj[v] if r not in o + d and len(o) < bounds[0]}
            nxt |= {(o, tuple(sorted((*d, r))), lo, hi) for v in d for r in graph.adj[v] if r not in o + d and len(d) < bounds[1]}
            nxt |= {(o, d, *x) for x in ((lo - 1, hi), (lo, hi + 1)) if x[0] >= 0 and x[1] < slots and x[1] - x[0] < bounds[2]}
        front = {b for b in nxt if inside(b) >= ratio * len(b[0]) * len(b[1]) * (b[3] - b[2] + 1)}
    return truth


def sampled(seed, regions, slots, n):
    cube = [(o, d, t) for o in range(regions) for d in range(regions) for t in range(slots) if o != d]
    return set(random.Random(seed).sample(cube, n))


def test_hot(hot):
    assert {tuple(r) for r in hot.collect()} == {(0, 3, 18), (1, 3, 18)}


@pytest.mark.parametrize("scale", [1, 7, 3001, 10**9 + 7])
def test_threshold_of_hot_cells_equals_a_sort(spark, scale):
    rng = random.Random(scale)
    flows = [1 + rng.randrange(60) * scale for _ in range(400)]
    c = spark.createDataFrame([(i, 0, 0, f) for i, f in enumerate(flows)], CELL + ", flow bigint")
    ordered = sorted(flows, reverse=True)
    for s_a, r in (("0.01", 4), ("0.1", 40), ("1", 400), ("0.001", 1)):
        assert cells.minsup(c, s_a) == (ordered[r - 1], 400)
    assert cells.minsup(c, "0.0101", "ceil") == (ordered[4], 400)
    assert cells.hot(c, "0.1", ties="cut").count() == 40 and cells.minsup(c.limit(0), "0.1") == (0, 0)


@pytest.mark.parametrize("mode", ["plain", "full", "packed"])
def test_two_origins_make_one_dense_block(hot, mode):
    got = rows(mine.enumerate_blocks(hot, GRAPH, 48, "0.6", mode, (2, 2, 2)).df)
    assert ((0, 1), (3,), 18, 18, 2, 2) in got
    assert not any(hi > lo and len(o) == 1 for o, _, lo, hi, *_ in got)


def test_all_modes_agree_with_brute_force(spark):
    sample = sampled(3, 5, 4, 20)
    h = spark.createDataFrame(sorted(sample), CELL)
    truth = brute(sample, GRAPH, 4, (2, 2, 2))
    for mode in mine.MODES:
        found = mine.enumerate_blocks(h, GRAPH, 4, "0.5", mode, (2, 2, 2))
        assert {x[:4]: x[4] for x in rows(found.df)} == truth
        assert sum(x["patterns"] for x in found.stats) == len(truth)
        assert mine.unsupported(found.df).count() == 0
    naive, fast, bounded = (rows(rank.enumerate_top(h, GRAPH, 4, 8, 5, m)[0]) for m in ("plain", "threshold", "full"))
    assert naive == fast == bounded


def test_slots_of_several_mask_words(spark):
    sample = {(o, d, t) for o, d, t in sampled(5, 4, 97, 60)} | {(0, 1, t) for t in range(58, 66)} | {(2, 1, 61), (2, 1, 62)}
    g, h = Graph(4, [(0, 2), (1, 3), (0, 3)]), spark.createDataFrame(sorted(sample), CELL)
    truth = brute(sample, g, 97, (2, 2, 3))
    for mode in ("full", "packed"):
        assert {x[:4]: x[4] for x in rows(mine.enumerate_blocks(h, g, 97, "0.5", mode, (2, 2, 3)).df)} == truth
    every, _ = approx.uniform(h, g, 97, "0.5", (2, 1, 2), 400)
    assert {x[:4] for x in rows(every)} <= {x[:4] for x in rows(approx.ratio_truth(h, g, 97, "0.5", (2, 1, 2)))}
    assert approx.weighted(h, g, 97, "0.5", (2, 1, 2), 50).count() and len(rank.enumerate_top(h, g, 97, 5, 5)[1]) == 3


def test_the_published_size_of_map(spark):
    n, slots = 315, 48
    rng = random.Random(9)
    g = Graph(n, [(i, i + 1) for i in range(n - 1)] + [(i, i + 18) for i in range(n - 18)])
    sample = sorted({(rng.randrange(n), rng.randrange(n), rng.randrange(slots)) for _ in range(150)} | {(o, d, 20) for o in (100, 101, 118) for d in (200, 201)})
    h = spark.createDataFrame([x for x in sample if x[0] != x[1]], CELL)
    full, packed = (mine.enumerate_blocks(h, g, slots, "0.6", m, (3, 2, 2)) for m in ("full", "packed"))
    assert not full.notes and rows(full.df) == rows(packed.df)
    assert ((100, 101, 118), (200, 201), 20, 20, 6, 6) in rows(packed.df)
    assert sum(x["bound_prunes"] for x in full.stats) > 0


def test_the_bound_is_never_below_the_slab(spark):
    sample = sampled(8, 5, 6, 40)
    h = spark.createDataFrame(sorted(sample), CELL)
    ix = mine.Index(h, GRAPH, 6)
    p, ids = ix.prefix(), GRAPH.dfs_ids()
    for lo, hi in ((0, 0), (1, 4), (0, 5)):  # the eight-term identity on boxes of numbers
        for a, b, c, d in ((0, 2, 1, 4), (0, 5, 0, 5), (3, 4, 2, 3)):
            box = sum((-1) ** (x + y + z + 1) * p[(a, b)[x], (c, d)[y], (lo, hi + 1)[z]] for x in (0, 1) for y in (0, 1) for z in (0, 1))
            assert box == sum(a <= ids[o] < b and c <= ids[e] < d and lo <= t <= hi for o, e, t in sample)
    parts = mine.extend(mine.seed(h), ix, (2, 2, 2), True)
    got = mine.together(ix.slab(ix.bounder()(x), dim) for dim, x in parts.items())
    assert got.where("ub < n").count() == 0 and got.count() > 0


def test_limits(spark):
    sample = sampled(4, 5, 6, 50)
    h = spark.createDataFrame(sorted(sample), CELL)
    dom = mine.Domain([0, 4], None, 1, 4)
    found = mine.enumerate_blocks(dom.filter(h), GRAPH, 6, "0.5", "packed", (2, 2, 2), dom)
    assert found.notes == ["the allowed origins are not connected"]
    assert all(set(o) <= {0, 4} and 1 <= lo <= hi <= 4 for o, _, lo, hi, *_ in rows(found.df))
    small, large = (rows(mine.enumerate_blocks(h, GRAPH, 6, "0.5", bounds=b).df) for b in ((1, 2, 2), (2, 2, 2)))
    assert small == {x for x in large if len(x[0]) == 1}
    with pytest.raises(TimeoutError):
        mine.enumerate_blocks(h, GRAPH, 6, "0.5", timeout_s=0)
    with pytest.raises(RuntimeError):
        mine.enumerate_blocks(h, GRAPH, 6, "0.5", max_blocks=3)
    assert rows(rank.enumerate_top(h, GRAPH, 6, None, 4, "plain", k_fraction=1.0)[0]) >= rows(rank.enumerate_top(h, GRAPH, 6, 5, 4, "plain")[0])
    assert mine.enumerate_blocks(h.limit(0), GRAPH, 6, "0.5").df.count() == 0


def test_approximations(spark):
    g = square(4)
    sample = sampled(2, 16, 6, 500)
    h = spark.createDataFrame(sorted(sample), CELL)
    truth = rows(approx.ratio_truth(h, g, 6, "0.5", (2, 2, 2)))
    pool = approx.region_pool(spark, g, 3, 1)
    for r in pool.collect():
        assert len(r.members) == 3 and g.is_connected(r.members) and r.seed_vertex in r.members
    assert approx.region_pool(spark, Graph(3, [(0, 1)]), 3, 1).count() == 0
    assert approx.region_pool(spark, g, 3, 1, per_seed=4).count() > pool.count()
    one, counts = approx.uniform(h, g, 6, "0.5", (2, 2, 2), 300)
    assert rows(one) <= truth and counts == {"accepted": 300, "shortfall": 0}
    spark.conf.set("spark.sql.shuffle.partitions", "3")
    assert rows(approx.uniform(h, g, 6, "0.5", (2, 2, 2), 300)[0]) == rows(one)  # no matter how the rows are dealt
    spark.conf.set("spark.sql.shuffle.partitions", "2")
    full, early = (rows(approx.weighted(h, g, 6, "0.5", (2, 2, 2), 40, early_stop=e)) for e in (False, True))
    assert full == early and full <= truth
    assert rows(approx.weighted_draw(h, g, 6, "0.5", (2, 2, 2), 200)) <= truth
    a = approx.accuracy(one, approx.ratio_truth(h, g, 6, "0.5", (2, 2, 2))).first()
    assert (a.n_found, a.n_exact, a.n_common) == (len(rows(one)), len(truth), len(rows(one)))
    assert approx.portable_hash(7, 5, 0, 1) == 1181085690
    assert spark.range(1).select(approx.hash_column(7, F.lit(5), 0, 1)).first()[0] == 1181085690


def test_block_relations_and_flows(spark):
    c = spark.createDataFrame([(0, 1, 0, 5), (0, 2, 0, 7), (3, 1, 1, 2)], CELL + ", flow bigint")
    b = spark.createDataFrame([(3, [0], [1], 0, 0, 1, 1), (4, [0], [1, 2], 0, 0, 2, 2), (5, [0], [1, 2], 0, 1, 2, 4)], "level int, o array<int>, d array<int>, t_lo int, t_hi int, cnt bigint, card bigint")
    assert {r.level: r.flow for r in flow.block_flow(b, c).collect()} == {3: 5, 4: 12, 5: 12}
    assert [r.level for r in mine.maximal(b).collect()] == [5] and mine.steps(b).count() == 2 and mine.unsupported(b).count() == 0
    two = b.alias("a").crossJoin(b.alias("b"))
    cols = lambda x: [F.col(f"{x}.{k}") for k in mine.KEY]
    assert two.where(mine.is_generalization(cols("a"), cols("b"))).count() == 6


def test_graphs(spark):
    assert GRAPH.is_connected([0, 1, 2]) and not GRAPH.is_connected([0, 2]) and len(Graph(4, [(0, 1)]).components()) == 3
    assert set(checked(spark.createDataFrame([(0, 1)] * 50 + [(2, 2)], "u int, v int"))) == {(0, 1)}


def test_costs_by_counting():
    sides = [(a, b) for a in itertools.product((0, 1), repeat=4) for b in itertools.product((0, 1), repeat=4) if any(a) and any(b) and not any(x & y for x, y in zip(a, b))]
    assert costs.levelwise(4, 3) == len(sides) * 6 == costs.bounded(4, 3, (4, 4, 3))
    assert costs.prefix(2, 3) == 36 and costs.sampling(10, (2, 3, 4)) == 240 and costs.combinations(3, 5, (1, 1, 2)) == 36


def test_entry_imports():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())
