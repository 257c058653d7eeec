"""Worked examples, invariants and edges of the cuts and of diffusion."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from tilebalance.operators import diffusion, partition
from tilebalance.operators.cost import LoadMap, gather, tile_load
from tilebalance.operators.grid import Grid
from tilebalance.plans.methods import costs
from tilebalance.sources.tables import grid_of

SF = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def loads(spark):
    return costs(spark, SF)


def boxes(cut):
    return [(*x.box, x.load) for x in cut.leaves]


def test_golden_cuts(loads):
    assert loads.total == 10_000 and int((loads.cost > 0).sum()) == 417 and loads.cost.max() == 124
    assert boxes(partition.share_cut(loads, 4)) == [(0, 16, 0, 2, 2784), (0, 16, 2, 32, 2201), (16, 32, 0, 2, 2828), (16, 32, 2, 32, 2187)]
    five = partition.share_cut(loads, 5)
    assert boxes(five) == [(0, 13, 0, 2, 2288), (0, 13, 2, 32, 1793), (13, 32, 0, 1, 1986), (13, 22, 1, 32, 1872), (22, 32, 1, 32, 2061)]
    assert [x.height for x in five.leaves] == [2, 2, 2, 3, 3]
    assert partition.share_cut(loads, 8, "y").loads() == [1636, 1148, 1690, 1138, 1270, 931, 1212, 975]
    assert boxes(partition.strips(loads, [2, 3])) == [(0, 13, 0, 2, 2288), (0, 13, 2, 32, 1793), (13, 32, 0, 1, 1986), (13, 32, 1, 3, 2192), (13, 32, 3, 32, 1741)]
    assert partition.even_tiles(grid_of("EV"), 2, 4, loads).loads() == [4802, 178, 5, 0, 4833, 175, 7, 0]


def test_golden_imbalance(spark):
    for n, share, strips in ((16, 1.2032, 4.5568), (32, 1.3824, 2.7168), (64, 1.2288, 1.5744), (128, 1.0752, 1.296)):
        now = costs(spark, SF, n=n)
        assert round(partition.imbalance(partition.share_cut(now, 32).loads()), 4) == share
        assert round(partition.imbalance(partition.strips(now, [8] * 4).loads()), 4) == strips


def test_golden_moves(spark, loads):
    old = partition.share_cut(loads, 8, "y")
    for t, static, full, limited, tiles, moved in ((10, 1.5664, 1.3496, 1.4088, 32, 740), (50, 3.2272, 1.1136, 1.8184, 272, 3593), (100, 3.5056, 1.0664, 1.8456, 448, 4217)):
        now = costs(spark, SF, t=t)
        cut = partition.tethered_cut(old, now)
        away = cut.owners() != old.owners()
        assert round(partition.imbalance(old.reloaded(now).loads()), 4) == static
        assert round(partition.imbalance(partition.share_cut(now, 8, "y").loads()), 4) == full
        assert (round(partition.imbalance(cut.loads()), 4), int(away.sum()), int(now.cost[away].sum())) == (limited, tiles, moved)
    # drift along y cannot be followed by cuts along x: the limited cut is stuck and the fallback fires
    cut, full = partition.tethered_or_full(partition.share_cut(loads, 8), costs(spark, SF, t=50))
    assert full and partition.imbalance(cut.loads()) < 1.25


def test_golden_exchange(loads):
    cut = partition.even_tiles(grid_of("EV"), 2, 4, loads)
    want = [[2784, 2196, 3, 2, 2828, 2180, 5, 2], [2784, 1270, 929, 2, 2828, 1212, 973, 2], [1636, 2418, 525, 406, 1690, 2350, 544, 431], [1636, 1148, 1795, 406, 1690, 1138, 1756, 431], [1636, 1148, 1270, 931, 1690, 1138, 1212, 975]]
    for t, row in enumerate(want, 1):
        cut = diffusion.strip_exchange(cut, loads, t)
        assert cut.loads() == row
    for t in (6, 7):
        assert diffusion.strip_exchange(cut, loads, t).loads() == want[-1]


def test_scalar_exchange(spark):
    start = spark.createDataFrame([(0, 16), (1, 0), (2, 0), (3, 0)], "pid long, load long")
    rows = diffusion.exchange(start, diffusion.chain(spark, 4), 4).collect()
    got = {t: [r["load"] for r in sorted(rows, key=lambda r: r["pid"]) if r["t"] == t] for t in range(5)}
    assert got == {0: [16, 0, 0, 0], 1: [8, 8, 0, 0], 2: [8, 4, 4, 0], 3: [6, 6, 2, 2], 4: [6, 4, 4, 2]}
    pair = spark.createDataFrame([(0, 10), (1, 2)], "pid long, load long")
    link = spark.createDataFrame([(0, 1)], "a long, b long")
    one = {r["pid"]: r["load"] for r in diffusion.diffuse(pair, link, 0.25).where("t = 1").collect()}
    two = {r["pid"]: r["load"] for r in diffusion.diffuse(pair, link, 0.25, spark.createDataFrame([(0, 1)], "pid long, load long")).where("t = 1").collect()}
    assert one == {0: 8, 1: 4} and two == {0: 9, 1: 4}


def test_colours(spark):
    links = {(r["a"] + 1, r["b"] + 1): r["colour"] for r in diffusion.colour_grid(spark, 4, 4).collect()}
    assert len(links) == 24 and links[5, 6] == 1 and links[6, 7] == 2 and links[2, 6] == 3 and links[6, 10] == 0
    of_one = {c for pair, c in links.items() if 1 in pair}
    assert of_one == {0, 2}
    for node in range(1, 17):
        mine = [c for pair, c in links.items() if node in pair]
        assert len(mine) == len(set(mine))
    torus = diffusion.colour_grid(spark, 4, 4, torus=True).collect()
    assert len(torus) == 32
    for node in range(16):
        mine = [r["colour"] for r in torus if node in (r["a"], r["b"])]
        assert sorted(mine) == [0, 1, 2, 3]


def test_pair_schedule():
    assert diffusion.pairs((5,), 1) == [(0, 0, 1), (0, 2, 3)]
    assert diffusion.pairs((2, 3), 1) == [(0, 0, 1), (1, 0, 1)]
    assert diffusion.pairs((2, 3), 2) == [(0, 0, 1), (1, 1, 2)]
    assert diffusion.pairs((1,), 1) == []
    assert diffusion.volume(16, 0, 3) == 2


grids = st.integers(2, 9).flatmap(lambda n: st.integers(2, 9).flatmap(lambda m: st.lists(st.integers(0, 5), min_size=n * m, max_size=n * m).map(lambda v: LoadMap(np.array(v).reshape(n, m)))))


@settings(max_examples=60, deadline=None)
@given(grids, st.integers(1, 9), st.sampled_from(["x", "y"]), st.sampled_from(["alternate", "longest", "aspect"]))
def test_cuts_cover_the_grid(loads, parts, first, rule):
    if parts > loads.n * loads.m:
        return
    cut = partition.share_cut(loads, parts, first, rule)
    owners = cut.owners()
    assert set(owners.ravel().tolist()) == set(range(parts)) and sum(cut.loads()) == loads.total
    assert sum((x.x1 - x.x0) * (x.y1 - x.y0) for x in cut.leaves) == loads.n * loads.m
    for x in cut.leaves:
        assert (owners[x.x0 : x.x1, x.y0 : x.y1] == x.pid).all()


@settings(max_examples=60, deadline=None)
@given(grids, st.integers(1, 8))
def test_dichotomy_finds_the_best_line(loads, parts):
    if parts <= loads.n * loads.m:
        assert boxes(partition.share_cut(loads, parts, search="dichotomy")) == boxes(partition.share_cut(loads, parts))


@settings(max_examples=60, deadline=None)
@given(grids, grids)
def test_limited_cuts_move_one_border(a, b):
    if (a.n, a.m) != (b.n, b.m):
        b = LoadMap(a.cost[::-1, ::-1].copy())
    old = partition.share_cut(a, 4)
    for level in (None, 0, 1):
        new = partition.tethered_cut(old, b, level)
        assert sorted(new.owners().ravel().tolist()) == sorted(new.owners().ravel().tolist()) and (new.owners() >= 0).all()
        assert [(x.dim, x.p_first, x.p_count) for x in new.nodes] == [(x.dim, x.p_first, x.p_count) for x in old.nodes]
        for x, y in zip(old.leaves, new.leaves, strict=True):
            assert sum(p != q for p, q in zip(x.box, y.box, strict=True)) <= 1
            assert y.x0 < y.x1 and y.y0 < y.y1


@settings(max_examples=60, deadline=None)
@given(grids, st.integers(1, 4))
def test_exchange_keeps_sums_and_narrows_pairs(loads, t):
    rows = [min(2, loads.m), min(3, loads.m)]
    cut = partition.strips(loads, rows)
    new = diffusion.strip_exchange(cut, loads, t)
    assert sum(new.loads()) == loads.total and (new.owners() >= 0).all()
    start = np.cumsum([0, *rows])
    for c, r, s in diffusion.pairs(tuple(rows), t):
        i, j = start[c] + r, start[c] + s
        assert abs(new.loads()[i] - new.loads()[j]) <= abs(cut.loads()[i] - cut.loads()[j])


def test_edges(spark):
    one = LoadMap(np.arange(12).reshape(3, 4))
    assert boxes(partition.share_cut(one, 1)) == [(0, 3, 0, 4, 66)]
    assert partition.share_cut(one, 12).parts == 12
    with pytest.raises(partition.TooManyProcessors):
        partition.share_cut(one, 13)
    with pytest.raises(ValueError):
        partition.halving(one, 6)
    assert partition.share_cut(LoadMap(np.array([[1, 2, 3, 4]])), 3).parts == 3
    lump = np.zeros((4, 4), np.int64)
    lump[2, 1] = 9
    assert sum(partition.share_cut(LoadMap(lump), 4).loads()) == 9
    assert partition.imbalance([0, 0]) == 1.0
    empty = spark.createDataFrame([], "x long, y long, vx long, vy long")
    assert gather(tile_load(empty, Grid(4, 4, 16, 16)), Grid(4, 4, 16, 16)).total == 0


def test_levels_engine_equals_the_driver_engine(spark, loads):
    from tilebalance.operators.lineage import shared
    from tilebalance.sources.tables import particles

    shared(spark)
    grid = grid_of("EV")
    table = tile_load(particles(spark, SF, "EV"), grid)
    for parts, first in ((5, "x"), (7, "y")):
        rows = sorted(tuple(r) for r in partition.share_cut_levels(table, grid, parts, first).collect())
        assert rows == sorted((x.pid, *x.box, x.height, x.load) for x in partition.share_cut(loads, parts, first).leaves)


def test_owner_expression_equals_the_map(spark, loads):
    from pyspark.sql import functions as F

    from tilebalance.operators.grid import tiles

    for cut in (partition.share_cut(loads, 7), partition.strips(loads, [2, 3, 1]), partition.even_tiles(grid_of("EV"), 3, 5, loads)):
        owners = cut.owners()
        rows = tiles(spark, grid_of("EV")).select("ti", "tj", cut.owner().alias("pid")).collect()
        assert all(owners[r["ti"], r["tj"]] == r["pid"] for r in rows) and len(rows) == 1024
        back = {r["pid"]: (r["x0"], r["x1"], r["y0"], r["y1"], r["full"]) for r in partition.collapse(partition.expand(cut.frame(spark))).collect()}
        assert back == {x.pid: (*x.box, True) for x in cut.leaves}
        assert F is not None
