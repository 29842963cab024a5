"""Driver-side planning against brute force and the worked fixtures."""

import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from gridtide.config import EVENTS, GridSpec
from gridtide.operators.governor import Governor
from gridtide.operators.planner import AxisStats, best_split, exact_subset, greedy_subset, rebalance_once
from gridtide.operators.routing import border_walk
from gridtide.plans.layout import Tile, covers, even_layout, merge_tiles, move_tiles, split_tile
from gridtide.plans.lineage import prune, resolve_chain, tile_history


def random_layout(rng, side, pieces):
    tiles = [Tile(0, 0, 0, 0, side - 1, side - 1)]
    while len(tiles) < pieces:
        big = [t for t in tiles if t.area > 1]
        if not big:
            break
        t = rng.choice(big)
        axis = rng.choice([a for a, n in (("row", t.height), ("col", t.width)) if n > 1])
        n = t.height if axis == "row" else t.width
        tiles = split_tile(tiles, t.tile_id, axis, rng.randrange(n - 1), "second", rng.randrange(4), 1)
    return tiles


@pytest.mark.parametrize("machines", [1, 2, 3, 5, 8, 22])
def test_even_layout_covers_with_near_equal_areas(machines):
    tiles = even_layout(EVENTS, machines)
    assert covers(EVENTS, tiles) and len(tiles) == machines
    areas = sorted(t.area for t in tiles)
    assert areas[-1] <= 2 * areas[0] + EVENTS.side


def test_even_layout_stops_at_cells():
    assert len(even_layout(GridSpec(side=2), 9)) == 4


@given(st.integers(0, 10**6))
@settings(max_examples=150, deadline=None)
def test_walk_finds_every_overlapping_tile(seed):
    rng = random.Random(seed)
    tiles = random_layout(rng, 8, rng.randrange(1, 14))
    walk = border_walk(tiles)
    x0, y0 = rng.randrange(8), rng.randrange(8)
    x1, y1 = rng.randrange(x0, 8), rng.randrange(y0, 8)
    want = {t.tile_id for t in tiles if t.cx0 <= x1 and t.cx1 >= x0 and t.cy0 <= y1 and t.cy1 >= y0}
    got = [i for i, _ in walk(x0, y0, x1, y1)]
    assert set(got) == want and len(got) == len(want)


def test_walk_trap():
    tiles = [Tile(i, i, *b) for i, b in enumerate([(0, 0, 0, 1), (0, 2, 0, 3), (1, 0, 1, 3), (2, 0, 2, 1), (2, 2, 2, 3)])]
    assert len(border_walk(tiles)(0, 0, 2, 3)) == 5
    assert len(border_walk(tiles, "first_met")(0, 0, 2, 3)) < 5


def axes_of(points, rects, tile):
    out = {}
    for axis in ("row", "col"):
        size = tile.height if axis == "row" else tile.width
        c = [np.zeros(size) for _ in range(5)]
        for x, y, new in points:
            c[0][y if axis == "row" else x] += 1
            c[2][y if axis == "row" else x] += new
        for x0, y0, x1, y1, new in rects:
            a, b = (y0, y1) if axis == "row" else (x0, x1)
            c[1][a] += 1
            c[2][a] += new
            c[3][a + 1 : b + 1] += 1
            c[4][a + 1 : b + 1] += new
        out[axis] = AxisStats(np.cumsum(c[0]), np.cumsum(c[1]), np.cumsum(c[2]), c[3], c[4])
    return out


def random_tile(rng, w, h):
    points = [(rng.randrange(w), rng.randrange(h), rng.random() < 0.5) for _ in range(rng.randrange(60))]
    rects = []
    for _ in range(rng.randrange(30)):
        x0, y0 = rng.randrange(w), rng.randrange(h)
        rects.append((x0, y0, rng.randrange(x0, w), rng.randrange(y0, h), rng.random() < 0.5))
    return points, rects


@given(st.integers(0, 10**6))
@settings(max_examples=150, deadline=None)
def test_parts_equal_direct_counts_at_every_line(seed):
    rng = random.Random(seed)
    w, h = rng.randrange(1, 9), rng.randrange(1, 9)
    tile = Tile(0, 0, 0, 0, w - 1, h - 1)
    points, rects = random_tile(rng, w, h)
    axes = axes_of(points, rects, tile)
    for axis, size in (("row", h), ("col", w)):
        for line in range(size - 1):
            want = []
            for low, high in ((0, line), (line + 1, size - 1)):
                inside = [new for x, y, new in points if low <= (y if axis == "row" else x) <= high]
                over = [r[4] for r in rects if (r[1] if axis == "row" else r[0]) <= high and (r[3] if axis == "row" else r[2]) >= low]
                want.append(len(inside) * len(over) * (sum(inside) + sum(over)))
            assert axes[axis].parts(line) == tuple(want)


@given(st.integers(0, 10**6))
@settings(max_examples=200, deadline=None)
def test_binary_split_equals_scan(seed):
    rng = random.Random(seed)
    w, h = rng.randrange(1, 12), rng.randrange(1, 12)
    points, rects = random_tile(rng, w, h)
    axes = axes_of(points, rects, Tile(0, 0, 0, 0, w - 1, h - 1))
    tile = float(axes["row"].n[-1] * axes["row"].q[-1] * axes["row"].r[-1])
    high, low = tile + rng.randrange(1000), float(rng.randrange(1000))
    a, b = best_split(axes, tile, high, low), best_split(axes, tile, high, low, "scan")
    assert (a is None) == (b is None) == (w == h == 1)
    if a:
        assert (a.gap, a.axis, a.moved, a.after) == (b.gap, b.axis, b.moved, b.after)


def test_subsets():
    costs = [(1, 8), (2, 5), (3, 4), (4, 3)]
    assert greedy_subset(costs, 9) == ([1], 8.0)
    assert exact_subset(costs, 9) == 9
    assert greedy_subset([(1, 60), (2, 30), (3, 10)], 40) == ([2, 3], 40.0)
    assert greedy_subset(costs, 9, "arrival") == ([1], 8.0)


@given(st.lists(st.integers(1, 1000), min_size=1, max_size=9), st.integers(1, 3000))
def test_greedy_reaches_half_of_the_best(costs, cap):
    tiles = list(enumerate(costs))
    best = exact_subset(tiles, cap)
    assert greedy_subset(tiles, cap)[1] >= best / 2


def test_governor_sequences():
    g = Governor(beta=20)
    assert [g.step(r) for r in (10, 9, 8)] == [False, False, True] and g.stage == 0
    assert [g.step(r) for r in (7, 6)] == [True, False]
    g = Governor(beta=20)
    for r in range(1, 8):
        g.step(r)
    assert g.stage == 2 and not g.rebalance
    g = Governor(beta=3)
    assert [g.step(r) for r in (1, 2, 3, 4, 5, 6)] == [False, False, False, True, True, True]
    g = Governor()
    assert [g.step(5) for _ in range(3)] == [False, False, True]


def test_one_cell_hotspot_ends_alone():
    tiles = [Tile(0, 0, 0, 0, 0, 0), Tile(1, 0, 1, 0, 3, 3), Tile(2, 1, 0, 1, 0, 3)]
    costs = {0: 100.0, 1: 5.0, 2: 1.0}
    new, act = rebalance_once(tiles, {0: 105.0, 1: 1.0}, lambda m: costs, None, 1)
    assert act.kind == "subset" and act.tiles == (1,)
    assert [t.tile_id for t in new if t.machine_id == 0] == [0]
    asked = []
    new, act = rebalance_once([Tile(0, 0, 0, 0, 0, 0), Tile(2, 1, 0, 1, 0, 3)], {0: 100.0, 1: 1.0}, lambda m: costs, asked.append, 1)
    assert act.kind == "none" and not asked


def test_split_moves_the_part_that_evens_out():
    axis = AxisStats(np.array([10.0, 20.0]), np.array([1.0, 2.0]), np.array([5.0, 10.0]), np.zeros(2), np.zeros(2))
    flat = AxisStats(np.array([20.0]), np.array([2.0]), np.array([10.0]), np.zeros(1), np.zeros(1))
    new, act = rebalance_once([Tile(0, 0, 0, 0, 0, 1), Tile(1, 1, 1, 0, 1, 1)], {0: 400.0}, lambda m: {0: 400.0}, lambda t: {"row": axis, "col": flat}, 3)
    assert act.kind == "split" and act.cut.gap == 0 and covers(GridSpec(side=2), new)


def test_merging():
    four = [Tile(i, 0, x, y, x, y) for i, (x, y) in enumerate([(0, 0), (1, 0), (0, 1), (1, 1)])]
    assert len(merge_tiles(four)) == 1
    shape = [Tile(0, 0, 0, 0, 1, 0), Tile(1, 0, 0, 1, 0, 1), Tile(2, 1, 1, 1, 1, 1)]
    assert len(merge_tiles(shape)) == 3


def test_lineage_of_a_split_and_its_expiry():
    first = [Tile(1, 1, 0, 0, 1, 1)]
    split = split_tile(first, 1, "col", 0, "second", 2, 5)
    history = tile_history([first] * 5 + [split] * 5)
    moved = next(t for t in split if t.machine_id == 2)
    assert [(t.tile_id, t.machine_id) for t, _ in resolve_chain(history, moved.tile_id, 0)] == [(moved.tile_id, 2), (1, 1)]
    assert [t.tile_id for t, _ in resolve_chain(history, moved.tile_id, 5)] == [moved.tile_id]
    assert all(not t.parent_ids for t in prune(history, 5))


def test_moves_keep_the_cover_and_use_new_ids():
    rng = random.Random(3)
    tiles = random_layout(rng, 8, 10)
    moved = move_tiles(tiles, {tiles[0].tile_id, tiles[3].tile_id}, 9, 4)
    assert covers(GridSpec(side=8), moved) and sum(t.machine_id == 9 for t in moved) == 2
    assert not {t.tile_id for t in moved if t.machine_id == 9} & {t.tile_id for t in tiles}
