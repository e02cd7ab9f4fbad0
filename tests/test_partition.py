"""Curves, regions, scores and the choice of their number."""

import itertools

import numpy as np
import pytest
from mjoin.functions import hilbert_expr, zorder_expr
from mjoin.partition.assign import MOST_CELLS, assign_regions, balanced_bits, copies_by_relation, duplication_factor, is_balanced, min_score_bruteforce, partition_score
from mjoin.partition.curves import cells, hilbert_coords, hilbert_index, rowmajor_index, zorder_index
from mjoin.partition.reducers import best_curve, best_fitted, best_linear, choose_reducers, delta, delta_curve, fit_best
from pyspark.sql import functions as F


@pytest.mark.parametrize(("m", "bits"), [(1, 4), (2, 1), (2, 4), (3, 3), (4, 2), (5, 1)])
def test_curve_visits_neighbours(m, bits):
    grid = cells((bits,) * m)
    at = hilbert_index(grid, bits)
    assert sorted(at.tolist()) == list(range(len(grid)))
    path = grid[np.argsort(at)]
    assert (np.abs(np.diff(path, axis=0)).sum(1) == 1).all()
    assert (hilbert_coords(at, m, bits) == grid).all()
    assert sorted(zorder_index(grid, bits).tolist()) == sorted(rowmajor_index(grid, bits).tolist()) == list(range(len(grid)))


@pytest.mark.parametrize(("m", "bits"), [(2, 1), (2, 4), (3, 2), (4, 2)])
def test_sql_positions_equal_numpy(spark, m, bits):
    grid = cells((bits,) * m)
    df = spark.createDataFrame(grid.tolist(), [f"c{d}" for d in range(m)])
    cols = [F.col(f"c{d}") for d in range(m)]
    rows = df.select(*cols, hilbert_expr(cols, bits).alias("h"), zorder_expr(cols, bits).alias("z")).collect()
    coords = np.array([r[:m] for r in rows])
    assert [r["h"] for r in rows] == hilbert_index(coords, bits).tolist()
    assert [r["z"] for r in rows] == zorder_index(coords, bits).tolist()


#: Scores of two relations of 1,600 rows on 16 by 16 cells, by number of regions.
SCORES = {"hilbert": (6400, 8400, 10000, 11800, 12800), "zorder": (6400, 9600, 11800, 13400, 12800), "rowmajor": (8000, 10000, 13400, 16800, 27200), "grid": (6400, 9600, 12800, 9600, 12800)}


@pytest.mark.parametrize("curve", SCORES)
def test_scores_of_two_relations(curve):
    assert tuple(partition_score(assign_regions(2, k, curve, 4), [1600] * 2) for k in (4, 5, 7, 9, 16)) == SCORES[curve]


def test_regions_are_disjoint_and_even():
    for m, k, curve in itertools.product((2, 3), (1, 3, 7, 8), ("hilbert", "zorder", "rowmajor", "random")):
        a = assign_regions(m, k, curve, 3)
        shares = a.shares()
        assert shares.sum() == 8**m and shares.max() - shares.min() <= 1
        assert duplication_factor(a, 0) >= 1
    with pytest.raises(ValueError):
        assign_regions(2, 65, "hilbert", 3)
    with pytest.raises(ValueError):
        assign_regions(3, 2, "hilbert", 7)
    assert MOST_CELLS == 1 << 20


def test_unequal_relations_need_other_shapes():
    cards = [160, 16_000]
    curve, auto = (partition_score(assign_regions(2, 16, c, 4, cards), cards) for c in ("hilbert", "auto"))
    assert curve == 64_640 and auto <= 18_560
    assert balanced_bits([1, 64], 6) == (0, 6)
    assert is_balanced(assign_regions(2, 16, "hilbert", 4), [10, 10]) and not is_balanced(assign_regions(2, 16, "hilbert", 4), [10, 99])


def test_volume_grows_with_regions():
    for m in (2, 3, 4):
        scores = [partition_score(assign_regions(m, k, "hilbert", 3), [100] * m) for k in (1, 2, 4, 8, 16, 32, 64)]
        assert scores == sorted(scores)


@pytest.mark.parametrize(("m", "side", "k"), [(2, 2, 2), (2, 2, 4), (2, 3, 3), (3, 2, 2), (3, 2, 4)])
def test_curve_against_the_least_score(m, side, k):
    least = min_score_bruteforce(m, side, k)
    if side == 2:
        assert partition_score(assign_regions(m, k, "hilbert", 1), [side] * m) == least
    else:
        assert least <= side * m * k


def test_number_of_regions():
    cards = [1000.0] * 3
    k = best_curve(cards)
    assert k == pytest.approx(3349.9379, abs=1e-3) and delta_curve(k, cards) == pytest.approx(447_769.4927, abs=1e-3)
    assert all(delta_curve(k, cards) <= delta_curve(k * f, cards) for f in (0.5, 0.9, 1.1, 2))
    assert best_linear([100.0, 100.0], 0.4, 100.0) == 13  # ceil(sqrt(0.6 * 10^4 / 40))
    assert choose_reducers(cards, 96, mode="curve") == choose_reducers(cards, 96, mode="linear") == 96
    assert 1 <= choose_reducers([3.0, 3.0], 8) <= 8 and choose_reducers([5.0], 8) == 1
    scan = choose_reducers([40.0, 40.0], 16)
    assert delta(scan, [40.0, 40.0]) == min(delta(k, [40.0, 40.0]) for k in range(1, 17))
    fit = fit_best([1e9, 1e10, 1e11], [2, 8, 32])
    assert best_fitted(1e10, fit) == 8 and choose_reducers([9.0, 9.0], 64, mode="fitted", bytes_out=1e11, fit=fit) == 32
