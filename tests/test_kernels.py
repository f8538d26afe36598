"""Hand-checkable instances, invariants and exact baselines of the numpy kernels."""

from dataclasses import replace

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from hazemedian import kernels as K
from hazemedian.model import PRACTICAL, REFERENCE
from hazemedian.plans.summarise import composed_error, ladder_levels, level_epsilon


def block(nodes, weights=None):
    """nodes: list of [(point, prob), ...]"""
    x = np.array([p for n in nodes for p, _ in n], float)
    prob = np.array([q for n in nodes for _, q in n], float)
    offsets = np.r_[0, np.cumsum([len(n) for n in nodes])]
    w = np.ones(len(nodes)) if weights is None else np.array(weights, float)
    return K.Block(np.arange(len(nodes)), w, np.add.reduceat(prob, offsets[:-1]), offsets, np.arange(len(x)), x, prob)


def random_block(n=600, z=10, d=3, seed=0, groups=3):
    rng = np.random.default_rng(seed)
    middle = rng.normal(0, 20, (groups, d))[rng.integers(0, groups, n)]
    x = (middle + rng.normal(0, 1, (n, d)))[:, None, :] + rng.normal(0, 0.5, (n, z, d))
    return K.Block(np.arange(n), np.ones(n), np.ones(n), np.arange(n + 1) * z, np.arange(n * z), x.reshape(-1, d), np.full(n * z, 1 / z))


def test_cost_of_one_node():
    b = block([[((0, 0), 0.5), ((2, 0), 0.5)]], [3])
    assert K.assigned_cost(b, np.array([[1.0, 0]])) == pytest.approx(3)
    assert K.assigned_cost(b, np.array([[0.0, 0]])) == pytest.approx(3)


def test_absent_mass_costs_nothing_and_spread_is_by_mass():
    b = block([[((0, 0), 0.25), ((2, 0), 0.25)]], [3])
    assert K.assigned_cost(b, np.array([[1.0, 0]])) == pytest.approx(1.5)
    assert K.spreads(b, np.array([[1.0, 0]]))[0] == pytest.approx(1)


def test_nodes_are_assigned_whole():
    b = block([[((0, 0), 0.5), ((10, 0), 0.5)]])
    c = np.array([[0.0, 0], [10, 0]])
    assert K.assigned_cost(b, c) == pytest.approx(5)
    assert (b.pair_weight * K.distances(b.coords, c).min(1)).sum() == 0


def test_iteration_approaches_weighted_median():
    x, w = np.array([[0.0], [1], [5]]), np.array([1.0, 1, 3])
    y, _, _ = K.iterative_medians(x, w, np.array([0, 3]), "step_tolerance", max_steps=500, tolerance=1e-12)
    assert y[0, 0] == pytest.approx(5, abs=1e-3)
    assert K.support_median(x, w) == 2


def test_step_ratio_rule_makes_two_updates_at_least():
    b = random_block(50)
    _, steps, status = K.iterative_medians(b.coords, b.prob, b.offsets)
    assert steps.min() >= 2 and steps.max() <= 15 and set(status) <= {1, 2, 3}


def test_single_location_and_coincidence():
    b = block([[((4, 4), 1.0)], [((0, 0), 0.4), ((1, 0), 0.2), ((2, 0), 0.4)]])
    y, _, status = K.iterative_medians(b.coords, b.prob, b.offsets)
    assert status[0] == 0 and (y[0] == [4, 4]).all()
    assert status[1] == 4  # the centre of gravity is a location
    y, _, _, status = K.node_medians(b, PRACTICAL, 1)
    assert status[1] == 4 and y[1, 0] in (0, 1, 2)


def test_ring_and_spread_edges():
    assert K.classes(np.array([0.999, 1, 2, 3.999, 4]), 1.0, True).tolist() == [0, 1, 2, 2, 3]
    assert K.classes(np.array([1, 1.0001, 2, 2.0001]), 1.0, False).tolist() == [0, 1, 1, 2]
    assert K.classes(np.array([0.0, 3]), 0.0, True).tolist() == [0, 0]


def test_draw_counts():
    assert K.draws_per_cell(np.array([5, 5, 5]), 1, 200, "even").tolist() == [66] * 3
    assert K.draws_per_cell(np.ones(300, int), 1, 200, "even").tolist() == [1] * 300
    assert K.draws_per_cell(np.array([10, 50]), 1, 200, "as_printed").tolist() == [20, 4]


def test_two_far_identical_groups_have_error_zero():
    nodes = [[((0, 0), 0.5), ((1, 0), 0.5)]] * 10 + [[((100, 0), 0.5), ((101, 0), 0.5)]] * 10
    b = block(nodes)
    p = replace(PRACTICAL, per_k=3)
    u = K.reduce_block(b, 2, p, 5)
    for c in (np.array([[0.5, 0], [100.5, 0]]), np.array([[7.0, 3], [50, 1]])):
        assert K.assigned_cost(u, c) == pytest.approx(K.assigned_cost(b, c))


def test_draws_are_unbiased_and_keep_weight():
    b = K.with_medians(random_block(300), PRACTICAL, 1)
    centres = K.kmedian_lloyd(b.median, b.weight, 3, 1, PRACTICAL)
    of, _ = K.cells(b, centres, PRACTICAL)
    fixed = np.array([[0.0, 0, 0], [10, 10, 10], [-20, 5, 3]])
    full = K.assigned_cost(b, fixed)
    for mass in ("weight", "expected_weight", "uniform"):
        p = replace(PRACTICAL, per_k=10, draw_mass=mass)
        costs = []
        for seed in range(120):
            u = K.draw(b, of, 3, p, seed)
            costs.append(K.assigned_cost(u, fixed))
            assert u.weight.sum() == pytest.approx(b.weight.sum())
        assert abs(np.mean(costs) - full) <= 4 * np.std(costs) / np.sqrt(len(costs)) + 1e-9


def test_exhausted_cells_have_error_zero():
    b = K.with_medians(random_block(40), PRACTICAL, 1)
    of = np.zeros((40, 3), int)
    u = K.draw(b, of, 1, replace(PRACTICAL, per_k=100, exhaust_small=True), 1)
    c = np.array([[1.0, 2, 3]])
    assert K.assigned_cost(u, c) == pytest.approx(K.assigned_cost(b, c))


@settings(max_examples=25, deadline=None)
@given(st.integers(0, 700), st.integers(1, 9))
def test_ladder_occupancy_is_a_binary_counter(n, step):
    capacity = 32
    ladder = K.Ladder(2, replace(PRACTICAL, per_k=4, capacity=capacity), 1)
    b = random_block(max(n, 1), 3, 2)
    for at in range(0, n, step * 10):
        ladder.add(b.take(np.arange(at, min(at + step * 10, n))))
    full = n // capacity
    assert ladder.occupancy()[0] == n % capacity
    assert sum(x << j for j, x in enumerate(ladder.occupancy()[1:])) == full
    assert ladder.reductions == full - bin(full).count("1")
    out = ladder.finish()
    assert (out is None) == (n == 0)
    if n:
        assert out.weight.sum() == pytest.approx(n)


def test_ladder_trace_of_capacity_two():
    ladder = K.Ladder(1, replace(PRACTICAL, per_k=1, capacity=2), 1)
    b = random_block(8, 2, 2)
    seen = []
    for k in range(8):
        ladder.add(b.take(np.array([k])))
        if k % 2:
            seen.append([j + 1 for j, x in enumerate(ladder.levels) if x is not None])
    assert seen == [[1], [2], [1, 2], [3]]


def test_ladder_does_not_depend_on_batches_and_repeats_itself():
    b = random_block(500)
    p = replace(PRACTICAL, per_k=10, capacity=64)
    outs = []
    for cut in (500, 37):
        ladder = K.Ladder(3, p, 9)
        for at in range(0, 500, cut):
            ladder.add(b.take(np.arange(at, min(at + cut, 500))))
        outs.append(ladder.finish())
    assert (outs[0].node_id == outs[1].node_id).all() and np.allclose(outs[0].weight, outs[1].weight)


def test_levels_and_errors():
    assert ladder_levels(8 * 5 + 3, 8) == [(0, 3), (1, 8), (3, 32)]
    assert composed_error([0.1, 0.1]) == pytest.approx(0.21)
    assert (1 + level_epsilon(0.5, 4)) ** 4 == pytest.approx(1.5)


@pytest.mark.parametrize("profile", [PRACTICAL, REFERENCE])
def test_summary_gap_and_quality(profile):
    b = random_block(1500, 6)
    p = replace(profile, per_k=30, capacity=400)
    ladder = K.Ladder(3, p, 2)
    ladder.add(b)
    u = ladder.finish()
    assert len(u) < 600
    centres, cost, _ = K.solve_assigned(u, 3, 1, p, restarts=3)
    full = K.assigned_cost(b, centres)
    assert abs(cost - full) / full < 0.1
    assert full <= 1.1 * K.solve_assigned(b, 3, 1, p, restarts=3)[1]


def test_guarded_rounds_never_cost_more():
    b = random_block(200, 5)
    costs = [K.solve_assigned(b, 4, 3, PRACTICAL, max_rounds=r)[1] for r in range(1, 8)]
    assert all(x >= y - 1e-9 for x, y in zip(costs, costs[1:], strict=False))


def test_solver_reaches_the_tiny_optimum():
    b = random_block(7, 4, 2, 3, 2)
    _, best = K.exact_small(b, 2)
    assert best <= K.solve_assigned(b, 2, 1, PRACTICAL, 5)[1] + 1e-9
    assert K.solve_assigned(b, 2, 1, replace(PRACTICAL, stop="step_tolerance", max_steps=200), 20)[1] <= 1.05 * best


def test_sampled_median_is_near_the_best():
    rng, good = np.random.default_rng(5), 0
    for trial in range(60):
        x = rng.normal(0, 1, (200, 2))
        y = K.sampled_median(x, np.ones(200), np.random.default_rng(trial))
        best = K.distances(x, x).sum(1).min()
        good += np.sqrt(((x - y) ** 2).sum(1)).sum() <= 3 * best
    assert good >= 54


def test_support_compression_keeps_mass():
    b = K.with_medians(random_block(4, 500, 2), PRACTICAL, 1)
    u = K.compress_support(b, replace(PRACTICAL, eps=1.0), 1)
    assert len(u.coords) < len(b.coords)
    assert np.allclose(np.add.reduceat(u.prob, u.offsets[:-1]), b.mass)


def test_fewer_locations_than_centres():
    b = block([[((0, 0), 1.0)], [((0, 0), 1.0)], [((1, 1), 1.0)]])
    centres, cost, _ = K.solve_assigned(b, 5, 1, PRACTICAL)
    assert len(centres) == 2 and cost == 0


def test_cost_scales_moves_and_adds_up():
    b = random_block(50, 4, 2)
    c = np.array([[1.0, 2], [3, 4]])
    moved = replace_coords(b, b.coords * 2 + 7)
    assert K.assigned_cost(moved, c * 2 + 7) == pytest.approx(2 * K.assigned_cost(b, c))
    halves = [b.take(np.arange(25)), b.take(np.arange(25, 50))]
    assert sum(K.assigned_cost(h, c) for h in halves) == pytest.approx(K.assigned_cost(b, c))
    heavy = replace_coords(b, b.coords)
    heavy.weight = b.weight * 2
    assert K.assigned_cost(heavy, c) == pytest.approx(K.assigned_cost(K.Block.join([b, b]), c))


def replace_coords(b, coords):
    return K.Block(b.node_id, b.weight, b.mass, b.offsets, b.loc_id, coords, b.prob)


def test_closed_forms():
    b = block([[((0, 0), 0.3), ((1, 0), 0.2)], [((0, 0), 0.25), ((2, 0), 0.25)], [((0, 0), 0.1), ((1, 0), 0.1), ((0, 1), 0.1)]])
    y, _, status = K.iterative_medians(b.coords, b.prob, b.offsets)
    assert y[0].tolist() == [0, 0] and y[1].tolist() == [1, 0] and status[:2].tolist() == [0, 0] and status[2] != 0
    line = np.array([[5.0], [1.0], [2.0], [9.0], [7.0]])
    y, _, status = K.iterative_medians(line, np.array([1.0, 1, 5, 1, 1]), np.array([0, 4, 5]))
    assert y.ravel().tolist() == [2, 7] and (status == 0).all()


def test_sampled_nodes_are_never_iterated(monkeypatch):
    """The cost of a sampled median doesn't grow with the support."""
    rng = np.random.default_rng(1)
    b = block([[(tuple(rng.normal(size=2)), 1 / 500) for _ in range(500)] for _ in range(3)])
    seen = []
    real = K.distances
    monkeypatch.setattr(K, "distances", lambda x, c: (seen.append(len(x) * len(c)), real(x, c))[1])
    monkeypatch.setattr(K, "iterative_medians", lambda *a: pytest.fail("iterated"))
    K.node_medians(b, replace(PRACTICAL, median="sampled"), 1)
    small = max(seen)
    for profile in (replace(PRACTICAL, dense_threshold=100), replace(PRACTICAL, median="sampled", candidates="lattice", repeats=0)):
        _, spread, _, status = K.node_medians(b, profile, 1)
        assert (status == 4).all() and (spread < 3).all()
    assert small < 500 * 500


def test_nodes_of_weight_zero():
    b = block([[((0, 0), 0.4), ((1, 0), 0.2), ((2, 0), 0.4)], [((0, 0), 0.5), ((5, 1), 0.5)]])
    b.weight[:] = 0
    for profile in (PRACTICAL, REFERENCE):
        y, spread, _, _ = K.node_medians(b, profile, 1)
        assert np.isfinite(y).all() and np.isfinite(spread).all()
