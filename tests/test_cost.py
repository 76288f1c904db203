"""Cost formulas and choices, without Spark where none is needed."""

import math

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from blockmv.plans import cost


@given(st.integers(2, 10**6), st.integers(0, 10**6), st.integers(2, 500))
@settings(max_examples=200, deadline=None)
def test_rule_is_cost_comparison(n, m, b):
    shape = cost.GraphShape(n, min(m, n * n))
    h, v = cost.cost_horizontal(shape, b), cost.cost_vertical(shape, b)
    if not math.isclose(h, v, rel_tol=1e-9):
        assert cost.prefers_horizontal(shape, b) == (h < v)


@given(st.integers(1, 1000), st.integers(0, 5000), st.integers(1, 64))
@settings(max_examples=100, deadline=None)
def test_limits_of_the_hybrid_cost(n, m, b):
    shape = cost.GraphShape(n, min(m, n * n))
    degrees = [(3, 0.5), (0, 0.5)]
    assert cost.cost_hybrid(n, b, 0.0, degrees) == pytest.approx(cost.cost_horizontal(shape, b))
    aware = 2 * n + 2 * n * (b - 1) * sum((1 - (1 - 1 / b) ** d) * p for d, p in degrees)
    assert cost.cost_degree_aware(n, b, degrees) == pytest.approx(aware)


def test_one_block_is_a_tie_and_goes_vertical():
    shape = cost.GraphShape(10, 1)
    assert cost.cost_horizontal(shape, 1) == 20
    assert cost.prefers_horizontal(cost.GraphShape(6, 10), 3) is False
    assert cost.cost_vertical(cost.GraphShape(6, 10), 3) == pytest.approx(23.4815, abs=1e-4)


def test_block_count():
    assert cost.block_count(1000, 16, 1000) == 16
    assert cost.block_count(10**6, 16, 1000) == 1000
    assert cost.block_count(10**6, 16, 1000, expansion=2.0) == 2000


def test_published_graphs_fall_as_reported():
    """The four real graphs vertical, the synthetic one horizontal, at 64 blocks."""
    shapes = {
        "web12": (6_231_126_594, 71_746_553_402),
        "web09": (1_684_876_525, 7_939_647_897),
        "web": (720_242_173, 6_636_600_779),
        "social": (41_652_230, 1_468_365_182),
        "rmat26": (42_147_725, 5_000_000_000),
    }
    got = {k: cost.prefers_horizontal(cost.GraphShape(*x), 64) for k, x in shapes.items()}
    assert got == {"web12": False, "web09": False, "web": False, "social": False, "rmat26": True}


def test_speedup_and_memory():
    assert cost.speedup({16: 40.0, 64: 10.0}, 16) == {16: 1.0, 64: 4.0}
    shape = cost.GraphShape(1000, 5000)
    assert cost.memory_elements("vertical", shape, 10) == 200
    assert cost.memory_elements("hybrid", shape, 10, heavy=7) == 207
    assert cost.memory_elements("vertex_cut", shape, 10, largest=99) == 99
