import pytest

from turnwise.plans import costmodel as c


def test_printed_deductions():
    t = c.PRINTED[128]
    assert t.shared_miss - t.private_hit < 350  # less than a cycle in picoseconds
    assert c.break_even_c(0.0, t) == pytest.approx(0.8)
    assert c.break_even_c(0.0, c.PRINTED[16]) == pytest.approx(0.224)
    assert c.break_even_c(0.0, c.PRINTED[4]) == pytest.approx(0.224 / 3.3, rel=1e-3)
    assert c.cost_hybrid(0.2, t) == pytest.approx(708) and c.cost_hybrid(0.5, t) == pytest.approx(624)


def test_break_even_is_where_costs_meet():
    t = c.AccessTimes(2.0, 9.0, 1.0, 1.5)
    for x in (0.3, 0.6, 0.9):
        assert c.cost_shared(c.break_even_h(x, t), t) == pytest.approx(c.cost_hybrid(x, t))
        assert c.cost_hybrid(c.break_even_c(x, t), t) == pytest.approx(c.cost_shared(x, t))


def test_capacity():
    assert c.hot_capacity(576_000_000, 8, 0.5, 5, 128) == 878_048
    assert c.hot_capacity(576_000_000, 8, 0.5, 1, 128) > 3.6 * c.hot_capacity(576_000_000, 8, 0.5, 4, 128)
    assert c.hot_capacity(576_000_000, 8, 0.5, 5, 16) > 6_000_000 * 0.99
    with pytest.raises(ValueError):
        c.hot_capacity(1, 1, 0, 1, 1)
