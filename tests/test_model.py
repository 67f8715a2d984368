"""The cost model: identities, and the values that the published constants give."""

import pytest
from hypothesis import given
from hypothesis import strategies as st

from blockdelta.functions import costmodel as m


@given(st.floats(0.001, 0.999), st.floats(0, 1))
def test_identities(rho, share):
    t_w, n = 2.0, 1000
    t_h = rho * t_w
    assert m.tau(share, t_w, t_h) * n == pytest.approx(m.overhead(n, share * n, t_h) - m.saving(n, share * n, t_w), abs=1e-6)
    assert m.speedup(1, rho) == pytest.approx(2 * rho)
    assert m.speedup(m.break_even(rho), rho) == pytest.approx(0, abs=1e-9)
    assert m.speedup(m.break_even(rho, keep_pending=True), rho, keep_pending=True) == pytest.approx(0, abs=1e-9)
    assert m.break_even(rho) > m.break_even(min(1 - 1e-9, rho * 1.01))
    assert m.break_even(rho) + m.break_even(rho, kind="clean") == pytest.approx(1)
    assert m.worst_case(t_w, t_h) == pytest.approx(2 * rho)


@pytest.mark.parametrize("share,change", [(0.03, -0.940), (0.40, -0.559), (0.50, -0.457), (0.56, -0.395), (0.62, -0.333), (0.87, -0.076), (0.95, 0.007), (1, 0.058)])
def test_published_constants(share, change):
    rho = 3.92e-5 / 1.35e-3
    assert rho == pytest.approx(0.029, abs=1e-4)
    assert m.speedup(share, 0.029) == pytest.approx(change, abs=6e-4)


def test_break_even_and_memory():
    assert m.break_even(0.029) == pytest.approx(0.9436, abs=1e-4)
    assert m.break_even(1.0) is None and m.break_even(1.5) is None
    assert m.ledger_bytes(1568, 128, 16) == 196
    assert m.ledger_bytes(1568, 16384, 16) == pytest.approx(1.53, abs=0.01)
    assert m.ledger_bytes(1 << 30, 128, 16) == 128 << 20
    assert m.hash_count(0, 0, 7) == 7
    low, high = m.speedup_bounds(0.03, 0.8, 0.029)
    assert low < high


def test_scaling(spark):
    rows = spark.createDataFrame([(768, 1.0, 0.1), (2400, 2.0, 0.1)], "ranks int, t_write double, t_hash double")
    eta = {r["ranks"]: r["eta"] for r in m.scaling(rows).collect()}
    assert eta[2400] > eta[768]
