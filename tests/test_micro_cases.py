"""Hand-computed cases: sixteen registers, three cell bits, ten-bit entries."""

import numpy as np
import pytest

from splitcount.functions import cost
from splitcount.operators import estimate as E
from splitcount.operators import split as S
from splitcount.operators.codec import Sketch, best_base_scan, merge

# name -> registers, (optimal base, sparse, bits), (smallest base, sparse, bits)
CASES = {
    "zeros": ([0] * 16, (0, 0, 48), (0, 0, 48)),
    "low": ([1] * 8 + [2] * 8, (1, 0, 48), (1, 0, 48)),
    "spread": ([0] + [5] * 7 + [9] * 7 + [12], (5, 1, 58), (0, 8, 128)),
    "edge": ([3] * 8 + [10] * 4 + [11] * 4, (3, 4, 88), (3, 4, 88)),
    "tie": ([1] * 4 + [9] * 4 + [17] * 4 + [25] * 4, (1, 12, 168), (1, 12, 168)),
    "stuck": ([0] * 5 + [1] + [9] * 10, (9, 6, 108), (0, 10, 148)),
    "few": ([0] * 12 + [1] * 4, (0, 0, 48), (0, 0, 48)),
}


def rows(spark, regs):
    return spark.createDataFrame([("g", j, r) for j, r in enumerate(regs) if r], "g string, j long, r long")


@pytest.mark.parametrize("name", CASES)
def test_memory_form(name):
    regs, best, low = CASES[name]
    s = Sketch.from_registers(np.array(regs))
    assert (s.base, s.sparse, s.bits) == best
    m = Sketch.from_registers(np.array(regs), base=min(regs))
    assert (m.base, m.sparse, m.bits) == low
    assert s.to_registers().tolist() == regs == m.to_registers().tolist()
    assert cost.split_bits(4, s.sparse) == s.bits


@pytest.mark.parametrize("name", [n for n in CASES if any(CASES[n][0])])
def test_relational_form(spark, name):
    regs, best, low = CASES[name]
    h = S.histogram(rows(spark, regs), ["g"], 4)
    for how in ("window", "theta", "maxby"):
        got = S.best_base(h, ["g"], 4, 3, how).first()
        assert (got["b"], got["sparse"], got["bits"]) == best
    got = S.base_at(h, S.min_base(h, ["g"]), ["g"], 4).first()
    assert (got["b"], got["sparse"], got["bits"]) == low


def test_lazy_step(spark):
    for name, base, moved in (("spread", 5, True), ("stuck", 0, False)):
        h = S.histogram(rows(spark, CASES[name][0]), ["g"], 4)
        got = S.lazy_step(h, S.min_base(h, ["g"]), ["g"], 4).first()
        assert (got["b"], got["moved"]) == (base, moved)


def test_window_edge():
    s = Sketch.from_registers(np.array(CASES["edge"][0]))
    assert s.cells[8] == 7 and s.get(8) == 10  # ten is the window's last value
    assert s.get(12) == 11 and s.sparse_part()[0].tolist() == [12, 13, 14, 15]


def test_merge_moves_base_below_both_starts():
    a, b = Sketch.from_registers(np.full(16, 2)), Sketch.from_registers(np.array([0] + [9] * 15))
    assert (a.base, b.base, b.sparse) == (2, 9, 1)
    got = merge([a, b])
    assert (got.base, got.sparse, got.bits) == (2, 0, 48)
    assert got.to_bytes() == merge([b, a]).to_bytes()


def test_estimates(spark):
    for name, est, v in (("zeros", 0.0, 16), ("low", 28.714667, 0), ("spread", 139.768597, 1), ("few", 4.602913, 12)):
        regs = CASES[name][0]
        assert Sketch.from_registers(np.array(regs)).estimate() == pytest.approx(est, abs=1e-6)
        if any(regs):
            got = E.from_registers(rows(spark, regs), ["g"], 4).first()
            assert got["est"] == pytest.approx(est, abs=1e-6) and got["v"] == v


def test_empty_global_sketch_counts_nothing(spark):
    none = spark.createDataFrame([], "j long, r long")
    assert [(r["r"], r["c"]) for r in S.histogram(none, [], 4).collect()] == [(0, 16)]
    assert E.from_registers(none, [], 4).first()["est"] == 0.0
    assert S.best_base(S.histogram(none, [], 4), [], 4).first()["bits"] == 48


def test_early_stop_visits_fewer_candidates():
    assert best_base_scan({0: 5, 1: 1, 9: 10}, 3).base == 9
    assert best_base_scan({0: 16}, 3).visited == 1
    assert best_base_scan({2: 15, 40: 1}, 3) .visited == 1  # one sparse register; fifteen lie under forty
