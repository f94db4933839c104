import math

import numpy as np
import pytest

from aclvec.functions.models import FilterGraphCost, GraphCost, IvfCost, RecallModel, ScanCost, ShardedGraphCost, fit_recall
from aclvec.functions.portable import draw_py, mix_py
from aclvec.operators.measures import logical_overhead, saving
from aclvec.operators.search import tune_depth


def test_recall_inverse_on_a_grid():
    m = RecallModel(3.0, 0.4)
    for s in (0.01, 0.1, 1.0):
        for target in (0.05, 0.39, 0.41, 0.6, 0.85):
            assert float(m.value(m.ef_for(target, s, 10), s, 10)) == pytest.approx(target)


def test_recall_is_continuous_and_within_bounds():
    m = RecallModel(9.0, 0.9)
    x = np.linspace(0, 5, 4000)
    v = m.value(x, 1.0, 1.0)
    assert v.min() >= 0 and v.max() <= 1 and np.abs(np.diff(v)).max() < 0.02
    assert float(m.value(0.9, 1, 1)) == pytest.approx(0.9)


def test_out_of_reach_raises():
    with pytest.raises(ValueError):
        RecallModel(4.0, 0.3).ef_for(0.9, 0.1, 10)


def test_published_savings_and_overheads():
    assert saving(1.4, 3.5) == pytest.approx(0.84)
    assert saving(1.24, 3.5) == pytest.approx(0.904)
    assert logical_overhead(1.0, 6.0, 128, 32) == pytest.approx(3.14, abs=0.01)


def test_costs():
    assert float(GraphCost(1, 20).value(1, 5)) == pytest.approx(math.log(2) * 25)
    assert float(ScanCost(64).value(10)) == 640
    assert float(IvfCost(10, 2).value(100)) == 30
    assert float(FilterGraphCost(64, 12).value(1000, 1.0)) == pytest.approx(76 * math.log(1000))
    s = ShardedGraphCost(1, 0, 100)
    assert float(s.value(1000, 1)) == pytest.approx(10 * math.log(100))


def test_fit_finds_planted_constants():
    ef = list(range(10, 1001, 20))
    rng = np.random.default_rng(1)
    y = RecallModel(2.5, 0.45).value(ef, 0.1, 10) + rng.normal(0, 0.003, len(ef))
    m, rmse = fit_recall(ef, [0.1] * len(ef), [10] * len(ef), y)
    assert abs(m.beta - 2.5) < 0.2 and abs(m.gamma - 0.45) < 0.03 and rmse < 0.01


def test_portable_hash_known_values():
    picked = [d for d in range(1000) if draw_py(d * 1009, 3, 1000) < 50]
    assert (len(picked), sum(picked)) == (48, 17996)
    assert 0 <= mix_py(2**31 - 1, 5) < 2**31


def test_tuning_reaches_the_target():
    asked = []

    def recall(ef):
        asked.append(ef)
        return min(1.0, ef / 200)

    ef, got = tune_depth(0.95, 150, recall)
    assert got >= 0.95 and ef <= 210 and len(asked) <= 8
