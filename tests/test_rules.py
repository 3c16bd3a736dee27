import numpy as np
import pytest

from graphsplit.functions import rules
from graphsplit.functions.hashing import mix


def test_adaptive_slack_worked_values():
    assert rules.eps_adaptive(0.03, 800, 8, 800, 8) == pytest.approx(0.009901634, abs=1e-9)
    assert rules.eps_adaptive(0.03, 800, 8, 404, 4) == pytest.approx(0.009852455, abs=1e-9)
    assert rules.eps_adaptive(0.03, 800, 8, 204, 2) == pytest.approx(0.009803922, abs=1e-9)
    assert rules.eps_adaptive(0.03, 1000, 5, 600, 3) == pytest.approx(0.014889157, abs=1e-9)


def test_adaptive_slack_composes_where_fixed_slack_compounds():
    for k in (8, 64):
        weight, f = 1000.0, k
        while f > 1:
            weight, f = (1 + rules.eps_adaptive(0.03, 1000, k, weight, f)) * weight / 2, f // 2
        assert weight <= 1.03 * 1000 / k + 1e-9
    assert 1.03 ** 3 - 1 == pytest.approx(0.0927, abs=1e-3)


def test_level_blocks():
    assert [rules.level_blocks(*a) for a in ((2000, 100, 8), (350, 50, 16), (20000, 200, 64), (2000, 100, 2), (16743, 200, 4096))] == [8, 8, 64, 2, 128]


def test_split_counts():
    assert rules.split_counts(5, 2) == [1, 1, 1, 2]
    assert rules.split_counts(11, 3) == [1, 1, 1, 2, 1, 2, 1, 2]
    assert rules.split_counts(7, 2) == [1, 2, 2, 2]
    assert (rules.split_counts(100, 6).count(2), rules.split_counts(100, 6).count(1)) == (36, 28) == rules.heavy_light(100)


def test_cluster_cap_makes_both_limits_one():
    total, k = 8000, 8
    cap = rules.cluster_cap(0.03, total, k, 200, 8000, 8000)
    assert rules.limit_relaxed(total, k, 0.03, cap) <= rules.limit_strict(total, k, 0.03) + 1e-9
    assert rules.cluster_cap(0.03, total, k, 200, 8000, 400) > cap


def test_relative_gain_prefers_heavy_nodes():
    assert (rules.relative_gain(2, 3), rules.relative_gain(-2, 4), rules.relative_gain(-2, 1)) == (6, -0.5, -2)


def test_hash_is_the_portable_one():
    assert int(mix(np.arange(100_000), 7).sum()) == 107_486_618_833_200
