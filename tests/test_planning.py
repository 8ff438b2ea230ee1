"""Properties of bandit rules, spaces, proposers, budgets, cost measures and the SQL scanner."""

from __future__ import annotations

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from foretell.catalogue import published
from foretell.functions import cost, draws
from foretell.operators import shared_scan as ss
from foretell.operators.random_features import Projection
from foretell.plans import evaluate
from foretell.plans.bandit import Eliminator, FixedArms, SuccessiveHalving, Trial
from foretell.plans.budget import Budget, Ledger
from foretell.plans.search import Observation, make
from foretell.plans.search.grid import grid
from foretell.plans.session import ClauseError
from foretell.plans.space import Choice, Family, ModelSpace, Real, kernel_svm, linear_pair, random_feature_logistic
from foretell.plans.sqlfront import find_clauses


def test_published_speedups_are_truncated_ratios():
    one = {d: r for k, d, r in published.THROUGHPUT if k == 1}
    got = {(k, d): cost.speedup(r, one[d]) for k, d, r in published.THROUGHPUT}
    assert got[20, 100] == 14.37 and got[20, 1000] == 13.75 and got[15, 10000] == 4.48 and got[2, 1000] == 2.02


def test_cost_constants():
    assert round(cost.balance(110, 60), 1) == 14.7 and round(6.8 / 0.45, 1) == 15.1
    assert cost.data_bytes(1_200_000, 160_000) == 1.536e12
    assert cost.overhead_ms(200, 10) == 20 and cost.round_trips(7) == 14
    m = cost.Machine()
    assert cost.roofline(1, 1, m) == 30 and cost.roofline(20, 1, m) == 110
    assert round(cost.balance_batch(m, 1), 1) == 3.7 and round(cost.balance_batch(m, 2), 1) == 7.3
    assert cost.choose_regime(1e3, 10, 100, 100, 8, 4, m, 1e9) == "local"
    assert cost.choose_regime(1e10, 1e4, 100, 100, 8, 4, m, 1e9) == "distributed"
    assert cost.saved_share(1.0, 10, 100) == pytest.approx(0.9)


def test_elimination_table():
    rule = Eliminator(slack=0.5)
    trials = [Trial(1, 10, 0.61), Trial(2, 10, 0.60), Trial(3, 10, float("nan")), Trial(4, 100, 0.2, True)]
    v = rule.sort(trials, [])
    assert [t.model_id for t in v.active] == [1, 2] and [t.model_id for t in v.dropped] == [3]
    v = rule.sort(trials, [0.9])  # strict: 0.6 * 1.5 is not above 0.9
    assert [t.model_id for t in v.active] == [1] and [t.model_id for t in v.finished] == [4]
    v = Eliminator(rule="error").sort([Trial(1, 10, 0.875), Trial(2, 10, 0.84)], [0.9])
    assert [t.model_id for t in v.active] == [1]
    once = Eliminator(slack=0.0, check="once")
    once.sort([Trial(1, 10, 0.5)], [])
    assert once.sort([Trial(1, 20, 0.1)], [0.9]).active
    assert not Eliminator(slack=0.0, include_current=True).sort([Trial(1, 10, 0.5)], []).active
    assert len(SuccessiveHalving().sort([Trial(i, 10, i / 10) for i in range(8)], []).active) == 4


def test_fixed_arms_prefer_the_better_arm():
    arms, pay = FixedArms(3), [0.2, 0.8, 0.5]
    for _ in range(300):
        k = arms.choose()
        arms.reward(k, pay[k])
    assert arms.pulls[1] > 150


@settings(max_examples=30, deadline=None)
@given(st.lists(st.floats(0.01, 0.99), min_size=1, max_size=12), st.floats(0.01, 0.99))
def test_elimination_ignores_order(qualities, best):
    trials = [Trial(i, 10, q) for i, q in enumerate(qualities)]
    a = {t.model_id for t in Eliminator().sort(trials, [best]).active}
    b = {t.model_id for t in Eliminator().sort(trials[::-1], [best]).active}
    assert a == b == {i for i, q in enumerate(qualities) if q * 1.5 > best}


def test_grid_sizes_and_ends():
    assert len(grid(linear_pair(), 128)) == 128
    for n in (2, 3, 4, 5):
        assert len(grid(random_feature_logistic(3), n**4)) == n**4
    rates = {c["rate"] for c in grid(linear_pair(), 128)}
    assert min(rates) == pytest.approx(1e-3) and max(rates) == pytest.approx(10)


def test_encoding_round_trips_and_conditional_parameters():
    for space in (linear_pair(), kernel_svm(), random_feature_logistic(4)):
        for i in range(20):
            c = space.draw(3, i)
            assert c.family in [f.name for f in space.families]
            back = space.decode(space.encode(c))
            for k, v in c.params:
                assert back[k] == pytest.approx(v)
            assert set(dict(c.params)) == set(space.family(c.family).parameters)


def _bowl(c) -> float:
    return min(1.0, 0.05 + 0.03 * (math.log10(c["rate"]) + 1) ** 2 + 0.02 * (math.log10(c["l2"]) + 2) ** 2)


@pytest.mark.parametrize("name", ["grid", "random", "directions", "simplex", "parzen", "forest", "gaussian_process"])
def test_proposers(name):
    def run():
        p, seen = make(name, linear_pair(), 48, 5), []
        while len(seen) < 48:
            fresh = p.propose(4, seen)
            assert len(fresh) <= 4
            if not fresh:
                break
            for c in fresh:
                assert 1e-3 * 0.999 <= c["rate"] <= 10.001 and 1e-4 * 0.999 <= c["l2"] <= 100.1
            seen += [Observation(c, _bowl(c)) for c in fresh]
        return seen

    first = run()
    assert [o.config for o in first] == [o.config for o in run()]
    assert min(o.error for o in first) < 0.2


def test_local_methods_refuse_categories():
    space = ModelSpace((Family("f", {"kind": Choice(("a", "b")), "x": Real(0, 1)}),))
    for name in ("directions", "simplex"):
        with pytest.raises(ValueError):
            make(name, space, 8)
    assert make("parzen", space, 8).propose(3, [])


def test_budget_first_limit_stops():
    b, ledger = Budget(models=3, scans=5), Ledger()
    assert not b.exhausted(ledger)
    ledger.charge(10, 5)
    assert b.exhausted(ledger) and b.room(ledger, 5) == 3
    assert Budget(target_error=0.1).exhausted(Ledger(), 0.05)


def test_measures():
    assert evaluate.retained_gain(0.5, 0.11, 0.1) == pytest.approx(0.975)
    assert evaluate.scans_saved(20, 100) == 0.8
    assert evaluate.false_discovery([0.001, 0.012, 0.013, 0.2, 0.031, 0.6]) == [True, True, True, False, True, False]
    assert evaluate.p_value(0.1, 0.5, 100) < 1e-6 < evaluate.p_value(0.49, 0.5, 100)


def test_matrix_form_equals_row_form_and_finite_differences():
    rng = np.random.default_rng(0)
    x, y = rng.standard_normal((60, 4)), (rng.random(60) > 0.5).astype(float)
    columns = [ss.Column(i, f, 0.1, 0.0, weights=rng.standard_normal((5, 1))) for i, f in enumerate(["logistic", "svm", "ridge"])]
    sums = {}
    for kernel in ("gemm", "rowloop"):
        t = ss.Task(columns, 1, kernel)
        t.add("train", x[:25], y[:25])
        t.add("train", x[25:], y[25:])
        sums[kernel] = t
    for a, b in zip(sums["gemm"].grads, sums["rowloop"].grads, strict=True):
        assert np.allclose(a, b, rtol=1e-9)
    for k in (0, 2):
        c, h = columns[k], 1e-6
        for i in range(5):
            up, down = c.weights.copy(), c.weights.copy()
            up[i, 0] += h
            down[i, 0] -= h
            z = ss.with_bias(x)
            slope = (ss.losses(c.family, z @ up, y) - ss.losses(c.family, z @ down, y)) / (2 * h)
            assert slope == pytest.approx(sums["gemm"].grads[k][i, 0], rel=1e-4, abs=1e-4)


def test_random_features_approach_their_kernels():
    rng = np.random.default_rng(1)
    x = rng.standard_normal((30, 3)) * 0.5
    gap = x[:, None, :] - x[None, :, :]
    exact = np.exp(-0.5 * (gap**2).sum(axis=2))
    errors = []
    for size in (64, 4096):
        z = Projection(3, size, 2).transform(x)
        errors.append(np.abs(z @ z.T - exact).max())
    assert errors[1] < errors[0] and errors[1] < 0.1
    z = Projection(3, 4096, 2, 1.0, "cauchy").transform(x)
    assert np.abs(z @ z.T - np.exp(-np.abs(gap).sum(axis=2))).max() < 0.12
    p = Projection(3, 10, 5)
    assert np.allclose(p.matrix(4, 3)[0], p.matrix()[0][:, 4:7])


def test_portable_draws_in_range():
    values = [draws.uniform_value("t", i) for i in range(2000)]
    assert 0 <= min(values) and max(values) < 1 and abs(np.mean(values) - 0.5) < 0.03


def test_clause_scanner():
    text, found = find_clauses("SELECT a, PREDICT(b, c, d) GIVEN t FROM r WHERE x = 'PREDICT(z) GIVEN q' -- PREDICT(y) GIVEN w\n AND PREDICT(b, c, d) = 'k' GIVEN t")
    assert len(found) == 1 and "PREDICT(z) GIVEN q" in text and text.count("_predicted_0") == 2
    assert next(iter(found.values())).predictors == ("c", "d")
    assert find_clauses("SELECT PREDICT(a) GIVEN (SELECT * FROM t) AS z FROM r")[0] == "SELECT _predicted_0 AS z FROM r"
    for bad in ("SELECT PREDICT(a, PREDICT(b) GIVEN t) GIVEN t FROM r", "SELECT PREDICT(a) FROM r", "SELECT PREDICT(a GIVEN t FROM r"):
        with pytest.raises(ClauseError):
            find_clauses(bad)
