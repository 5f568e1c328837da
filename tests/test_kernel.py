"""Worked examples and invariants of the facility pass and the phased miner."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from phasewise.baselines.means import reduce_to_k
from phasewise.operators import engine
from phasewise.operators.engine import Miner, NoProgress, Settings
from phasewise.operators.kernel import StopLimits, facility_pass
from phasewise.plans.schedule import check_constants, plan_phase


def run_pass(values, price, weights=None, u=0.5, **more):
    x = np.array(values, float).reshape(-1, 1)
    w = np.ones(len(x)) if weights is None else np.array(weights, float)
    return facility_pass(x, w, np.full(len(x), u), price, **more)


LINE = [0, 1, 10, 11, 3, 50, 0, 10]


def test_one_pass():
    p = run_pass(LINE, 4.0)
    assert p.rows.tolist() == [0, 2, 4, 5] and p.weight.tolist() == [3, 3, 1, 1]
    assert (p.facility, p.service, p.total, p.ssq, p.max_dist) == (16, 2, 18, 2, 1)
    assert [i for i, g in zip(p.rows, p.gained) if not g] == [4, 5]


@pytest.mark.parametrize("limits, reason", [(StopLimits(cost_cap=10), "cost"), (StopLimits(median_cap=2), "medians")])
def test_breach_leaves_the_last_point_unread(limits, reason):
    p = run_pass(LINE, 4.0, limits=limits)
    assert (p.read, p.weight.tolist(), p.stop_reason) == (4, [2, 2], reason)


def staged(monkeypatch, prices, **more):
    plan = engine.plan_phase
    monkeypatch.setattr(engine, "plan_phase", lambda phase, floor, **k: engine.replace(plan(phase, floor, **k), price=prices[phase - 1], runs=1))
    return Miner(Settings(**{"draws": "constant", "floor": 1.0, "cost_cap": 1e9, "median_cap": 1e9, "floor_growth": "none"} | more), 1)


def step(m, first_id, values):
    x = np.array(values, float).reshape(-1, 1)
    return m.step(np.arange(first_id, first_id + len(x)), x, np.ones(len(x)), 100)


def test_second_phase_absorbs_retires_and_conserves(monkeypatch):
    m = staged(monkeypatch, [4.0, 8.0])
    step(m, 0, LINE)
    step(m, 8, [1, 60, 10, 12])
    verdicts = {v["median_id"]: v["verdict"] for v in m.log.verdicts}
    assert verdicts == {4: "absorbed", 5: "outlier"}
    assert m.ids.tolist() == [0, 2, 9] and m.w.tolist() == [5, 5, 1]
    assert {i: (c.age, c.score) for i, c in m.candidates.items()} == {9: (1, 1)}
    last = m.log.phases[-1]
    assert (last["service_cost"], last["facility_cost"], last["total_cost"]) == (6, 32, 38)
    assert m.w.sum() + 1 == 12


def test_windows_turn_a_candidate_into_an_inlier(monkeypatch):
    m = staged(monkeypatch, [8.0, 8.0])
    step(m, 0, [0, 40, 60, 80])
    m.w[0], m.candidates = 9.0, {i: engine.Candidate(i, 1, 1, 1, 1.0) for i in (1, 2, 3)}
    step(m, 10, [38, 39, 41, 42, 1])
    assert {v["median_id"]: v["verdict"] for v in m.log.verdicts} == {1: "inlier", 2: "outlier", 3: "outlier"}
    assert m.log.phases[-1]["total_cost"] == 39 and m.w.tolist() == [10, 5]


@pytest.mark.parametrize("rule, more", [("stalled", {0}), ("stalled_light", set())])
def test_light_rule_spares_heavy_medians(monkeypatch, rule, more):
    m = staged(monkeypatch, [8.0, 8.0], candidate_rule=rule)
    step(m, 0, [0, 40, 60, 80])
    m.w[0], m.candidates = 9.0, {}
    step(m, 10, [38, 39, 41, 42])
    assert set(m.candidates) & {0} == more


def test_constants():
    with pytest.warns(UserWarning):
        assert check_constants(34, 34) == (30, -70)
    assert check_constants(22, 68) == (30, 0)
    with pytest.raises(ValueError):
        check_constants(34, 34, strict=True)


def test_schedule():
    p = plan_phase(1, 1.0, k=2, n=4177, gamma=34, beta=34)
    assert round(p.median_cap) == 20393 and p.runs == 17 and round(p.price, 5) == 0.05355
    assert p.median_cap * p.price == pytest.approx(p.cost_cap)
    assert [plan_phase(1, 1, k=2, n=4177, gamma=34, beta=34, log_base=b).runs for b in ("2", "10")] == [25, 8]


numbers = st.lists(st.integers(0, 1000), min_size=1, max_size=120)


@settings(max_examples=60, deadline=None)
@given(numbers, st.floats(0.5, 200), st.integers(0, 3))
def test_pass_invariants(values, price, seed):
    x = np.array(values, float).reshape(-1, 1)
    u = np.random.default_rng(seed).random(len(x))
    p = facility_pass(x, np.ones(len(x)), u, price)
    assert p.rows[0] == 0 and p.weight.sum() == len(x)
    assert (p.dist <= price).all()  # a step never costs more than the price
    assert p.total == pytest.approx(p.service + price * len(p.rows))
    nearest = np.abs(x - x[p.rows].T).min(1).sum()
    assert nearest <= p.service + 1e-9


@settings(max_examples=30, deadline=None)
@given(numbers, st.integers(1, 3), st.integers(5, 40))
def test_miner_conserves_weight_and_settles_in_age(values, phases, num):
    x = np.array(values, float).reshape(-1, 1)
    m = Miner(Settings(k=2, outlier_phases=phases, num=num, runs=2, floor_growth="on_breach"), 1)
    log = m.run(np.arange(len(x)), x, np.ones(len(x)))
    out = [v for v in log.verdicts if v["verdict"] == "outlier"]
    assert m.w.sum() + sum(v["weight"] for v in out) == pytest.approx(len(x))
    assert all(v["score"] <= v["age"] <= phases for v in log.verdicts)
    assert not {v["median_id"] for v in out} & set(m.ids.tolist())
    assert all(p["points_read"] + p["unread"] == p["points_in"] for p in log.phases)


def test_literal_growth_of_the_floor():
    x = np.arange(50, dtype=float).reshape(-1, 1)
    log = Miner(Settings(num=10, runs=1), 1).run(np.arange(50), x, np.ones(50))
    floors = [p["floor"] for p in log.phases]
    assert all(b == pytest.approx(34 * a) for a, b in zip(floors, floors[1:]))


def test_limits_split_a_chunk_and_progress_is_guarded():
    x = np.arange(40, dtype=float).reshape(-1, 1) * 100
    log = Miner(Settings(num=40, runs=1, median_cap=15, floor_growth="on_breach"), 1).run(np.arange(40), x, np.ones(40))
    assert log.phases[0]["points_read"] == 15 and log.phases[0]["stop_reason"] == "medians"
    with pytest.raises(NoProgress):
        Miner(Settings(num=40, runs=1, median_cap=0.5, floor_growth="none"), 1).run(np.arange(40), x, np.ones(40))


@pytest.mark.parametrize("values", [[], [5.0], [5.0] * 20, [1.0, 2.0]])
def test_small_streams(values):
    x = np.array(values).reshape(-1, 1)
    m = Miner(Settings(num=7, runs=1), 1)
    m.run(np.arange(len(x)), x, np.ones(len(x)))
    assert m.seen == len(x)


def test_duplicate_start_can_be_an_error():
    with pytest.raises(ValueError, match="zero floor"):
        Miner(Settings(zero_floor="error", runs=1), 1).run(np.arange(4), np.array([[5.0], [5.0], [7.0], [9.0]]), np.ones(4))
    m = Miner(Settings(runs=1, beta=1.0), 1)
    m.set_floor(np.array([[5.0], [5.0], [7.0], [9.0]]))
    assert m.floor == 2


def test_reduction_to_k():
    x, w = np.array([[0.0], [1], [2], [3], [10]]), np.ones(5)
    assert reduce_to_k(x, w, 1, "exhaustive")[1] == 12
    assert reduce_to_k(x, w, 2, "exhaustive")[1] == reduce_to_k(x, w, 2, "local_swap")[1] == 4
    assert reduce_to_k(x, w, 2)[1] >= 4


def test_choices_are_checked():
    with pytest.raises(ValueError, match="winner"):
        Settings(winner="any")
