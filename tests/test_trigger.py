"""The adaptive rule: anchors, ablations, any split of the stream."""

import math
import random

import pytest

from cellbalance.operators import measures
from cellbalance.plans import trigger as t


def test_drift_anchors():
    fired = t.drift_loop(t.Rule(20), 0.0002, 3000)[1]
    assert [f[0] for f in fired] == [305, 754, 1230, 1704, 2178, 2652]
    assert [f[1] for f in fired] == ["degrade"] + ["interval"] * 5
    assert fired[-1][2] == pytest.approx(473.686, abs=1e-3)
    assert [f[0] for f in t.drift_loop(t.Rule(50), 0.001, 2000)[1]] == [105, 426, 772, 1115, 1459, 1802]
    assert fired[-1][3] == pytest.approx(t.ideal_interval(20, 0.0002), rel=0.1)


def test_flat_run_never_fires():
    assert t.drift_loop(t.Rule(20), 0.0, 1000)[1] == []


def test_ablations_and_split():
    rng = random.Random(3)
    rows = [(s, 1 + s * 0.002 + rng.random()) for s in range(1, 900)]
    rule = t.Rule(30.0)
    whole = t.replay_states(rows, rule, t.StepState())[1]
    state, parts = t.StepState(), []
    for cut in range(0, len(rows), 37):
        state, found = t.replay_states(rows[cut : cut + 37], rule, state)
        parts += found
    assert parts == whole
    only_loss = t.replay_states(rows, t.Rule(30.0, use_interval=False), t.StepState())[1]
    assert {f[1] for f in only_loss} <= {"degrade", "loss"}
    assert all(b[0] - a[0] > rule.eval_len for a, b in zip(whole, whole[1:]))


def test_adaptive_beats_fixed_after_a_sharp_degradation():
    def average(policy):
        secs, fired = t.drift_loop(t.Rule(20), 0.0012, 6000, policy=policy, flat=4000)
        return (sum(secs[4000:]) + 20 * sum(f[0] > 4000 for f in fired)) / 2000

    gain = measures.improvement(average("fixed"), average("adaptive"))
    assert 5 < gain < 15


def test_medians_and_ratios():
    assert t.median_of_recent((3.0,)) == 3.0 and t.median_of_recent((3.0, 1.0)) == 2.0 and t.median_of_recent((5.0, 1.0, 2.0)) == 2.0
    assert math.isinf(t.ideal_interval(5, 0))
    assert round(measures.speedup(9.92, 0.995), 2) == 9.97 and round(measures.improvement(4.17, 3.78), 1) == 9.4


def test_overhead_orders():
    cost = lambda preset, n, p: {m: measures.overhead_model(m, n, p, **measures.PRESETS[preset]) for m in ("single_site", "peer", "hybrid")}
    slow = cost("slow_network", 4 * 65_520, 65_520)
    fast = cost("fast_network", 2 * 393_216, 393_216)
    assert slow["hybrid"] < slow["single_site"] < slow["peer"]
    assert fast["peer"] < fast["hybrid"] < fast["single_site"]
