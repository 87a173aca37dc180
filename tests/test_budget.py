"""Mechanisms and budgets: plain numbers."""

import itertools
import math

import pytest

from mistcount.functions import budget as bd
from mistcount.functions import likelihood as lk
from mistcount.layout import Layout
from mistcount.operators import estimate as es


def test_epsilon_of_each_mechanism():
    for e in (0.1, 0.5, 1.0, 3.0):
        assert bd.symmetric(e).epsilon == pytest.approx(e)
        assert bd.half_flip(e).epsilon == pytest.approx(e)
        assert bd.half_flip_loose(e).epsilon < e  # wastes budget
        assert bd.half_flip_appendix(e).epsilon < e
    with pytest.raises(ValueError):
        bd.epsilon_of(0.4, 0.3)
    assert math.isinf(bd.symmetric(math.inf).epsilon)


def test_privacy_is_met_exactly():
    f = bd.symmetric(1.0)
    assert bd.is_private(f.p, f.q, 1.0) and not bd.is_private(f.p, f.q, 0.999)
    assert not bd.is_private(1.0, 0.0, 50)


def test_loose_choice_at_the_equivalent_budget_is_the_tight_one():
    for e in (0.25, 1.0, 4.0):
        assert bd.half_flip_loose(bd.loose_equivalent(e)).q == pytest.approx(bd.half_flip(e).q)
        assert bd.loose_equivalent(e) >= 2 * e


GOLDEN = {(1, 1): (0.510120, (0, 0.854698, 0.854698, 0.540272), (0.459728, 0.145302, 0.145302, 1)), (0.5, 2): (0.415847, (0, 0.684027, 0.967917, 0.553034), (0.446966, 0.032083, 0.315973, 1)), (3, 0.25): (0.235958, (0, 0.993847, 0.586534, 0.537054), (0.462946, 0.413466, 0.006153, 1))}


def test_pair_transitions():
    for (a, b), (star, ors, ands) in GOLDEN.items():
        assert bd.combine_or([a, b]) == pytest.approx(star, abs=1e-6)
        assert bd.transition(a, b) == pytest.approx(ors, abs=1e-6)
        assert bd.transition(a, b, "and") == pytest.approx(ands, abs=1e-6)
    assert bd.combine_xor([1, 1]) == pytest.approx(0.433781, abs=1e-6)
    assert bd.combine_xor([1, 3]) == pytest.approx(0.891222, abs=1e-6)


def closed(ones, epsilons):
    """The one-shot law for noisy bits whose ones are listed."""
    star = math.exp(-bd.combine_or(epsilons))
    return (1 - math.prod(-math.exp(-epsilons[i]) for i in ones)) / (1 + star)


def test_one_shot_law_is_pairwise_induction_in_any_order():
    epsilons = [0.7, 1.3, 2.2]
    want = (0, 0.663420, 0.760011, 0.579208, 0.893825, 0.564381, 0.516415, 0.606199)
    for bits, w in zip(itertools.product((0, 1), repeat=3), want, strict=True):
        assert closed([i for i, b in enumerate(bits) if b], epsilons) == pytest.approx(w, abs=1e-6)
    for order in itertools.permutations(range(3)):
        first = bd.transition(epsilons[order[0]], epsilons[order[1]])
        second = bd.transition(bd.combine_or([epsilons[order[0]], epsilons[order[1]]]), epsilons[order[2]])
        for bits in itertools.product((0, 1), repeat=3):
            t = first[2 * bits[order[0]] + bits[order[1]]]
            chained = t * second[2 + bits[order[2]]] + (1 - t) * second[bits[order[2]]]
            assert chained == pytest.approx(closed([i for i, b in enumerate(bits) if b], epsilons))


def test_one_sketch_is_left_as_it_is():
    assert closed([], [1.5]) == 0 and closed([0], [1.5]) == pytest.approx(1)


def test_every_operation_has_its_law():
    """Noisy inputs through the transition have the noise of the combined budget around the operation's result."""
    for truth in itertools.product((0, 1), repeat=4):
        if len(set(truth)) == 1 or truth in ((0, 0, 1, 1), (1, 1, 0, 0), (0, 1, 0, 1), (1, 0, 1, 0)):
            continue
        e1, e2 = 0.8, 1.7
        t = bd.transition(e1, e2, truth=truth)
        assert all(-1e-9 <= x <= 1 + 1e-9 for x in t)
        star = bd.combine_xor([e1, e2]) if truth in ((0, 1, 1, 0), (1, 0, 0, 1)) else bd.combine_or([e1, e2])
        f1, f2, f = bd.symmetric(e1), bd.symmetric(e2), bd.symmetric(star)
        for x, y in itertools.product((0, 1), repeat=2):
            p1, p2 = (f1.p if x else f1.q), (f2.p if y else f2.q)
            out = sum(t[2 * a + b] * (p1 if a else 1 - p1) * (p2 if b else 1 - p2) for a in (0, 1) for b in (0, 1))
            assert out == pytest.approx(f.p if truth[2 * x + y] else f.q)


def test_a_larger_budget_is_out_of_reach():
    star = bd.combine_or([1.0, 1.0])
    q = bd.symmetric(star + 1e-3).q
    w = math.exp(-1.0)
    # the chance for no ones: (1 - q) - (1 - 2 q) / (1 - w)^2
    assert (1 - q) - (1 - 2 * q) / (1 - w) ** 2 < 0


def test_budgets_form_a_semigroup():
    a, b, c = 0.4, 1.1, 2.5
    for f in (bd.combine_or, bd.combine_xor):
        assert f([f([a, b]), c]) == pytest.approx(f([a, f([b, c])])) == pytest.approx(f([a, b, c]))
        assert f([a, math.inf]) == pytest.approx(a)


STDERR = {1e2: (1.0807, 1.3824, 3.1722, 0.4898, 0.1904, 0.1002), 1e3: (0.1234, 0.1596, 0.3517, 0.0633, 0.0380, 0.0323), 1e4: (0.0297, 0.0413, 0.0823, 0.0174, 0.0130, 0.0123), 1e6: (0.0274, 0.0388, 0.0769, 0.0157, 0.0112, 0.0101)}


def test_standard_errors():
    layout = Layout()
    for n, want in STDERR.items():
        flips = [bd.symmetric(1), bd.half_flip(1), bd.half_flip_loose(1), bd.symmetric(2), bd.symmetric(4), bd.symmetric(math.inf)]
        for f, w in zip(flips, want, strict=True):
            assert lk.stderr_value(layout, n, f.p, f.q) / n == pytest.approx(w, abs=6e-5)
    for k, w in {1: 0.0125, 2: 0.0142, 4: 0.0177, 8: 0.0254, 16: 0.0455, 32: 0.120}.items():
        assert es.stderr_after_merge(layout, [3.0] * k, 1e6) / 1e6 == pytest.approx(w, rel=0.01)


def test_deterministic_merge_costs_up_to_four_times_the_variance():
    ratio = lambda e: (lk.stderr_value(Layout(), 1e6, *_pq(bd.half_flip(e))) / lk.stderr_value(Layout(), 1e6, *_pq(bd.symmetric(e)))) ** 2
    assert ratio(1.0) == pytest.approx(2.0, abs=0.02)
    assert ratio(30.0) == pytest.approx(4.0, abs=0.02)


def _pq(f):
    return f.p, f.q


def test_planning():
    assert es.plan_buckets(0.02, 1.0, 1e6) == 8192
    e = es.plan_epsilon(0.02, 4, 1e6)
    assert es.stderr_after_merge(Layout(), [e] * 4, 1e6) / 1e6 == pytest.approx(0.02, rel=1e-3)
    with pytest.raises(ValueError):
        es.plan_epsilon(0.001, 4, 1e6)
    assert es.plan_layout(150, 1.0).buckets <= 256 and es.plan_layout(15000, 1.0).buckets == 4096
    constants = [es.asymptotic_constant(Layout(), *_pq(bd.symmetric(e))) for e in (0.25, 0.5, 1, 2, 4)]
    assert constants == pytest.approx([6.68, 3.38, 1.76, 1.005, 0.716], rel=0.01)
