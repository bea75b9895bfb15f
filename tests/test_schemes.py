"""Worked cases, exact decoding from every sufficient set, thresholds, errors."""

from fractions import Fraction
from itertools import combinations

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from tolerant_gd.operators import analytic, lagrange, polycode
from tolerant_gd.operators.simulate import Replay
from tolerant_gd.plans.scheme import available, expansion, message_threshold, recoverable, scheme, slots, worker_threshold


def unit_times(n, workers, seed=0):
    return 0.01 - np.log(np.random.default_rng(seed).random((n, workers))) / 10


@pytest.mark.parametrize(
    ("sch", "messages"),
    [
        (scheme("gradcode_single", 6, 3), 4),
        (scheme("gradcode_shared", 6, 3, order=2), 5),
        (scheme("gradcode_layered", 6, 3, orders=(3, 2)), 8),
        (scheme("gradcode_single", 10, 3, P=2), 3),
        (scheme("lagrange_single", 6, 3), 3),
        (scheme("lagrange_multi", 6, 3), 11),
        (scheme("lagrange_single", 20, 3), 13),
        (scheme("lagrange_multi", 40, 10, polys=2), 39),
        (scheme("uncoded_partial", 40, 2, tolerance=0.05), 38),
    ],
)
def test_thresholds(sch, messages):
    assert message_threshold(sch) == messages


def test_worked_recoveries():
    shared = scheme("gradcode_shared", 6, 3, order=2)
    assert recoverable(shared, [0, 1, 3])
    assert sum(recoverable(shared, c) for c in combinations(range(6), 3)) == 14
    assert worker_threshold(scheme("gradcode_repeat", 40, 10)) == 31
    assert recoverable(scheme("gradcode_repeat", 40, 10), [0, 10, 20, 30])
    plain, split = scheme("gradcode_single", 10, 3), scheme("gradcode_single", 10, 3, P=2)
    sets = [c for n in range(11) for c in combinations(range(10), n)]
    good, more = {c for c in sets if recoverable(plain, c)}, {c for c in sets if recoverable(split, c)}
    assert (len(good), len(more)) == (56, 256)
    assert good <= more


def test_layered_example_with_partial_workers():
    """Three full workers, two with the lighter message only, one dead: eight messages."""
    sch = scheme("gradcode_layered", 6, 3, orders=(3, 2))
    got = Replay(sch)
    unit = np.array([[1.0, 1.0, 1.0, 1.4, 1.4, 9.0]])
    end, load = got.complete(got.ready(unit, np.zeros_like(unit)))
    assert end[0] == 3.0
    assert load[0] == 8


@pytest.mark.parametrize("case", [("cyclic", 6, 3), ("cyclic", 7, 4), ("shared", 6, 2)])
def test_every_sufficient_set_decodes(case):
    kind, K, m = case
    masks = polycode.supports([(w, j, (w + j) % K) for w in range(K) for j in range(m)])
    points = list(range(1, K + 1))
    h = polycode.degree(masks, set(range(K)))
    g = [Fraction(v) for v in np.random.default_rng(1).integers(-50, 50, K)]
    codes = [Fraction(0)] * K
    for i, b, c in polycode.encode_coefs(masks, points):
        codes[i] += c * g[b]
    for received in combinations(range(K), h + 1):
        weights, d = polycode.decode_coefs(points, list(received), h)
        assert sum(w * codes[i] for i, w in weights) == d * sum(g)


def test_layered_code_decodes_from_all_495_sets():
    sch = scheme("gradcode_layered", 6, 3, orders=(3, 2))
    masks = polycode.supports(slots(sch), [(w, m) for w in range(6) for m in (2, 3)])
    h = polycode.degree(masks, set(range(6)))
    assert h == 7
    g = list(range(3, 9))
    codes = [0] * 12
    for i, b, c in polycode.encode_coefs(masks):
        codes[i] += c * g[b]
    for received in combinations(range(12), 8):
        weights, d = polycode.decode_coefs(list(range(1, 13)), list(received), h)
        assert sum(w * codes[i] for i, w in weights) == d * sum(g)


def test_uneven_columns_need_padding():
    masks = [{0, 1}, {1, 2}, {2}]
    with pytest.raises(ValueError):
        polycode.encode_coefs(masks)
    h, codes = polycode.degree(masks, {0, 1, 2}), [0, 0, 0]
    for i, b, c in polycode.encode_coefs(masks, pad=True):
        codes[i] += c * (10, 20, 30)[b]
    weights, d = polycode.decode_coefs([1, 2, 3], [0, 1, 2], h)
    assert sum(w * codes[i] for i, w in weights) == 60 * d


@pytest.mark.parametrize(("K", "r", "polys"), [(6, 3, 3), (6, 3, 1), (6, 4, 2), (10, 5, 5), (20, 3, 3), (6, 2, 1)])
def test_lagrange_in_the_field(K, r, polys):
    """Scalar blocks: the decoded value is the sum of squares times theta, from random sets of threshold size."""
    code, p = lagrange.Code(K, r, polys), lagrange.PRIME
    rng = np.random.default_rng(2)
    x = [int(v) for v in rng.integers(0, 1000, code.blocks * polys)]
    x[K:] = [0] * (len(x) - K)
    values = []
    for _, _, w in code.encode_coefs():
        total = 0
        for q in range(polys):
            coded = sum(a * b for a, b in zip(w, x[q * code.blocks : (q + 1) * code.blocks], strict=True)) % p
            total += coded * coded * 7
        values.append(total % p)
    for _ in range(5):
        received = [int(i) for i in rng.permutation(len(values))[: code.threshold]]
        assert sum(w * values[i] for i, w in code.decode_coefs(received)) % p == 7 * sum(v * v for v in x)
    with pytest.raises(ValueError):
        code.decode_coefs(list(range(code.threshold - 1)))


@pytest.mark.parametrize(
    "bad",
    [
        ("gradcode_repeat", 10, 3, {}),
        ("gradcode_single", 10, 3, {"P": 3}),
        ("gradcode_single", 12, 5, {"P": 4}),
        ("gradcode_shared", 6, 3, {"order": 4}),
        ("gradcode_layered", 6, 3, {"orders": (4, 2)}),
        ("gradcode_hybrid", 10, 3, {"orders": (3, 2)}),
        ("lagrange_multi", 6, 1, {}),
        ("lagrange_multi", 6, 3, {"polys": 2}),
        ("first_workers", 6, 1, {"need": 7}),
        ("nothing", 6, 1, {}),
    ],
)
def test_impossible_schemes_are_refused(bad):
    name, K, r, options = bad
    with pytest.raises(ValueError):
        scheme(name, K, r, **options)


def test_expansion_must_be_asked_for():
    with pytest.raises(ValueError):
        expansion(scheme("lagrange_single", 6, 3), 100)
    assert expansion(scheme("lagrange_single", 6, 3), 100, allow_expand=True) == 300
    assert expansion(scheme("uncoded_multi", 6, 3), 100) == 0


@settings(max_examples=25, deadline=None)
@given(st.integers(0, 10_000), st.sampled_from([(6, 3), (12, 4), (20, 4)]))
def test_identities_and_dominance(seed, shape):
    K, r = shape
    unit = unit_times(20, K, seed)
    zero = np.zeros_like(unit)

    def t(*args, **options):
        p = Replay(scheme(*args, **options))
        return p.complete(p.ready(unit, zero))[0]

    same = [
        (t("gradcode_shared", K, r, order=1), t("uncoded_multi", K, r)),
        (t("lagrange_multi", K, r, polys=r), t("lagrange_single", K, r)),
        (t("uncoded_partial", K, r, tolerance=0.0), t("uncoded_multi", K, r)),
        (t("wait_all", K), unit.max(axis=1)),
        (t("gradcode_shared", K, r, order=r), t("gradcode_single", K, r)),
    ]
    if K % r == 0:
        same.append((t("gradcode_repeat", K, r), t("gradcode_single", K, r, P=K // r)))
    for a, b in same:
        assert np.allclose(a, b)
    assert (t("gradcode_single", K, r, P=K // r if K % r == 0 else 1) <= t("gradcode_single", K, r) + 1e-12).all()
    assert (t("uncoded_partial", K, r, tolerance=0.2) <= t("uncoded_multi", K, r)).all()
    assert (t("uncoded_multi", K, r) <= t("uncoded_single", K, r) + 1e-12).all()


def test_closed_forms():
    assert analytic.expected_workers(40, 10, 31) == pytest.approx(1.549575, abs=1e-6)
    assert analytic.expected_workers(40, 10, 7) == pytest.approx(0.289745, abs=1e-6)
    assert analytic.cdf_messages(6, 3, 11, 0.2, "enumerate") == pytest.approx(0.61459641, abs=1e-8)
    assert analytic.cdf_messages(6, 3, 11, 0.2, "convolve") == pytest.approx(0.61459641, abs=1e-8)
    assert analytic.cdf_messages(10, 5, 19, 0.2) == pytest.approx(0.85361575, abs=1e-8)
    multi = scheme("lagrange_multi", 40, 10)
    assert analytic.expected_completion(lambda t: analytic.cdf(multi, t), 3.0, 0.002) == pytest.approx(0.12688, abs=3e-4)
    with pytest.raises(ValueError):
        analytic.cdf(scheme("uncoded_multi", 6, 3), 0.1)


def test_closed_form_agrees_with_simulation():
    for sch in (scheme("gradcode_single", 6, 3), scheme("lagrange_multi", 10, 5), scheme("gradcode_layered", 12, 4, orders=(4, 3), P=3)):
        unit = unit_times(20_000, sch.K, 5)
        p = Replay(sch)
        ends, _ = p.complete(p.ready(unit, np.zeros_like(unit)))
        for t in (0.1, 0.2, 0.4):
            c = analytic.cdf(sch, t)
            assert abs((ends <= t).mean() - c) <= 4 * (c * (1 - c) / 20_000) ** 0.5 + 1e-3


def test_ties_and_zero_delay():
    p = Replay(scheme("uncoded_multi", 6, 3))
    unit = np.ones((1, 6))
    end, load = p.complete(p.ready(unit, np.zeros_like(unit)))
    assert (end[0], load[0]) == (1.0, 6)
    assert available(scheme("wait_all", 6)) == 6


def test_facade(spark):
    from tolerant_gd import api

    s = api.scheme("gradcode_layered", 6, 3, orders=(3, 2))
    grads = spark.createDataFrame([(b, 0, (b + 1) * 10) for b in range(6)], "batch int, dim int, v bigint")
    assert [tuple(r) for r in api.decode(api.encode(grads, s), [11, 3, 0, 7, 5, 2, 9, 4], s).collect()] == [(0, 210)]
    assert api.layout(spark, s).count() == 18
    assert api.messages(spark, s).count() == 12
    lat = api.latency(spark, "shifted_exponential", 5, 6)
    assert api.complete(api.arrivals(lat, api.messages(spark, s))).count() == 5
    with pytest.raises(ValueError):
        api.lagrange_encode(grads, api.scheme("lagrange_single", 6, 3), ["v"])
    with pytest.raises(ValueError):
        api.latency(spark, "none", 1, 1)


def test_worker_threshold_is_the_worst_case_of_all_sets():
    cases = [scheme("wait_all", 5), scheme("first_workers", 6, need=4), scheme("relaunch", 5), scheme("backup_workers", 4, extra=3), scheme("backup_workers", 3, extra=4)]
    for K, r in ((6, 1), (6, 2), (6, 3), (8, 4), (7, 3), (9, 3)):
        for P in (1, 2, 3):
            if K % P or r > K // P:
                continue
            cases += [scheme("gradcode_single", K, r, P=P), scheme("gradcode_layered", K, r, P=P, orders=(r, max(1, r - 1)))]
            cases += [scheme("gradcode_shared", K, r, P=P, order=m) for m in range(1, r + 1)]
        cases += [scheme(n, K, r) for n in ("uncoded_multi", "uncoded_single")] + [scheme("uncoded_partial", K, r, tolerance=0.3)]
        if K % r == 0:
            cases.append(scheme("gradcode_repeat", K, r))
    cases += [scheme("gradcode_hybrid", 6, 3, P=2, orders=(3, 2)), scheme("lagrange_single", 6, 3), scheme("lagrange_multi", 6, 3), scheme("lagrange_multi", 8, 4, polys=2), scheme("lagrange_multi", 9, 3)]
    for s in cases:
        least = next(n for n in range(1, s.workers + 1) if all(recoverable(s, c) for c in combinations(range(s.workers), n)))
        assert worker_threshold(s) == least, s
