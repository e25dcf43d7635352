import math

import pytest

from ebbset import params as P


def test_flip_rates_of_the_synthetic_benchmark():
    drop, add = P.flip_rates(0.5, 0.05)
    assert drop == pytest.approx(1 / 3)
    assert add == pytest.approx(1 / 57)


def test_presets():
    assert [s.name for s in P.PRESETS if s.is_metric] == ["jaccard", "hamming", "anderberg", "rogers_tanimoto"]
    assert not any(P.DICE.is_lshable(a) for a in (0.01, 0.5, 1))


def test_calculators():
    assert P.gray_zone(0.25) == 0.125
    assert P.theory_alpha(0.5, 0.5) == 0.125 / 600
    assert P.max_level(P.JACCARD, 0.5, 0.5, 0.5, 1600) == pytest.approx(0.0)
    assert P.max_level(P.ANDERBERG, 0.5, 0.5, 0.5, 3200) == pytest.approx(0.0)
    assert P.detect_probability(0.25, 5, 300) == pytest.approx(1 - (1 - 0.25**5) ** 300)
    r1, r2, p1, p2 = P.sensitivity(0.5, 0.5, 0.5, 0.001)
    assert p1 == 0.25 and p2 == pytest.approx(6 * 0.001 / (0.5 * 0.9))
    assert P.useful(0.5, 0.5, 0.5, 0.001) and not P.useful(0.5, 0.5, 0.5, 0.1)
    for e in (0.1, 0.3, 0.5):
        low, high = P.ratio_bounds(e)
        assert low >= 1 - 2 * e and high <= 1 + 5 * e


@pytest.mark.parametrize("r1", [0.1, 0.25, 0.3, 0.5, 0.8])
@pytest.mark.parametrize("alpha", [0.01, 0.05, 0.3])
def test_wide_windows_share_a_level(r1, alpha):
    p = P.SketchParams(log_m=16, alpha=alpha, r1=r1)

    def window(n):
        high, low = max(alpha * n, 1.0), min(alpha * n / 2**p.width, float(2 ** p.grid[-1]))
        return {k for k in p.grid if low <= 2**k <= high or (k == 0 and low <= 1)}

    for a in (1, 2, 3, 7, 20, 33, 100, 517, 2000, 65536):
        for b in {math.ceil(r1 * a), (math.ceil(r1 * a) + a) // 2, a}:
            assert window(a) & window(b), (a, b)
