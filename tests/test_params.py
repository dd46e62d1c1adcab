from __future__ import annotations

import math

import pytest

from vecforest.functions.params import SUCCESS, ForestParams, chi2_survival, chi2_upper, derive_params, pick_L

# fixed values: K = 16, c = 1.5
KNOWN = {1: (4.1566, 0.08428), 2: (3.7276, 0.05527), 3: (3.5203, 0.04411), 4: (3.3885, 0.03799), 5: (3.2937, 0.03405), 8: (3.1123, 0.02752), 16: (2.8811, 0.02092)}


@pytest.mark.parametrize("L", KNOWN)
def test_eps_and_beta(L):
    p = derive_params(16, 1.5, L)
    assert p["eps"] == pytest.approx(KNOWN[L][0], abs=1e-4)
    assert p["beta"] == pytest.approx(KNOWN[L][1], abs=1e-5)


def test_chi2_inverts():
    for k in (1, 4, 15, 16):
        for a in (0.01, 0.3, 0.7788, 0.99):
            assert chi2_survival(chi2_upper(a, k), k) == pytest.approx(a, abs=1e-12)
    assert chi2_survival(3.841458820694124, 1) == pytest.approx(0.05, abs=1e-9)


def test_knee_and_guarantee():
    assert pick_L() in (3, 4, 5)
    assert SUCCESS == pytest.approx(0.1321, abs=1e-4)
    assert ForestParams().guaranteed(1000, 50)
    assert not ForestParams(K=4, L=16).guaranteed(1000, 50)
    assert not ForestParams(max_candidates=10).guaranteed(1000, 50)
    assert math.isclose(ForestParams(K=4, L=16).beta_theory, 0.39899, abs_tol=1e-4)
