"""Padding identities, monotone collisions, the minwise threshold identity, and why padding is needed."""

import math

import numpy as np
import pytest

from itemset_sieve.families import BitSample, Covering, MinWise
from itemset_sieve.operators.vertical import min_support
from itemset_sieve.plans import padding, params
from itemset_sieve.plans.params import Facts


def vectors(seed, m=12, n=40):
    rng = np.random.default_rng(seed)
    return (rng.random((m, n)) < rng.uniform(0.1, 0.8, (m, 1))).astype(np.uint8)


@pytest.mark.parametrize("seed", range(5))
def test_padded_distance_and_similarity_depend_on_shared_transactions_alone(seed):
    v = vectors(seed)
    a = int(v.sum(1).max())
    for x in v:
        for y in v:
            p, q = padding.materialise(x, a, "stored"), padding.materialise(y, a, "query")
            ip = int((x & y).sum())
            assert len(p) == len(q) == len(x) + 2 * a and p.sum() == q.sum() == a
            assert (p ^ q).sum() == padding.hamming_from_ip(ip, a)
            assert math.isclose((p & q).sum() / (p | q).sum(), padding.jaccard_from_ip(ip, a))
            assert padding.ip_from_hamming(padding.hamming_from_ip(ip, a), a) == ip
            assert math.isclose(padding.ip_from_jaccard(padding.jaccard_from_ip(ip, a), a), ip, abs_tol=1e-9)


def facts(**more):
    return Facts(**({"n": 1000, "s_min": 100, "m": 50, "A": 300, "theta": 0.1, "eps": 0.3, "delta": 0.1} | more))


@pytest.mark.parametrize("family", [BitSample, MinWise, Covering])
def test_collision_probability_rises_with_shared_transactions(family):
    f = family(facts(A=130), **({"lambda_override": 50} if family is MinWise else {}))
    p = [f.collision_prob(ip) for ip in range(60, 130)]
    assert all(x < y for x, y in zip(p, p[1:]))


@pytest.mark.parametrize("eps", [0.1, 0.3, 0.7])
@pytest.mark.parametrize("most", [101, 150, 300, 900])
def test_minwise_threshold_is_where_both_guarantees_meet(eps, most):
    p = params.minwise(facts(A=most, eps=eps))
    assert math.isclose(p["accept"], (1 + p["eps_m"]) * p["omega"], rel_tol=1e-12)


def test_strict_rounding_keeps_the_promised_miss_probability():
    for m in (2, 16, 215):
        p = params.bitsample(facts(m=m))
        assert (1 - p["p1"] ** p["k"]) ** p["L"] <= 0.1 + 1e-12


def test_inner_product_alone_has_no_symmetric_hash():
    a, b, c = np.array([1, 1, 1, 0]), np.array([1, 1, 1, 1]), np.array([0, 0, 0, 1])
    assert (a & b).sum() > (c & c).sum()


def test_threshold_is_exact_in_decimals():
    assert min_support("0.45", 1000) == 450 and min_support(0.1, 4006) == 401 and min_support("0.02", 14743) == 295
    assert min_support("0.000001", 10) == 1


def test_banding_meets_its_promise():
    bands, rows = params.banding(400, 0.6, 0.05)
    assert bands * rows <= 400 and (1 - 0.6**rows) ** bands <= 0.05 and (1 - 0.6 ** (rows + 1)) ** (400 // (rows + 1)) > 0.05


def test_error_budget():
    assert params.delta_for(0.16, 4) == 0.01
