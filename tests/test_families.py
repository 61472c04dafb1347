"""Keys: independent of blocks, equal to their definition on padded vectors, and covering without misses."""

import itertools

import numpy as np
import pytest

from itemset_sieve.families import BitSample, Covering, MinWise
from itemset_sieve.operators.vertical import BLOCK
from itemset_sieve.plans.params import Facts


def packed(v):
    out = np.zeros((len(v), BLOCK), np.uint8)
    out[:, : v.shape[1]] = v
    return np.packbits(out, axis=1, bitorder="little")


def keys(family, v, side):
    return family.finish(family.partial(packed(v), 0), v.sum(1), side)


def data(seed=0, m=14, n=60, s_min=12):
    rng = np.random.default_rng(seed)
    v = (rng.random((m, n)) < 0.45).astype(np.uint8)
    v = v[v.sum(1) >= s_min]
    return v, Facts(n, s_min, len(v), int(v.sum(1).max()), s_min / n, 0.3, 0.1)


def test_bit_sampling_keys_are_equal_iff_the_sampled_padded_bits_are():
    from itemset_sieve.plans.padding import materialise

    v, f = data()
    fam = BitSample(f)
    p = np.array([materialise(x, f.A, "stored") for x in v])
    q = np.array([materialise(x, f.A, "query") for x in v])
    ks, kq = keys(fam, v, "stored"), keys(fam, v, "query")
    for t in range(fam.width):
        pos = fam.pos[fam.table == t]
        same = (p[:, None, pos] == q[None, :, pos]).all(2)
        assert (same == (ks[:, None, t] == kq[None, :, t])).all()


def test_minwise_slots_agree_as_often_as_padded_vectors_are_similar():
    v, f = data(1)
    fam = MinWise(f, lambda_override=3000)
    a, b = keys(fam, v, "stored"), keys(fam, v, "query")
    for i, j in itertools.product(range(len(v)), repeat=2):
        ip = int((v[i] & v[j]).sum())
        assert abs((a[i] == b[j]).mean() - ip / (2 * f.A - ip)) < 0.05


@pytest.mark.parametrize("mode", ["blocks", "exact_radius0"])
@pytest.mark.parametrize("seed", range(6))
def test_covering_never_misses(mode, seed):
    v, f = data(seed)
    fam = Covering(f, seed=seed, mode=mode)
    a, b = keys(fam, v, "stored"), keys(fam, v, "query")
    for i, j in itertools.product(range(len(v)), repeat=2):
        if (v[i] & v[j]).sum() >= f.s_min:
            assert (a[i] == b[j]).any()


@pytest.mark.parametrize("seed", range(4))
def test_full_covering_meets_for_all_small_differences(seed):
    n, r = 14, 4
    f = Facts(n, 5, 2, 7, 5 / n, 0.3, 0.1)
    fam = Covering(f, seed=seed, mode="full")
    assert fam.bits == int(fam.p["t"]) * r + 1
    x = np.random.default_rng(seed).integers(0, 2, n).astype(np.uint8)
    for k in range(r + 1):
        for at in itertools.combinations(range(n), k):
            y = x.copy()
            y[list(at)] ^= 1
            w = fam._even(fam.partial(packed(np.stack([x, y])), 0).reshape(2, fam.b, fam.cells))
            total = np.bitwise_xor.reduce(fam.partial(packed(np.stack([x, y])), 0).reshape(2, fam.b, fam.cells), axis=2)
            k0, k1 = (total[:, :, None] ^ w)[:, 0, 1:]
            assert (k0 == k1).any()


@pytest.mark.parametrize("family", [BitSample, MinWise, Covering])
def test_blocks_combine_in_any_order(family):
    v, f = data(2, n=60)
    fam = family(f)
    whole = fam.partial(packed(v), 0)
    left, right = v.copy(), v.copy()
    left[:, 30:], right[:, :30] = 0, 0
    a, b = fam.partial(packed(left), 0), fam.partial(packed(right), 0)
    assert (fam.combine(a, b) == whole).all() and (fam.combine(b, a) == whole).all()


def test_an_itemset_without_sampled_positions_keeps_a_key():
    f = Facts(1000, 1, 2, 1, 0.001, 0.3, 0.1)
    v = np.zeros((2, 1000), np.uint8)
    v[0, 3] = v[1, 7] = 1
    assert keys(BitSample(f), v, "stored").shape == (2, BitSample(f).width)


def test_pair_survival_over_seeds():
    v, f = data(3, m=8)
    pairs = [(i, j) for i in range(len(v)) for j in range(len(v)) if i != j and (v[i] & v[j]).sum() >= f.s_min]
    hits = 0
    for seed in range(60):
        fam = BitSample(f, seed=seed)
        a, b = keys(fam, v, "stored"), keys(fam, v, "query")
        hits += sum((a[i] == b[j]).any() for i, j in pairs)
    assert hits / (60 * len(pairs)) >= 1 - f.delta - 0.03


def test_bit_sampling_looks_at_sampled_transactions_alone():
    f = Facts(100_000, 300, 40, 1200, 0.003, 0.3, 0.1)
    fam = BitSample(f)
    bits = np.random.default_rng(0).integers(0, 256, (9, BLOCK // 8), dtype=np.uint8)
    seen = fam.view(bits, 1)
    inside = np.unique(fam.pos[(fam.pos >= BLOCK) & (fam.pos < 2 * BLOCK)] - BLOCK)
    assert seen.shape[1] == -(-len(inside) // 8) < BLOCK // 16
    other = np.unpackbits(bits, axis=1, bitorder="little")
    other[:, np.setdiff1d(np.arange(BLOCK), inside)] ^= 1
    assert (fam.partial(np.packbits(other, axis=1, bitorder="little"), 1) == fam.partial_of(seen, 1)).all()
    both = seen[:4] & seen[4:8]
    assert (fam.partial_of(both, 1) == fam.partial(bits[:4] & bits[4:8], 1)).all()


@pytest.mark.parametrize("family", [MinWise, Covering])
def test_paddings_of_any_length_fit_into_memory(family):
    import tracemalloc

    a = 10**8 if family is MinWise else 10**6
    f = Facts(4 * a, a - 4, 40, a, (a - 4) / (4 * a), 0.3, 0.1)
    fam = family(f)
    tracemalloc.start()
    fam.finish(fam.empty(3), np.array([1, a // 2, a]), "stored")
    assert tracemalloc.get_traced_memory()[1] < 200_000_000
    tracemalloc.stop()


def test_padding_minima_grow_smaller_and_are_those_of_uniform_hashes():
    f = Facts(1000, 10, 40, 1000, 0.01, 0.3, 0.1)
    fam = MinWise(f, lambda_override=4000)
    low = fam.finish(fam.empty(4), np.array([999, 990, 900, 0]), "query").astype(float) / 2**64
    assert (np.diff(low, axis=0) <= 0).all()
    assert np.allclose(low.mean(1), [1 / 2, 1 / 11, 1 / 101, 1 / 1001], rtol=0.08)
    assert (fam.finish(fam.empty(4), np.array([999, 990, 900, 0]), "stored") != fam.finish(fam.empty(4), np.array([999, 990, 900, 0]), "query")).mean() > 0.99


def test_minwise_blocks_equal_plain_minima_and_are_quick():
    import time

    rng = np.random.default_rng(4)
    n = 2 * 32_768
    fam = MinWise(Facts(n, 1000, 25, 9000, 0.02, 0.3, 0.1), lambda_override=300)
    dense = np.vstack([rng.random((25, 32_768)) < p for p in (0.1,)] + [rng.random((3, 32_768)) < 1e-4, np.zeros((1, 32_768), bool)])
    bits = np.packbits(dense, axis=1, bitorder="little")
    began = time.perf_counter()
    got = fam.partial_of(bits, 1)
    took = time.perf_counter() - began
    began = time.perf_counter()
    want = fam.empty(len(bits))
    for lo in range(0, 300, 60):
        h = fam.hashes(fam.transactions(1), range(lo, lo + 60))
        for i, row in enumerate(dense):
            if row.any():
                want[i, lo : lo + 60] = h[:, np.nonzero(row)[0]].min(1)
    plain = time.perf_counter() - began
    print(took, plain)
    assert (got == want).all() and took < 0.7 * plain


@pytest.mark.parametrize("remembered", [4096, 0])
@pytest.mark.parametrize("mode", ["blocks", "exact_radius0"])
@pytest.mark.parametrize("pad", [True, False])
def test_pairs_found_block_by_block_are_those_of_all_keys(remembered, mode, pad, monkeypatch):
    from itemset_sieve.operators import meetings

    monkeypatch.setattr(meetings, "MATRIX", remembered)
    rng = np.random.default_rng(5)
    v = (rng.random((9, 700)) < rng.uniform(0.5, 0.95, (9, 1))).astype(np.uint8)
    v[3] = v[2]
    members = np.array(list(itertools.combinations(range(9), 2)))
    sets = v[members[:, 0]] & v[members[:, 1]]
    keep = sets.sum(1) >= 150
    members, sets = members[keep], sets[keep]
    s = sets.sum(1)
    f = Facts(700, 150, len(sets), int(s.max()), 150 / 700, 0.3, 0.1)
    fam = Covering(f, seed=2, mode=mode, pad=pad)
    a, b = keys(fam, sets, "stored"), keys(fam, sets, "query")
    want = {}
    for i, j in itertools.permutations(range(len(sets)), 2):
        t = np.nonzero(a[i] == b[j])[0]
        if len(t) and len({*members[i], *members[j]}) == 3:
            want[i, j] = t[0]
    pos = np.arange(f.n + 2 * f.A)
    half, got = fam.b // 2, {}
    block = fam.places(pos)[0] // fam.cells
    for lo, hi in ((0, half), (half, fam.b)):
        own = np.append(pos[(block >= lo) & (block < hi)], -1)
        bits = np.packbits(np.where((own >= 0) & (own < f.n), v[:, np.minimum(own, f.n - 1)], 0), axis=1, bitorder="little")
        for met in meetings.meet(fam, members, s, lo, hi, own, bits, True):
            for i, j, t in zip(*(x.tolist() for x in met)):
                got[i, j] = min(t, got.get((i, j), t))
    assert got == want and len(want) > 20
    one_way = {tuple(sorted(p)) for lo, hi in ((0, fam.b),) for a, q, _ in meetings.meet(fam, members, s, lo, hi, pos, np.packbits(np.concatenate([v, np.zeros((9, 2 * f.A), np.uint8)], axis=1), axis=1, bitorder="little"), False) for p in zip(a.tolist(), q.tolist())}
    assert one_way == {tuple(sorted(p)) for p in want}


def test_itemsets_without_any_difference_meet_at_once():
    from itemset_sieve.operators import meetings

    members = np.array(list(itertools.combinations(range(18), 2)))
    f = Facts(200_000, 100_000, len(members), 200_000, 0.5, 0.3, 1e-6)
    fam = Covering(f)
    assert meetings.by_group(len(members), fam)
    pos = np.arange(f.n)
    pos = pos[fam.places(pos)[0] // fam.cells < 2000]
    bits = np.full((18, -(-len(pos) // 8)), 255, np.uint8)
    looked = []
    fam.keys_of = lambda x: looked.append(x.shape[1]) or Covering.keys_of(fam, x)
    met = list(meetings.meet(fam, members, np.full(len(members), f.n), 0, 2000, pos, bits, True))
    assert sum(len(a) for a, _, _ in met) == 153 * 32 and sum(looked) <= 4


def test_minwise_looks_at_few_positions_of_usual_itemsets(monkeypatch):
    from itemset_sieve.families import minwise

    rng = np.random.default_rng(6)
    ones = rng.random((70, BLOCK)) < rng.uniform(0.05, 0.6, (70, 1))
    fam = MinWise(Facts(3 * BLOCK, 4900, 70, 60_000, 0.05, 0.3, 0.1), lambda_override=2500)
    looked, scramble, arrivals = [], minwise.scramble, MinWise.arrivals
    monkeypatch.setattr(minwise, "scramble", lambda x, seed: looked.append(x.size) or scramble(x, seed))
    monkeypatch.setattr(MinWise, "arrivals", lambda *a: looked.append((r := arrivals(*a))[0].size) or r)
    got = fam.partial_of(np.packbits(ones, axis=1, bitorder="little"), 1)
    assert sum(looked) < 2500 * BLOCK / 50
    assert np.allclose((got.astype(float) / 2**64).mean(1) * (ones.sum(1) + 1), 1, atol=0.12)
    x, y = ones[0] & ones[1], ones[0] | ones[1]
    assert abs((got[0] == got[1]).mean() - x.sum() / y.sum()) < 0.05
