"""Families, moves and chain state against brute force over all families of up to five items."""

import random
from itertools import combinations

import pytest

from posterior_patterns.operators import bic, catalogue, entropy, expmodel, family, moves, sampler
from posterior_patterns.operators.family import mask_of
from posterior_patterns.operators.state import ChainState
from posterior_patterns.sources.tables import EXAMPLE_ROWS, row_mask

ROWS = [row_mask(r) for r in EXAMPLE_ROWS]
F1 = [mask_of(p) for p in ((1, 2), (2, 3), (2, 4), (4, 5))]


def cache():
    return entropy.EntropyCache(ROWS, [1] * len(ROWS))


@pytest.mark.parametrize("k, n", [(1, 1), (2, 2), (3, 8), (4, 61), (5, 822)])
def test_catalogue_sizes(k, n):
    found = catalogue.decomposable(k)
    assert len(found) == n == len({tuple(f) for f in found})
    assert all(family.is_decomposable(f) and family.is_decomposable_by_elimination(f) and family.cycle_witness(f) is None for f in found)


def test_general_families():
    assert [len(catalogue.general(k)) for k in (1, 2, 3, 4)] == [1, 2, 9, 114]


def test_not_decomposable():
    triangle, ring = [3, 5, 6], [3, 6, 12, 9]
    for f in (triangle, ring):
        assert not family.is_decomposable(f) and not family.is_decomposable_by_elimination(f) and family.cycle_witness(f)


@pytest.mark.parametrize("k", [3, 4, 5])
def test_moves_are_the_edge_flips(k):
    h, n = cache(), len(ROWS)
    for f in catalogue.decomposable(k):
        flips = sorted(map(tuple, moves.neighbours_by_flip(f, k)))
        merges, splits = moves.legal_merges(f), moves.legal_splits(f)
        mine = [tuple(moves.merge(f, *m)) for m in merges] + [tuple(moves.split(f, *s)) for s in splits]
        assert sorted(mine) == flips and len(set(mine)) == len(mine) == moves.degrees(f)[2]
        assert len(family.closure(f)) == family.family_size(f)
        assert len(f) <= k and len(moves.joints(f)) <= k - 1
        here = bic.log_bic(f, h, n)
        for s, x, y in merges:
            assert bic.log_bic(moves.merge(f, s, x, y), h, n) - here == pytest.approx(bic.move_delta(True, h, n, s, x, y), abs=1e-9)
        for whole, x, y in splits:
            assert bic.log_bic(moves.split(f, whole, x, y), h, n) - here == pytest.approx(bic.move_delta(False, h, n, whole & ~x & ~y, x, y), abs=1e-9)


def test_paths_to_independence():
    for f in catalogue.decomposable(5):
        now = f
        for step in moves.path_to_independence(f):
            now = moves.split(now, *step)
            assert family.is_decomposable(now)
        assert now == family.singletons(5)


@pytest.mark.parametrize("k, steps", [(5, 1500), (9, 1000), (25, 250)])
def test_incremental_state_is_the_rebuilt_one(k, steps):
    rng, state = random.Random(k), ChainState(k)
    for _ in range(steps):
        fresh = ChainState(k, sorted(state.maxs))
        assert (state.parts, state.once, state.occ, state.md) == (fresh.parts, fresh.once, fresh.occ, fresh.md)
        is_merge, s, x, y = state.move(rng.randrange(state.degree))
        (state.merge if is_merge else state.split)(s, x, y)


def test_every_move_is_drawn_once():
    for f in catalogue.decomposable(4):
        state = ChainState(4, f)
        drawn = {state.move(i) for i in range(state.degree)}
        assert len(drawn) == state.degree


def test_unequal_components_are_drawn_uniformly():
    state = ChainState(4, [3, 4, 8])
    assert (len(state.once), state.md) == (1, 5)
    assert {state.move(i)[2:] for i in range(1, 6)} == {(1, 4), (1, 8), (2, 4), (2, 8), (4, 8)}


def test_toy_families():
    assert moves.reduced_family(F1, 2) == [1, 4, 8] and moves.reduced_family(F1, 8) == [2, 16]
    f2 = moves.merge(F1, 2, 4, 8)
    assert f2 == sorted([3, 14, 24]) and moves.reduced_family(f2, 2) == [1, 12] and moves.reduced_family(f2, 8) == [6, 16]
    f3 = moves.merge(f2, 8, 4, 16)
    assert moves.reduced_family(f3, 12) == [2, 16]
    assert (14, 4, 8) not in moves.legal_splits(f3)


def test_worked_example_weights():
    h, n = cache(), 9
    assert [round(h(mask_of(s)), 4) for s in ((1,), (2,), (3,), (4,), (5,), (1, 2), (2, 3), (2, 4), (4, 5))] == [0.6870, 0.6870, 0.6870, 0.6365, 0.6870, 1.3108, 1.3689, 1.0609, 1.0609]
    import math

    a, b = bic.log_bic(F1, h, n), bic.log_bic(family.singletons(5), h, n)
    assert 1 / (1 + math.exp(b - a)) == pytest.approx(0.72030, abs=1e-5)


def test_likelihood_is_the_density_over_rows():
    import numpy as np

    q = np.bincount(ROWS, minlength=32) / 9
    for f in (F1, [7, 12, 24], family.singletons(5)):
        p = expmodel.closed_form(q, f)
        assert p.sum() == pytest.approx(1)
        assert bic.log_lik(f, cache(), 9) == pytest.approx(sum(np.log(p[r]) for r in ROWS))
        fitted, _ = expmodel.fit_ipf(q, f)
        assert abs(fitted - p).max() < 1e-8
    assert expmodel.fit_ipf(q, [3, 5, 6, 8, 16])[0].sum() == pytest.approx(1)


def test_stationary_law_of_a_chain():
    h, n = cache(), 9
    import math

    weights = {tuple(f): bic.log_bic(f, h, n) for f in catalogue.decomposable(3)}
    total = sum(map(math.exp, weights.values()))
    for proposal in ("legal", "flip"):
        families, _ = sampler.run_chain(h, 3, n, 60_000, 3, proposal=proposal, thin=4)
        for f, w in weights.items():
            share = sum(tuple(x) == f for x in families) / len(families)
            assert share == pytest.approx(math.exp(w) / total, abs=0.03)


def test_degenerate_chains():
    assert sampler.default_steps(1) == 0
    families, _ = sampler.run_chain(entropy.EntropyCache([0, 1], [3, 4]), 1, 7, 10, 1)
    assert families == [[1]]
    families, _ = sampler.run_chain(entropy.EntropyCache([], []), 3, 0, 50, 1)
    assert family.is_decomposable(families[0])
    families, _ = sampler.run_chain(entropy.EntropyCache([7], [5]), 3, 5, 200, 1)
    assert families and family.is_decomposable(families[0])


def test_wide_patterns_have_the_same_entropies():
    rng = random.Random(1)
    masks = [rng.getrandbits(10) for _ in range(200)]
    wide = entropy.EntropyCache([m | 1 << 80 if m & 1 else m for m in masks] + [1 << 90], [1] * 200 + [0])
    narrow = entropy.EntropyCache(masks, [1] * 200)
    for s in combinations(range(10), 3):
        m = sum(1 << i for i in s)
        assert wide(m) == pytest.approx(narrow(m))
    assert wide(1 << 80) == pytest.approx(narrow(1))


def test_seeds_give_the_same_chain():
    a = sampler.run_chain(cache(), 5, 9, 500, 8)[0]
    assert a == sampler.run_chain(cache(), 5, 9, 500, 8)[0] == sampler.run_chain(cache(), 5, 9, 500, 8, rebuild=True)[0]


def test_separators_do_not_depend_on_the_junction_tree():
    """All spanning trees of greatest weight over the maximal sets have the same intersections."""
    for f in catalogue.decomposable(5):
        want = sorted(s for *_, s in family.junction_tree(f))
        pairs = list(combinations(range(len(f)), 2))
        best = -1
        for edges in combinations(pairs, len(f) - 1):
            home = list(range(len(f)))
            for a, b in edges:
                home = [home[a] if x == home[b] else x for x in home]
            if len(set(home)) > 1:
                continue
            cuts = sorted(f[a] & f[b] for a, b in edges)
            weight = sum(c.bit_count() for c in cuts)
            if weight > best:
                best, found = weight, {tuple(cuts)}
            elif weight == best:
                found.add(tuple(cuts))
        if len(f) > 1:
            assert found == {tuple(want)}


def test_a_clique_bound_is_kept():
    h = entropy.EntropyCache([31] * 20 + [0] * 20, [1] * 40)
    for proposal in ("legal", "flip"):
        families, _ = sampler.run_chain(h, 5, 40, 2000, 2, proposal=proposal, max_clique=3, thin=50)
        assert max(m.bit_count() for f in families for m in f) == 3


def test_candidate_extensions_of_independence_and_chain():
    """105 pairs extend 15 single items, 13 triples the chain of 15."""
    from posterior_patterns.operators import measures

    chain = family.maximal([*family.singletons(15), *(3 << i for i in range(14))])
    assert measures.candidate_extensions(family.singletons(15)) == 105
    assert sum((s | x | y).bit_count() == 3 for s, x, y in moves.legal_merges(chain)) == 13


def test_default_steps_as_published():
    assert [sampler.default_steps(k) for k in (15, 100, 139, 90)] == [4063, 46052, 68590, 40499]
