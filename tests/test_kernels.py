import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st

from fieldseg.functions.grid import GridSpec
from fieldseg.operators import kernels as k
from fieldseg.operators.critical import link_table


def test_spiral_ghost_pointers():
    """Ghost pointers of the worked example reach P in three rounds."""
    start = dict(zip("ABCDEFHIKLNO", "BCDFFIILLOOP"))
    rounds = [start]
    for _ in range(3):
        p = rounds[-1]
        rounds.append({a: p.get(b, b) for a, b in p.items()})
    want = ["BCDFFIILLOOP", "CDFIILLOOPPP", "FILOOPPPPPPP", "PPPPPPPPPPPP"]
    assert ["".join(r.values()) for r in rounds] == want
    ids, ptr = np.array([ord(c) for c in start]), np.array([ord(c) for c in start.values()])
    for in_place in (True, False):
        ends, n = k.double(ids, ptr, in_place)
        assert set(ends) == {ord("P")} and n <= 3


def test_chain_of_locals_needs_a_second_pass():
    ids = np.array([1, 2, 5, 9, 10])
    near = k.EdgeNeighbours(np.array([10, 1, 5, 2]), np.array([1, 5, 2, 9]))
    assert set(ids[k.local_components(ids, near)[0]]) == {10}
    assert len(set(ids[k.local_components(ids, near, 0)[0]])) > 1


@settings(max_examples=60, deadline=None)
@given(st.integers(2, 40), st.lists(st.tuples(st.integers(0, 39), st.integers(0, 39)), max_size=80), st.booleans())
def test_components_are_union_find(n, pairs, double):
    ids = np.arange(n) * 3
    pairs = [(a, b) for a, b in pairs if a < n and b < n]
    src, dst = (np.array([p[i] * 3 for p in pairs], np.int64) for i in (0, 1))
    near = k.EdgeNeighbours(src, dst)
    got = ids[k.local_components(ids, near)[0]]
    want = k.union_find(src, dst)
    assert got.tolist() == [want.get(i, i) for i in ids.tolist()]
    wave = k.breadth_first(ids, near)
    assert len(set(wave)) == len(set(got)) == len({(a, b) for a, b in zip(wave, got)})


@settings(max_examples=40, deadline=None)
@given(st.sampled_from([(12,), (5, 4), (3, 4, 3), (1, 6), (6, 1)]), st.integers(0, 10**6), st.sampled_from(["simplicial", "axis", "full"]), st.booleans())
def test_segmentation_is_the_naive_walk(dims, seed, connectivity, up):
    spec = GridSpec(dims, connectivity)
    f = np.random.default_rng(seed).integers(0, 6, spec.n)
    ids = np.arange(spec.n)
    rank = np.empty(spec.n, np.int64)
    rank[np.lexsort((ids, f))] = ids
    near = k.GridNeighbours(dims, spec.stencil())
    ptr = k.steepest_local(ids, rank, near, np.zeros(spec.n, bool), up)
    star = {int(i): {int(i)} for i in ids}
    for s, t in near(ids):
        for a, b in zip(s.tolist(), t.tolist()):
            star[a].add(b)
    best = max if up else min
    assert ptr.tolist() == [best(star[i], key=lambda v: rank[v]) for i in range(spec.n)]
    for in_place in (True, False):
        d = ptr.copy()
        k.compress_local(d, in_place)
        for i in range(spec.n):
            j = i
            while ptr[j] != j:
                j = ptr[j]
            assert d[i] == j


def test_link_tables():
    t = link_table(GridSpec((4, 4)))
    assert len(t) == 64 and t[63].tolist() == [63, 1, 0] and t[0].tolist() == [0, 0, 0]
    t = link_table(GridSpec((4, 4, 4)))
    assert len(t) == 16384 and t[-1].tolist() == [16383, 1, 2]
    assert (link_table(GridSpec((4,)))[:, 1] == [0, 1, 1, 2]).all()
