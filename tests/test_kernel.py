import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from orthant import kernel as K

RNG = np.random.default_rng(7)
CLOUDS = {
    "random": RNG.normal(size=(700, 3)),
    "clustered": np.concatenate([RNG.normal(c, 0.01, (200, 3)) for c in (0, 5, 50)]),
    "spots": RNG.integers(0, 4, (600, 3)).astype(float),
    "line": np.outer(np.arange(300.0), [1, 2, 3]),
    "constant": np.ones((90, 3)),
    "one_dim": RNG.exponential(size=(400, 1)),
    "few": RNG.normal(size=(3, 3)),
    "none": np.zeros((0, 3)),
    "huge": RNG.normal(size=(300, 10)) * 1e150,
    "tiny": RNG.normal(size=(300, 2)) * 1e-150,
}
POLICIES = [K.SplitPolicy(), K.SplitPolicy.vfm(), K.SplitPolicy.brm(), K.SplitPolicy("cycle", "exact"), K.SplitPolicy("variance_full", "hist", local_sample=64)]


@pytest.mark.parametrize("cloud", CLOUDS)
@pytest.mark.parametrize("policy", POLICIES, ids=lambda p: f"{p.dim_rule}-{p.value_rule}")
@pytest.mark.parametrize("bucket", [1, 8, 32, 256])
def test_search_equals_brute_force(cloud, policy, bucket):
    x = CLOUDS[cloud]
    ids = RNG.permutation(len(x)).astype(np.int64)
    q = np.concatenate([x[:40], x[:20] + 0.3, np.full((1, x.shape[1]), 1e3)])
    for k in (1, 5):
        want = K.brute(x, ids, q, k)
        for order in ("near_first", "far_first"):
            got = K.search(K.build(x, ids, bucket, policy), q, k, order=order)
            assert (got.d2 == want[0]).all() and (got.ids == want[1]).all()


@pytest.mark.parametrize("regions", [True, False])
def test_one_query_by_the_stack(regions):
    for x in CLOUDS.values():
        ids = np.arange(len(x))
        tree = K.build(x, ids, 8)
        for q in np.concatenate([x[:10], x[:10] * 1.5 + 2]):
            d2, found = K.brute(x, ids, q[None], 4)
            want = [(float(a), int(b)) for a, b in zip(d2[0], found[0]) if b != K.NO_ID]
            assert K.search_one(tree, q, 4, regions=regions)[0] == want if len(x) else True


def test_radius_and_own_id():
    x = CLOUDS["random"]
    ids = np.arange(len(x))
    tree = K.build(x, ids)
    want = K.brute(x, ids, x, 5, 0.05, ids)
    got = K.search(tree, x, 5, 0.05, ids)
    assert (got.ids == want[1]).all() and (got.d2 == want[0]).all()
    assert (K.search(tree, np.full((1, 3), 99.0), 5, 1.0).ids == K.NO_ID).all()


def test_replacement_keeps_the_kth_distance():
    x = np.array([[1.0], [5.0], [9.0], [2.0], [3.0]])
    assert [p[0] for p in K.search_one(K.build(x, np.arange(5), 8), np.zeros(1), 3)[0]] == [1, 4, 9]


def test_a_dimension_crossed_twice():
    x = np.array([[0.0, 22.0], [15.0, 30.0], [21.0, 0.0]])
    n = np.array
    tree = K.Tree(x, n([0, 1, 2]), n([0, -1, 0, -1, -1]), n([10.0, 0, 20.0, 0, 0]), n([1, -1, 3, -1, -1]), n([2, -1, 4, -1, -1]), n([0, 0, 1, 1, 2]), n([3, 1, 3, 2, 3]), n([x.min(0), x[0], x[1:].min(0), x[1], x[2]]), n([x.max(0), x[0], x[1:].max(0), x[1], x[2]]), n([0, 1, 1, 2, 2]))
    assert K.search_one(tree, np.zeros(2), 1)[0] == [(441.0, 2)]
    assert K.search(tree, np.zeros((1, 2)), 1).ids[0, 0] == 2


def test_five_cells_by_hand():
    pts = {1: (1, 1), 2: (2, 3), 3: (1, 4), 4: (4, 1), 5: (5, 2), 6: (4, 4), 7: (1, 6), 8: (3, 7), 9: (5, 5.5), 10: (7, 1), 11: (6.5, 3.5), 12: (9, 2), 13: (7, 7), 14: (8, 9), 15: (9.5, 6)}
    x, ids = np.array(list(pts.values()), dtype=float), np.array(list(pts))
    got = K.search(K.build(x, ids, 3), np.array([[4.5, 1.5], [5.5, 4.25]]), 3)
    assert got.ids.tolist() == [[4, 5, 6], [11, 9, 6]]
    assert got.d2.tolist() == [[0.5, 0.5, 6.5], [1.5625, 1.8125, 2.3125]]


@settings(max_examples=60, deadline=None)
@given(st.lists(st.floats(-1e6, 1e6), min_size=1, max_size=200), st.lists(st.floats(-1e6, 1e6), min_size=1, max_size=50), st.integers(1, 40))
def test_both_bin_lookups_agree(edges, values, stride):
    e, v = np.unique(edges), np.array(values + edges)
    assert (K.bin_two_level(v, e, stride) == K.bin_binary(v, e)).all()


def test_bins_at_the_edges():
    e, v = np.arange(100.0), np.array([-1, 0, 31.5, 32, 99, 100])
    assert K.bin_two_level(v, e).tolist() == K.bin_binary(v, e).tolist() == [0, 1, 32, 33, 100, 100]
    assert K.histogram(v, e).sum() == len(v)


def test_tree_is_a_partition_and_balanced():
    x = CLOUDS["random"]
    tree = K.build(x, np.arange(len(x)), 32)
    leaves = tree.leaves
    assert (tree.end - tree.start)[leaves].sum() == len(x) and (tree.end - tree.start)[leaves].max() <= 32
    for f in leaves:
        own = tree.points[tree.start[f] : tree.end[f]]
        assert (own >= tree.lo[f]).all() and (own <= tree.hi[f]).all()
    assert tree.depth.max() <= 7


def test_prefix_and_translation():
    x = np.round(CLOUDS["random"] * 64) / 64
    ids = np.arange(len(x))
    a, b = K.search(K.build(x, ids), x[:50], 6), K.search(K.build(x + 8, ids), x[:50] + 8, 5)
    assert (a.ids[:, :5] == b.ids).all() and (a.d2[:, :5] == b.d2).all()


def test_median_edge_equals_the_histogram_rule():
    for _ in range(300):
        v = RNG.integers(0, RNG.integers(1, 12), RNG.integers(1, 30)).astype(float)
        below = {e: 2 * (v < e).sum() for e in np.unique(v)[1:]}
        want = min(below, key=lambda e: (abs(below[e] - len(v)), e)) if below else None
        assert K.median_edge(np.sort(v)) == want


def test_metrics_by_brute_force():
    x, q = RNG.normal(size=(500, 3)), RNG.normal(size=(20, 3))
    ids = RNG.permutation(500).astype(np.int64)
    plain = {"l1": np.abs(x[None] - q[:, None]).sum(axis=2), "linf": np.abs(x[None] - q[:, None]).max(axis=2)}
    for metric, d in plain.items():
        found = K.search(K.build(x, ids, 16), q, 4, metric=metric)
        assert np.allclose(found.d2, np.sort(d, axis=1)[:, :4]) and (found.ids == K.brute(x, ids, q, 4, metric=metric)[1]).all()


@pytest.mark.parametrize("dims", [1, 3, 15])
@pytest.mark.parametrize("shift", [0.0, 1e7])
def test_exhaustive_search_measures_what_rounding_leaves_open(dims, shift):
    """Far from the origin, among copies and ties: the same ids and distances as by measuring every pair."""
    rng = np.random.default_rng(dims)
    x = np.concatenate([rng.normal(size=(3000, dims)), np.full((300, dims), 0.25), rng.integers(0, 2, (3000, dims))]) + shift
    ids = rng.permutation(len(x)).astype(np.int64)
    q = np.concatenate([x[::37], rng.normal(size=(20, dims)) + shift])
    own = np.concatenate([ids[::37], np.full(20, -1)])
    for r2, mine in ((np.inf, None), (1.5, None), (np.inf, own)):
        d2, found = K.brute(x, ids, q, 7, r2, mine)
        every = K.distance(x[None, :, :], q[:, None, :])
        every = np.where((every > r2) | ((ids[None, :] == mine[:, None]) if mine is not None else False), np.inf, every)
        want = K.top_k(every, np.where(np.isinf(every), K.NO_ID, ids[None, :]), 7)
        assert (d2 == want[0]).all() and (found == want[1]).all()


def test_one_bucket_and_farthest_first_take_bounded_memory():
    """A step's arrays don't grow with the bucket, nor with queries times boxes."""
    import tracemalloc

    rng = np.random.default_rng(3)
    x, ids = rng.normal(size=(60_000, 3)), np.arange(60_000)
    q = x[:2048] + 0.01
    want = K.brute(x, ids, q, 5)
    for bucket, order in ((60_000, "near_first"), (32, "far_first")):
        tree = K.build(x, ids, bucket)
        tracemalloc.start()
        found = K.search(tree, q, 5, order=order)
        assert tracemalloc.get_traced_memory()[1] < 64 << 20
        tracemalloc.stop()
        assert (found.d2 == want[0]).all() and (found.ids == want[1]).all()


@pytest.mark.parametrize(("scale", "spread"), [(1e-30, 0.2), (1.0, 0.2), (1e30, 0.2), (1e120, 0.2), (1e-160, 1e-4), (1.0, 1e-4)])
def test_exhaustive_search_looks_over_most_pairs_in_single_precision(monkeypatch, scale, spread):
    """Few pairs are left to double precision, also where the points come in pieces; the answers are those of measuring all."""
    rng, left, make = np.random.default_rng(8), [], K._block_product
    x = np.concatenate([rng.normal(size=(16_000, 3)), 3 + spread * rng.normal(size=(4000, 3))])[rng.permutation(20_000)] * scale
    ids, q = rng.permutation(len(x)).astype(np.int64), x[::80] * (1 + 1e-7)
    monkeypatch.setattr(K, "_block_product", lambda x, ids: lambda q, *a, one=make(x, ids): left.append(len(q) * len(x)) or one(q, *a))
    for r2, own in ((np.inf, None), (0.02 * scale**2, None), (np.inf, ids[::80])):
        d2, found = K.brute(x, ids, q, 5, r2, own)
        assert sum(left) < 0.2 * len(x) * len(q) or spread < 0.1
        left.clear()
        every = K.distance(x[None, :, :], q[:, None, :])
        every = np.where((every > r2) | ((ids[None, :] == own[:, None]) if own is not None else False), np.inf, every)
        want = K.top_k(every, np.where(np.isinf(every), K.NO_ID, ids[None, :]), 5)
        assert (d2 == want[0]).all() and (found == want[1]).all()
        best = K.Nearest(q, 5, r2, own)
        for i in (0, 3, 1000, 1001, 9000):
            to = {0: 3, 3: 1000, 1000: 1001, 1001: 9000, 9000: len(x)}[i]
            best.meet(x[i:to], ids[i:to])
        left.clear()
        assert all((a == b).all() for a, b in zip(best.answers(), want, strict=True))
