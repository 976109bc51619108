"""Predicates, covers, kernel and methods, in process."""

import itertools

import numpy as np
import pytest

from rangeann.functions.predicates import _ALLEN, ALL_MASKS, ALLEN, ORIENTATIONS, atomic_plan, atoms_of, plan
from rangeann.functions.tree import cover, height_of, levels_of, span
from rangeann.plans.kernel import OPEN, Counters, Edges, GrowingGraph, Scan, Shard, differing, grow, nearest_before, rng_prune, squared, static_graph, walk
from rangeann.plans.methods import METHODS, Domain, Exact, Oriented, SharedTree, VersionedTree, cover_bound, edge_bound, label_changes, level_edges, qualifies, seen_edges, snapshots, tree_edges

VALUES = range(1, 7)


def in_box(box, left, right, lq, rq):
    ends, of = {"lq": lq, "rq": rq}, {"l": left, "r": right}
    attribute, order, key = ORIENTATIONS[box.orient]
    ok = True
    if box.version:
        v, e = order * of[attribute], order * ends[box.version]
        ok &= v < e if box.version_strict else v <= e
    if box.low:
        ok &= of[key] > ends[box.low] if box.low_strict else of[key] >= ends[box.low]
    if box.high:
        ok &= of[key] < ends[box.high] if box.high_strict else of[key] <= ends[box.high]
    return ok and (not box.residual or left == lq)


def intervals():
    return [(a, b) for a in VALUES for b in VALUES if a <= b]


@pytest.mark.parametrize("mask", ALL_MASKS)
def test_plans_equal_their_masks(mask):
    for (left, right), (lq, rq) in itertools.product(intervals(), repeat=2):
        want = bool(qualifies(mask, np.array([left]), np.array([right]), lq, rq)[0])
        assert want == any(in_box(b, left, right, lq, rq) for b in plan(mask)) == any(in_box(b, left, right, lq, rq) for b in atomic_plan(mask))
    assert len(plan(mask)) <= 2 and len({b.orient for b in plan(mask)}) <= 2


def test_allen_boxes_part_all_pairs():
    define = {
        "before": lambda l, r, a, b: r < a, "meets": lambda l, r, a, b: r == a and l < a, "overlaps": lambda l, r, a, b: l < a < r < b, "finished_by": lambda l, r, a, b: l < a and r == b,
        "contains": lambda l, r, a, b: l < a and b < r, "starts": lambda l, r, a, b: l == a and r < b, "equals": lambda l, r, a, b: l == a and r == b, "started_by": lambda l, r, a, b: l == a and b < r,
        "during": lambda l, r, a, b: a < l and r < b, "finishes": lambda l, r, a, b: a < l and r == b, "overlapped_by": lambda l, r, a, b: a < l < b < r, "met_by": lambda l, r, a, b: l == b and b < r, "after": lambda l, r, a, b: l > b,
    }
    for (left, right), (lq, rq) in itertools.product([i for i in intervals() if i[0] < i[1]], repeat=2):
        hold = [n for n in ALLEN if define[n](left, right, lq, rq)]
        assert len(hold) == 1 and hold == [n for n in ALLEN if in_box(_ALLEN[n], left, right, lq, rq)]


@pytest.mark.parametrize("bad", [0, 16, "1", None])
def test_masks_are_checked(bad):
    with pytest.raises(ValueError):
        atoms_of(bad)


@pytest.mark.parametrize("height", range(7))
def test_covers_are_exact_disjoint_and_small(height):
    for low in range(1, (1 << height) + 1):
        for high in range(low, (1 << height) + 1):
            nodes = cover(low, high, height)
            ranks = [k for n in nodes for k in range(span(n, height)[0], span(n, height)[1] + 1)]
            assert sorted(ranks) == list(range(low, high + 1)) and len(nodes) <= max(1, 2 * height)
            assert (levels_of(np.array([low, high]), nodes, height) >= 0).all()
    assert cover(3, 2, height) == [] and height_of(1) == 0 and height_of(5) == 3 and cover_bound(1 << height) >= 1


def worked_example():
    """Four values; three objects begin at 1, three at 2, two at 3."""
    left, right = [1, 1, 1, 2, 2, 2, 3, 3], [1, 3, 4, 2, 4, 2, 3, 4]
    rng = np.random.default_rng(0)
    return Shard(np.arange(8), rng.standard_normal((8, 3)), np.array(left), np.array(right))


def test_worked_example_touches_the_path_of_r():
    s = worked_example()
    height = height_of(4)
    path = lambda r: [span((1 << j) | ((r - 1) >> (height - j)), height) for j in range(height + 1)]
    assert path(2) == [(1, 4), (1, 2), (2, 2)] and path(4) == [(1, 4), (3, 4), (4, 4)]
    domain = Domain(s, "LU", cuts=np.arange(1, 5))
    assert domain.height == 2 and [np.flatnonzero(domain.version == v).tolist() for v in (1, 2, 3)] == [[0, 1, 2], [3, 4, 5], [6, 7]] and domain.version_at(4, False) == 3
    tree = SharedTree(s, domain, 4, 10)
    made = {path: [v for v, _ in copies] for path, copies in tree.copies.items()}
    # nodes as (level, number): each version copies what its objects' paths touch and shares the rest
    assert made == {(0, 0): [1, 2, 3], (1, 0): [1, 2], (1, 1): [1, 2, 3], (2, 0): [1], (2, 1): [2], (2, 2): [1, 3], (2, 3): [1, 2, 3]}


def main_shard(n=120, seed=0, domain=40, dims=8):
    rng = np.random.default_rng(seed)
    left = rng.integers(0, domain, n)
    right = left + rng.integers(0, 12, n)
    return Shard(np.arange(n) * 3, rng.standard_normal((n, dims)), left, right)


@pytest.mark.parametrize("orient", ORIENTATIONS)
def test_labels_hold_every_prefix(orient):
    s = main_shard()
    whole_domain = Domain(s, orient)
    version = whole_domain.version
    whole = level_edges(s, whole_domain, 1, 5, 20, 0)
    for v in np.unique(version)[::4]:
        keep = np.flatnonzero(version <= v)
        part = s.take(keep)
        alone = level_edges(part, Domain(part, orient, cuts=whole_domain.cuts), 1, 5, 20, 0)
        alone = alone[alone[:, 4] == OPEN]
        seen = whole[(whole[:, 3] <= v) & (whole[:, 4] >= v)]
        assert set(map(tuple, seen[:, 1:3].tolist())) == {(int(keep[a]), int(keep[b])) for a, b in alone[:, 1:3]}
        assert np.bincount(seen[:, 1]).max(initial=0) <= 5


@pytest.mark.parametrize(("n", "dims", "prune"), [(90, 6, True), (90, 1, True), (60, 6, False), (400, 5, True)])
def test_replayed_events_are_single_insertions(n, dims, prune):
    rng = np.random.default_rng(n + dims)
    x, version = rng.standard_normal((n, dims)), np.sort(rng.integers(0, n // 3, n))
    g = GrowingGraph(x, 6, 25, prune=prune, scan=True)
    for r in range(n):
        g.insert(r, int(version[r]))
    got = grow(x, version, np.array([0, n]), 6, 25, prune)
    assert sorted(map(tuple, got.tolist())) == sorted(map(tuple, g.edges().tolist()))


def test_candidates_are_the_nearest_before():
    x = np.random.default_rng(0).standard_normal((700, 4))
    x[300:320] = x[5]  # ties
    for a, found, dist in nearest_before(x, 12, start=40, block=64, chunk=128):
        for i in range(len(found)):
            d = squared(x[: a + i], x[a + i])
            want = np.lexsort((np.arange(a + i), d))[:12]
            assert np.allclose(dist[i][: len(want)], d[want]) and (set(found[i].tolist()) == set(want.tolist()) or len(set(d[want].round(9))) < 12)


@pytest.mark.parametrize("cut", [0, 1, 40, 119])
def test_extended_graphs_are_those_of_one_build(cut):
    s = main_shard()
    order = np.lexsort((s.ids, s.left))
    s = Shard(s.ids[order], s.vectors[order], s.left[order], s.right[order], np.arange(len(s)))
    whole = Domain(s, "LU")
    for level in (0, 2, whole.height):
        want = level_edges(s, whole, level, 5, 20, 3)
        part = s.take(np.arange(cut))
        old = level_edges(part, Domain(part, "LU", cuts=whole.cuts), level, 5, 20, 3) if cut else np.zeros((0, 5), np.int64)
        got = level_edges(s, whole, level, 5, 20, 3, fresh=np.arange(len(s)) >= cut, old=old)
        assert sorted(map(tuple, got.tolist())) == sorted(map(tuple, want.tolist()))


def test_edges_respect_births_degrees_and_bounds():
    s = main_shard()
    domain = Domain(s, "LU")
    rows = tree_edges(s, domain, 6, 30, 0).rows()
    assert (rows[:, 3] >= np.maximum(domain.version[rows[:, 1]], domain.version[rows[:, 2]])).all() and (rows[:, 3] <= rows[:, 4]).all()
    assert len(rows) <= edge_bound(len(s), 6, domain.height)
    assert len(rows) < len(SharedTree(s, domain, 6, 30).rows()) < len(snapshots(s, "LU", 6, 30))
    again = Edges.unpacked(Edges.of(len(s), rows, domain.height + 1).packed())
    assert sorted(map(tuple, again.rows().tolist())) == sorted(map(tuple, rows.tolist()))
    parts = [rows[rows[:, 0] == j][:, 1:] for j in range(domain.height + 1)]
    merged = Edges.merged(len(s), [tuple(p[np.argsort(p[:, 0], kind="stable")].T) for p in parts])
    assert sorted(map(tuple, merged.rows().tolist())) == sorted(map(tuple, rows.tolist()))


def test_a_search_touches_little_of_a_large_set():
    work = {}
    for n in (1_000, 8_000):
        s = main_shard(n, domain=400, dims=6)
        domain = Domain(s, "LU")
        tree = Oriented(s, domain, tree_edges(s, domain, 12, 40, 16), 12)
        v = VersionedTree(orientations=()).build(s)
        v.orient = {"LU": tree}
        rng = np.random.default_rng(1)
        work[n] = np.mean([v.search(rng.standard_normal(6), lq, lq + 80, 15, 10, 30)[2].distances for lq in range(50, 300, 10)])
    assert work[8_000] < 2.5 * work[1_000] < 1_000


@pytest.mark.parametrize("low", [None, 3, 3.5, 400])
@pytest.mark.parametrize("high", [None, 17, 20.5, 1])
@pytest.mark.parametrize("buckets", [6, 4096])
def test_leaves_part_an_interval(low, high, buckets):
    s = main_shard()
    d = Domain(s, "LU", buckets)
    for strict in (False, True):
        first, last, cut = d.leaves(low, high, strict, strict)
        for leaf in range(1, len(d.cuts) + 1):
            keys = d.keys[d.leaf == leaf]
            fine = np.ones(len(keys), bool)
            if low is not None:
                fine &= keys > low if strict else keys >= low
            if high is not None:
                fine &= keys < high if strict else keys <= high
            assert fine.all() if first <= leaf <= last else leaf in cut or not fine.any()
        assert len(cut) <= 2


@pytest.mark.parametrize("variant", ["shared", "snapshot"])
def test_storage_variants_answer_alike(variant):
    s = main_shard(70)
    a, b = VersionedTree(6, 30, small=0).build(s), VersionedTree(6, 30, small=0, variant=variant, orientations=ORIENTATIONS).build(s)
    rng = np.random.default_rng(1)
    for mask in ALL_MASKS:
        q, lq = rng.standard_normal(8), int(rng.integers(0, 40))
        x, y = (t.search(q, lq, lq + 6, mask, 5, 12) for t in (a, b))
        assert x[0].tolist() == y[0].tolist() and x[1].tolist() == y[1].tolist() and x[2].unqualified == 0


def test_snapshots_of_large_sets_are_refused():
    with pytest.raises(ValueError):
        VersionedTree(variant="snapshot", snapshot_limit=100).build(main_shard())


@pytest.mark.parametrize("options", [{}, {"mode": "disjoint"}, {"exact_below": 10**6}, {"exact_below": 20}, {"buckets": 7}, {"graph": "static_rng"}, {"graph": "walked"}, {"levels": "hier"}, {"small": 0}])
def test_wide_searches_are_exact(options):
    s = main_shard(200)
    tree, truth = VersionedTree(8, 40, **options).build(s), Exact().build(s)
    rng = np.random.default_rng(2)
    for mask in ALL_MASKS:
        for lq, width in ((5, 0), (12, 7), (-5, 3), (60, 9), (7.5, 4.25)):
            q = rng.standard_normal(8)
            a, b = tree.search(q, lq, lq + width, mask, 10, 400), truth.search(q, lq, lq + width, mask, 10, 1)
            assert a[0].tolist() == b[0].tolist() and a[2].missed == 0 and a[2].unqualified == 0


def test_marks_widen_a_walk():
    s = main_shard(300)
    tree = VersionedTree(8, 40).build(s).orient["LU"]
    marks = s.ids % 15 == 0
    box = __import__("rangeann.functions.predicates", fromlist=["plan"]).plan(15)[0]
    for lq in (0, 10, 20):
        q = np.random.default_rng(lq).standard_normal(8)
        got, _ = tree.find(q, *tree.bounds(box, lq, lq + 15), 3, 3, residual=marks)
        rows = np.flatnonzero(qualifies(15, s.left, s.right, lq, lq + 15) & marks)
        want = sorted(zip(squared(s.vectors[rows], q).tolist(), rows.tolist(), strict=True))[:3]
        assert [r for _, r in got[:3]] == [r for _, r in want]


@pytest.mark.parametrize(("n", "domain", "dims"), [(1, 1, 1), (7, 1, 2), (30, 2, 1), (0, 1, 3)])
def test_tiny_and_uniform_sets(n, domain, dims):
    rng = np.random.default_rng(0)
    left = rng.integers(0, domain, n)
    s = Shard(np.arange(n), np.round(rng.standard_normal((n, dims))), left, left)
    for name in ("vtg", "post_filter", "tree_graph", "quad_graph", "segmented_store"):
        if n or name == "vtg":
            got = METHODS[name]().build(s).search(np.zeros(dims), 0, domain, 8, 50, 60)
            assert len(got[0]) == n


@pytest.mark.parametrize("name", [n for n in METHODS if n not in ("knn_ann", "pre_filter")])
def test_methods_reach_the_truth_and_refuse_other_masks(name):
    s = main_shard(300, domain=60)
    method = METHODS[name]
    if method.point_objects:
        s = Shard(s.ids, s.vectors, s.left, s.left)
    built, truth = method().build(s), Exact().build(s)
    rng, hit, total = np.random.default_rng(4), 0, 0
    for _ in range(12):
        q, lq = rng.standard_normal(8), int(rng.integers(5, 45))
        rq = lq if method.point_queries else lq + 12
        for mask in method.masks[-1:]:
            a, b = built.search(q, lq, rq, mask, 10, 150), truth.search(q, lq, rq, mask, 10, 1)
            fine = qualifies(mask, s.left, s.right, lq, rq)
            assert fine[a[0]].all() and (np.diff(a[1]) >= 0).all()
            hit, total = hit + len(set(a[0]) & set(b[0])), total + len(b[0])
    assert hit >= 0.9 * total and built.edge_count >= 0 and built.size >= 0
    if len(method.masks) < 15:
        with pytest.raises(ValueError):
            built.search(np.zeros(8), 1, 1, 1, 5, 5)
    if method.point_queries:
        with pytest.raises(ValueError):
            built.search(np.zeros(8), 1, 3, 2, 5, 5)
    if method.point_objects:
        with pytest.raises(ValueError):
            method().build(main_shard()).search(np.zeros(8), 1, 3, 8, 5, 5)


@pytest.mark.parametrize("name, options", [*((n, {}) for n in METHODS), ("vtg", {"mode": "disjoint"}), ("vtg", {"buckets": 16}), ("vtg", {"levels": "hier", "small": 4})])
def test_searches_together_are_searches_alone(name, options):
    s = main_shard(300, domain=60)
    if METHODS[name].point_objects:
        s = Shard(s.ids, s.vectors, s.left, s.left)
    built, rng = METHODS[name](m=6, ef_con=30, **options).build(s), np.random.default_rng(6)
    asked = [(rng.standard_normal(8), a, a if built.point_queries else a + b) for a, b in zip(rng.integers(-5, 65, 30).tolist(), rng.integers(0, 25, 30).tolist(), strict=True)]
    for mask in (built.masks[-1], *built.masks[:12:5]):
        for ef in (5, 40, 400):
            for (q, lq, rq), (rows, d, work) in zip(asked, built.search_many(asked, mask, 5, ef), strict=True):
                alone = built.search(q, lq, rq, mask, 5, ef)
                assert rows.tolist() == alone[0].tolist() and np.allclose(d, alone[1])
                if ef < 400:  # a full width: whether what fell out of it had been met as open is told apart by the order of one expansion
                    work.exhausted, work.missed = alone[2].exhausted, alone[2].missed
                assert work == alone[2]


def test_pruning_keeps_what_nothing_kept_shadows():
    v = np.array([[0.0, 0], [1, 0], [2, 0], [0, 1.5], [1.1, 0.1]])
    order = np.array([1, 4, 3, 2])
    assert rng_prune(v[0], order, squared(v[order], v[0]), v, 4).tolist() == [1, 3]
    assert rng_prune(v[0], order, squared(v[order], v[0]), v, 1).tolist() == [1]


@pytest.mark.parametrize("width, most", [(5, 3), (40, 4), (100, 16), (130, 200)])
def test_lists_pruned_together_are_lists_pruned_alone(width, most, monkeypatch):
    from rangeann.plans import kernel

    rng = np.random.default_rng(width)
    x = rng.standard_normal((300, 5))
    found, dist = np.full((40, width), -1), np.full((40, width), np.inf)
    for i in range(40):
        n = int(rng.integers(0, width + 1))
        rows = rng.choice(np.arange(40, 300), n, replace=False)
        order = np.argsort(squared(x[rows], x[i]))
        found[i, :n], dist[i, :n] = rows[order], squared(x[rows], x[i])[order]
    want = [rng_prune(x[i], found[i][found[i] >= 0], dist[i][found[i] >= 0], x, most).tolist() for i in range(40)]
    grown = GrowingGraph(x, most, 50)
    full = [i for i in range(40) if (found[i] >= 0).any()]
    assert grown.pruned_each(full, [rng.permutation(found[i][found[i] >= 0]).tolist() for i in full]) == [want[i] for i in full]
    for places in (7, 32, 64):
        monkeypatch.setattr(kernel, "PLACES", places)
        keep = kernel.kept_of(x, found, dist, most, True)
        assert [f[k].tolist() for f, k in zip(found, keep, strict=True)] == want


def test_members_are_sought_once_for_equal_intervals(monkeypatch):
    from rangeann.operators import index as ix

    s, calls = main_shard(300, domain=60), []
    tree = VersionedTree(m=6, ef_con=30, orientations=("LU",)).build(s).orient["LU"]
    alive, bounds = Oriented.alive, Oriented.bounds
    monkeypatch.setattr(Oriented, "alive", lambda *a: calls.append("alive") or alive(*a))
    monkeypatch.setattr(Oriented, "bounds", lambda *a: calls.append("bounds") or bounds(*a))
    row = {f"{c}_{n}": f(x) for c, x in (("l", s.left), ("r", s.right)) for n, f in (("min", np.min), ("max", np.max))}
    q = np.random.default_rng(2).standard_normal((40, 8))
    one = ix.together(row, s, {"LU": tree}, plan(15), [(0, q[0], 10, 30)], 5, 40, "layered")
    few, calls[:] = len(calls), []
    found = ix.together(row, s, {"LU": tree}, plan(15), [(i, v, 10, 30) for i, v in enumerate(q)], 5, 40, "layered")
    assert len(calls) == few and [r[:3] for r in found if r[0] == 0] == [r[:3] for r in one]


def test_segments_cells_and_lists_take_queries_together(monkeypatch):
    """No single walks: many queries are one call."""
    from rangeann.plans import kernel, methods

    s, rng = main_shard(300, domain=60), np.random.default_rng(6)
    asked = [(rng.standard_normal(8), a, a + 20) for a in range(0, 40, 4)]
    for name in ("segmented_store", "quad_graph"):
        built = METHODS[name](m=6, ef_con=30).build(s)
        with monkeypatch.context() as m:
            m.setattr(methods, "walk", None)
            built.search_many(asked, 8, 5, 20)
    with monkeypatch.context() as m:
        m.setattr(kernel, "rng_prune", lambda *a, f=kernel.rng_prune: calls.append(1) or f(*a))
        calls: list[int] = []
        METHODS["stab_graph"](m=6, ef_con=30).build(s)
    assert len(calls) < len(s)  # one an insertion, none a removal


def test_static_graph_and_walk_find_the_nearest():
    s = main_shard(150)
    e = static_graph(s.vectors, np.arange(150), 8, 40)
    near = {u: e[e[:, 0] == u][:, 1].tolist() for u in range(150)}
    q = s.vectors[7] + 0.01
    best = walk(q, s.vectors, [0], lambda u: near[u], 60, Counters())
    assert best[0][1] == 7 and len(best) == 60 and walk(q, s.vectors, [], lambda u: near[u], 5, Counters()) == []


def test_removed_vertices_leave_the_walk():
    s = main_shard(40)
    g = GrowingGraph(s.vectors, 6, 20)
    for r in range(40):
        g.insert(r, 1)
    g.remove(5, 3)
    e = g.edges()
    at = lambda v: e[(e[:, 2] <= v) & (e[:, 3] >= v)]
    assert 5 in at(2)[:, 0] and 5 not in at(3)[:, 0] and 5 not in at(3)[:, 1]


@pytest.mark.parametrize("residual", [None, 3])
def test_a_check_finds_what_a_walk_cannot_reach(residual):
    rng = np.random.default_rng(7)
    s = Shard(np.arange(300), rng.integers(-3, 4, (300, 4)).astype(float), rng.integers(0, 40, 300), rng.integers(40, 90, 300))
    d = Domain(s, "LU")
    bare = Oriented(s, d, Edges.of(300, np.zeros((0, 5), np.int64), d.height + 1), 8, 4)
    marks = None if residual is None else s.ids % residual == 0
    missing = 0
    for box in plan(2):
        for lq, rq in ((10, 50), (39, 41), (0, 89)):
            q = rng.integers(-3, 4, 4).astype(float)
            fine = (s.left <= lq) & (rq <= s.right) & (True if marks is None else marks)
            want = sorted((float(x), int(i)) for x, i in zip(((s.vectors - q) ** 2).sum(axis=1)[fine], s.ids[fine], strict=True))[:10]
            walked, checked = (sorted(bare.find(q, *bare.bounds(box, lq, rq), 10, 20, residual=marks, check=c)[0])[:10] for c in (False, True))
            assert checked == want
            missing += walked != want
    assert missing


def test_counts_over_edges_are_those_of_single_versions():
    rng = np.random.default_rng(3)
    rows = np.column_stack([rng.integers(0, 3, 400), rng.integers(0, 9, 400), rng.integers(0, 9, 400), rng.integers(1, 9, 400), rng.integers(9, 15, 400)])
    e = Edges.of(9, rows, 3)
    of = {(j, u): rows[(rows[:, 0] == j) & (rows[:, 1] == u)] for j in range(3) for u in range(9)}
    for most in (4, 12, 100):
        assert e.crowded(most) == sum(((own[:, 3] <= v) & (own[:, 4] >= v)).sum() > most for own in of.values() for v in set(own[:, 3].tolist()))
    assert np.array_equal(np.concatenate(list(e.parts(7))), e.rows())


def test_memory_of_a_shard_is_bounded(monkeypatch):
    """A shard of full size takes little beside what a worker holds anyway, and smaller blocks of lists give the same edges."""
    import tracemalloc

    from rangeann.operators.index import SHARD_ROWS
    from rangeann.plans import kernel

    rng = np.random.default_rng(5)
    left = rng.integers(0, 50, SHARD_ROWS)
    s = Shard(np.arange(SHARD_ROWS), rng.normal(size=(SHARD_ROWS, 64)), left, left + rng.integers(0, 97, SHARD_ROWS))
    d = Domain(s, "LU")
    tracemalloc.start()
    edges = level_edges(s, d, 0, 16, 100)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 64 << 20
    monkeypatch.setattr(kernel, "CANDIDATES", 10**6)
    assert (level_edges(s, d, 0, 16, 100) == edges).all()


@pytest.mark.parametrize(("n", "different", "dims"), [(400, 8, 5), (300, 150, 16), (600, 20, 64)])
def test_copies_of_vectors_are_linked_alike_by_both_builders(n, different, dims):
    rng = np.random.default_rng(n)
    x = rng.standard_normal((different, dims)).astype(np.float32).astype(float)[rng.integers(0, different, n)]
    version = np.arange(n) // 3
    g, at_once = (GrowingGraph(x, 6, 25, scan=True) for _ in range(2))
    for r, near in enumerate(at_once.scans(np.arange(n), block=64)):
        g.insert(r, int(version[r]))
        at_once.insert_each([r], [int(version[r])], [near])
    want = sorted(map(tuple, g.edges().tolist()))
    assert sorted(map(tuple, at_once.edges().tolist())) == sorted(map(tuple, grow(x, version, np.array([0, n]), 6, 25).tolist())) == want


@pytest.mark.parametrize(("most_exact", "block"), [(8192, 64), (0, 100)])
def test_nearest_rows_are_by_distance_and_row(monkeypatch, most_exact, block):
    from rangeann.plans import kernel

    monkeypatch.setattr(kernel, "EXACT_ROWS", most_exact)  # 0: sought in single precision
    rng = np.random.default_rng(1)
    x = rng.standard_normal((500, 8)).astype(np.float32).astype(float)
    x[rng.permutation(500)[:200]] = x[7]
    x[100:130] = x[5] + 1e-7 * rng.standard_normal((30, 8))
    want = [np.lexsort((np.arange(i), squared(x[:i], x[i])))[:12].tolist() for i in range(500)]
    assert [[r for r in f if r >= 0] for _, found, _ in nearest_before(x, 12, block=block, chunk=128) for f in found.tolist()] == want
    scan = Scan(x, 12)
    assert [c.tolist() for a in range(0, 500, block) for c in scan.block(a, min(500, a + block), chunk=128)] == want


def test_differing_counts_pairs_of_each_version():
    rng = np.random.default_rng(3)
    spans = [rng.integers(1, 15, (40, 4)) for _ in range(2)]
    for e in spans:
        e[:, :2] %= 4
    e[:5, 3] = OPEN
    rows = [np.column_stack([np.zeros(40, int), e]) for e in spans]
    want = sum(len(set.symmetric_difference(*({(s, t) for _, s, t, b, e in r.tolist() if b <= v <= e} for r in rows))) for v in range(1, 13))
    changes = [label_changes(r, 4, 12) for r in rows]
    assert differing(*changes) == want > 0 == differing(changes[0], changes[0])


@pytest.mark.parametrize("level", [0, 2, 5])
def test_lists_are_seen_as_single_insertions_leave_them(monkeypatch, level):
    """Rounds over all nodes, candidates in blocks; what is stated too much or too little counts at all versions it is so."""
    s = main_shard(300, domain=60)
    domain = Domain(s, "LU")
    node, last = domain.node(level), len(domain.versions)
    rows = level_edges(s, domain, level, 5, 20, 0)
    live = [set() for _ in range(last + 1)]
    for k in np.unique(node).tolist():
        g, members = GrowingGraph(s.vectors, 5, 20, scan=True), np.flatnonzero(node == k)
        for v in range(1, last + 1):
            for r in members[domain.version[members] == v][np.argsort(s.ids[members[domain.version[members] == v]])].tolist():
                g.insert(r, v)
            live[v] |= set(g.live())
    calls = []
    with monkeypatch.context() as m:
        m.setattr(GrowingGraph, "candidates", None)  # no scan an insertion
        m.setattr(GrowingGraph, "trim", lambda self, *a, f=GrowingGraph.trim: calls.append(1) or f(self, *a))
        seen = seen_edges(s, domain, level, 5, 20)
    assert len(calls) == np.bincount(node).max()
    for given in (rows, rows[::3], np.concatenate([rows, [[level, 0, 1, 2, OPEN]]]), np.concatenate([rows[:-9], rows[-9:] + [0, 0, 0, 1, 0]])):
        want = sum(len(live[v] ^ {(a, b) for _, a, b, p, q in given.tolist() if p <= v <= q}) for v in range(1, last + 1))
        assert differing(label_changes(given, len(s), last), seen) == want
    assert differing(label_changes(rows, len(s), last), seen) == 0
