"""The shard graph: structure, a slow twin, exact limits, order and options."""

import heapq

import numpy as np
import pytest
from hypothesis import given, settings, strategies as st

from rangevec.operators.competitors import METHODS, Codebook, Shard, common_edges, kmeans
from rangevec.operators.kernel import DIST, EDGES, HOPS, Graph, Params, build, estimated, histogram
from rangevec.operators.multiattr import zcover
from rangevec.sources.durable import open_arrays, store_arrays


def data(n=240, d=8, seed=0, clusters=0):
    rng = np.random.default_rng(seed)
    x = rng.normal(size=(n, d))
    if clusters:
        x = rng.normal(size=(clusters, d))[rng.integers(0, clusters, n)] + 0.2 * x
    attr = rng.permutation(n).astype(float)
    level = np.minimum(rng.geometric(0.75, n) - 1, 4)
    return x, attr, np.arange(n), level


def graph(n=240, segments=4, seed=0, **p):
    x, attr, vid, level = data(n, seed=seed)
    seg = (attr * segments // n).astype(int)
    return build(x, attr, vid, seg, level, segments, Params(**{"m": 8, "ef_cons": 40, **p}))


def brute(g, q, lo, hi, k):
    ids = np.flatnonzero((g.attr >= lo) & (g.attr <= hi))
    d = np.linalg.norm(g.x[ids] - q, axis=1)
    return [int(ids[i]) for i in np.lexsort([ids, d])[:k]]


class Twin:
    """The method written out with dictionaries and heaps, one candidate at a time, for comparison."""

    def __init__(self, x, attr, seg, level, segments, m, ef):
        self.x, self.attr, self.seg, self.level, self.s, self.m, self.ef = x, attr, seg, level, segments, m, ef
        self.near, self.mask, self.entry, self.hops = {}, {}, {}, 0
        for v in range(len(x)):
            self.add(v)

    def d(self, a, b):
        return float(np.sqrt(((a - b) ** 2).sum()))

    def prune(self, v, ids, m):
        kept = []
        for o in sorted(ids, key=lambda o: (self.d(self.x[v], self.x[o]), o)):
            if len(kept) < m and all(self.d(self.x[e], self.x[o]) >= self.d(self.x[v], self.x[o]) for e in kept):
                kept.append(o)
        return kept

    def search(self, q, start, width, neighbours, ok=lambda v: True):
        cand, seen, best = [(self.d(q, self.x[start]), start)], {start}, []
        if ok(start):
            best.append(cand[0])
        while cand:
            d, o = heapq.heappop(cand)
            if len(best) >= width and d > max(best)[0]:
                break
            self.hops += 1
            for v in neighbours(o):
                if v not in seen:
                    seen.add(v)
                    heapq.heappush(cand, (self.d(q, self.x[v]), v))
                    if ok(v):
                        best = sorted([*best, (self.d(q, self.x[v]), v)])[:width]
        return [v for _, v in sorted(best)]

    def add(self, v):
        i, top = self.seg[v], self.level[v]
        for layer in range(top + 1):
            self.near[layer, v], self.mask[layer, v] = [[] for _ in range(self.s)], set()
        for j in range(self.s):
            if j not in self.entry:
                continue
            ep = self.entry[j]
            for layer in range(self.level[ep], -1, -1):
                found = self.search(self.x[v], ep, self.ef if layer <= top else 1, lambda o: self.near[layer, o][j])  # noqa: B023
                ep = found[0]
                if layer <= top:
                    for o in self.prune(v, found, self.m):
                        self.near[layer, v][j].append(o)
                        back = self.near[layer, o][i]
                        back.append(v)
                        self.near[layer, o][i] = self.prune(o, back, self.m) if len(back) > self.m else sorted(back, key=lambda w: self.d(self.x[o], self.x[w]))  # noqa: B023
                        self.mask[layer, o] &= {w for c in self.near[layer, o] for w in c}
        if i not in self.entry or top > self.level[self.entry[i]]:
            self.entry[i] = v
        for layer in range(top + 1):
            own = lambda o: [w for c in self.near[layer, o] for w in c]  # noqa: B023, E731
            self.mask[layer, v] = set(self.prune(v, own(v), self.m))
            for o in list(self.mask[layer, v]):
                if v in own(o):
                    self.mask[layer, o].add(v)
                    if len(self.mask[layer, o]) > self.m:
                        self.mask[layer, o] = set(self.prune(o, own(o), self.m))

    def start(self, segs):
        return max((self.entry[j] for j in segs if j in self.entry), key=lambda v: (self.level[v], -self.seg[v]))

    def layered(self, q, ep, width, neighbours, ok):
        for layer in range(self.level[ep], 0, -1):
            ep = self.search(q, ep, 1, lambda o: neighbours(layer, o))[0]  # noqa: B023
        return self.search(q, ep, width, lambda o: neighbours(0, o), ok)

    def post(self, q, lo, hi, k, ef):
        return [v for v in self.layered(q, self.start(range(self.s)), ef, lambda layer, o: self.mask[layer, o], lambda v: True) if lo <= self.attr[v] <= hi][:k]

    def hybrid(self, q, lo, hi, k, ef, segs, m):
        share = -(-m // len(segs))
        return self.layered(q, self.start(segs), ef, lambda layer, o: [v for j in segs for v in self.near[layer, o][j][:share]], lambda v: lo <= self.attr[v] <= hi)[:k]


@pytest.mark.parametrize("segments", [1, 3])
def test_the_slow_twin_agrees(segments):
    """Insertion with one candidate at a time gives the twin's edges and masks, and both graph searches its results."""
    x, attr, vid, level = data(150, 6, seed=5)
    seg = (attr * segments // 150).astype(int)
    g = build(x, attr, vid, seg, level, segments, Params(m=5, ef_cons=20, wave=1))
    t = Twin(x, attr, seg, level, segments, 5, 20)
    for layer, one in enumerate(g.layers):
        for r, v in enumerate(one.node.tolist()):
            assert [c[c >= 0].tolist() for c in one.ids[r]] == t.near[layer, v], (layer, v)
            assert set(one.ids[r][one.mask[r]].tolist()) == t.mask[layer, v], (layer, v)
    assert {j: int(e) for j, e in enumerate(g.entry)} == t.entry
    rng = np.random.default_rng(1)
    for _ in range(25):
        q, (lo, hi) = rng.normal(size=6), sorted(rng.integers(0, 150, 2))
        segs = list(range(int(lo * segments // 150), int(hi * segments // 150) + 1))
        assert [v for _, v in g.post(q, lo, hi, 5, 15)] == t.post(q, lo, hi, 5, 15)
        t.hops = 0
        assert [v for _, v in g.hybrid(q, lo, hi, 5, 15, segs, 9)] == t.hybrid(q, lo, hi, 5, 15, segs, 9)
        assert int(g.spent[0, HOPS]) == t.hops


def test_waves_find_as_much():
    """Expanding several candidates at once sees at least what one at a time does."""
    x, attr, vid, level = data(400)
    zero = np.zeros(400, int)
    g = build(x, attr, vid, zero, zero, 1, Params(m=8, ef_cons=40))
    rng = np.random.default_rng(6)
    q, start = rng.normal(size=(30, 8)), np.zeros(30, np.int64)
    first = np.linalg.norm(x[0] - q, axis=1)
    one, many = (g.spread(q, start, first, 40, g.chunks(0, np.zeros(30, np.int64)), wave=w)[0] for w in (1, 8))
    assert (many <= one + 1e-12).all()


@pytest.mark.parametrize("p", [{}, {"candidates": "exact"}, {"base_degree": 16}, {"mask_degree": 16}, {"entry": "last"}, {"wave": 1}])
@pytest.mark.parametrize("segments", [1, 4])
def test_structure(p, segments):
    assert graph(segments=segments, **p).problems() == []


def test_repeated_vectors_and_ties():
    x = np.repeat(np.eye(6), 20, axis=0)
    attr = np.tile([0.0, 1.0, 2.0, 3.0], 30)
    g = build(x, attr, np.arange(120), attr.astype(int), np.zeros(120, int), 4, Params(m=4, ef_cons=30))
    assert g.problems() == [] and [v for _, v in g.pre(x[0], 0, 3, 20)] == list(range(20))


def test_storage_and_growth(tmp_path):
    """Arrays come back as they were, and growing a stored graph equals building at once."""
    x, attr, vid, level = data(200)
    seg, p = (attr * 4 // 200).astype(int), Params(m=6, ef_cons=30)
    whole = build(x, attr, vid, seg, level, 4, p)
    half = build(x[:120], attr[:120], vid[:120], seg[:120], level[:120], 4, p)
    stored = Graph.of_arrays(open_arrays(store_arrays(f"file://{tmp_path}", "g", half.arrays())), 4, p)
    grown = stored.grown(x[120:], attr[120:], vid[120:], seg[120:], level[120:])
    for v in range(120, 200):
        grown.insert(v)
    assert len(whole.layers) == len(grown.layers) and all((a.ids == b.ids).all() and (a.mask == b.mask).all() and (a.next == b.next).all() and a.head == b.head for a, b in zip(whole.layers, grown.layers, strict=True))
    assert (whole.entry == grown.entry).all() and grown.problems() == []


def test_the_chain_is_navigated():
    """Few steps lead to the first object of a range, which is the first one at or above its lower bound."""
    x, attr, vid, _ = data(2000, 2)
    level = np.minimum(np.random.default_rng(3).geometric(0.75, 2000) - 1, 6)
    g = build(x, attr, vid, np.zeros(2000, int), level, 1, Params(m=4, ef_cons=4))
    steps = []
    for lo in np.random.default_rng(4).uniform(-1, 2001, 100):
        first, n = g.first_from(lo)
        above = attr[attr >= lo]
        assert first == (int(vid[attr == above.min()][0]) if len(above) else None)
        steps.append(n)
    assert np.mean(steps) < 60
    assert g.chain() == list(np.lexsort([vid, attr]))


def test_estimates():
    rng = np.random.default_rng(0)
    attr = rng.uniform(0, 100, 1200)
    lo = rng.uniform(-10, 90, 60)
    hi = lo + rng.uniform(0, 60, 60)
    want = np.array([((attr >= a) & (attr <= b)).sum() for a, b in zip(lo, hi, strict=True)])
    assert np.abs(estimated(histogram(attr), lo, hi) - want).max() <= 2 * 1200 / 64 + 2
    ties = np.concatenate([attr, np.full(300, 50.0)])
    whole = estimated(histogram(ties), np.array([-1.0, 20.0]), np.array([101.0, 80.0]))
    assert whole[0] == 1500 and abs(whole[1] - ((ties >= 20) & (ties <= 80)).sum()) <= 60
    assert histogram(attr)[:, 2].sum() == 1200 and estimated(histogram(np.zeros(0)), lo, hi).max() == 0


def test_full_settings_are_exact():
    g = graph(120, m=130, ef_cons=200, mask_degree=400)
    rng = np.random.default_rng(9)
    for _ in range(25):
        q, (lo, hi) = rng.normal(size=8), sorted(rng.integers(0, 120, 2))
        segs = sorted(set(range(int(lo * 4 // 120), int(hi * 4 // 120) + 1)))
        want = brute(g, q, lo, hi, 10)
        assert [v for _, v in g.pre(q, lo, hi, 10)] == want
        assert [v for _, v in g.hybrid(q, lo, hi, 10, 200, segs, 600)] == want
        assert [v for _, v in g.post(q, lo, hi, 10, 200)] == want


def test_side_by_side_is_one_by_one():
    """Searching queries together changes neither results nor what each of them takes."""
    g = graph(500)
    rng = np.random.default_rng(8)
    q, lo = rng.normal(size=(40, 8)), rng.integers(0, 300, 40).astype(float)
    hi = lo + rng.integers(0, 200, 40)
    hit = (np.arange(4) >= (lo * 4 // 500)[:, None]) & (np.arange(4) <= (hi * 4 // 500)[:, None])
    for pick in ("chunk", "distance"):
        together, spent = g.hybrid_many(q, lo, hi, 5, 30, hit, 12, pick), g.spent
        for i in range(40):
            assert g.hybrid_many(q[i : i + 1], lo[i : i + 1], hi[i : i + 1], 5, 30, hit[i : i + 1], 12, pick)[0] == together[i] and (g.spent[0] == spent[i]).all()
    together, spent = g.post_many(q, lo, hi, 5, 30, True), g.spent
    for i in range(40):
        assert g.post(q[i], lo[i], hi[i], 5, 30, True) == together[i] and (g.spent[0] == spent[i]).all()
    assert (spent[:, EDGES] >= spent[:, DIST] - 20).all()


@pytest.mark.parametrize("how", ["pre", "post", "hybrid"])
def test_results_are_in_range_sorted_and_few(how):
    g = graph()
    rng = np.random.default_rng(1)
    for _ in range(20):
        q, (lo, hi) = rng.normal(size=8), sorted(rng.integers(0, 240, 2))
        segs = list(range(int(lo * 4 // 240), int(hi * 4 // 240) + 1))
        found = {"pre": lambda: g.pre(q, lo, hi, 5), "post": lambda: g.post(q, lo, hi, 5, 20), "hybrid": lambda: g.hybrid(q, lo, hi, 5, 20, segs, 16)}[how]()
        ids = [v for _, v in found]
        assert len(ids) <= 5 and len(set(ids)) == len(ids) and all(lo <= g.attr[v] <= hi for v in ids) and found == sorted(found, key=lambda e: (e[0], g.vid[e[1]]))


def test_good_recall():
    g = graph(600)
    rng, hits = np.random.default_rng(2), []
    for _ in range(40):
        q, (lo, hi) = rng.normal(size=8), sorted(rng.integers(0, 600, 2))
        segs = list(range(int(lo * 4 // 600), int(hi * 4 // 600) + 1))
        want = brute(g, q, lo, hi, 10)
        hits.append(len(set(want) & {v for _, v in g.hybrid(q, lo, hi, 10, 60, segs, 24)}) / max(1, len(want)))
    assert np.mean(hits) > 0.95


def test_point_empty_and_growing():
    g = graph()
    q = np.zeros(8)
    assert [g.attr[v] for _, v in g.pre(q, 7, 7, 10)] == [7] and g.pre(q, 7.2, 7.8, 10) == []
    assert len(g.post(q, 3, 12, 10, 10)) <= len(g.post(q, 3, 12, 10, 10, grow=True)) == 10
    empty = Graph(np.zeros((0, 8)), *[np.zeros(0)] * 4, 4, Params())
    assert empty.pre(q, 0, 1, 3) == empty.post(q, 0, 1, 3, 9) == empty.hybrid(q, 0, 1, 3, 9, [0], 4) == []


def test_one_segment_hybrid_without_range_is_the_layered_search():
    g = graph(segments=1)
    plain = METHODS["hnsw_post"](Shard.of(g.vid, g.x, g.attr, g.level), Params(m=8, ef_cons=40))
    rng = np.random.default_rng(3)
    for _ in range(10):
        q = rng.normal(size=8)
        a = [v for _, v in g.hybrid(q, -np.inf, np.inf, 5, 30, [0], 64)]
        assert a == [v for _, v in plain.search(q, -np.inf, np.inf, 5, 30)]


def test_picks():
    g = graph()
    o, hit = 5, np.array([[True, True, True, False]])
    look = lambda pick: g.picked(0, hit, 7, pick, np.zeros(1, np.int64))(np.array([0]), np.array([o]))[0]
    one = g.layers[0]
    r = one.row[o]
    assert [v for v in look("chunk") if v >= 0] == [v for j in range(3) for v in one.ids[r, j, :3] if v >= 0]
    near = sorted((d, v) for j in range(3) for d, v in zip(one.dist[r, j], one.ids[r, j], strict=True) if v >= 0)
    assert [v for v in look("distance") if v >= 0] == [v for _, v in near[:7]]


@pytest.mark.parametrize("name", sorted(METHODS))
def test_methods(name):
    x, attr, vid, level = data(200, clusters=12)
    s = Shard.of(vid, x, attr, level)
    m = METHODS[name](s, Params(m=8, ef_cons=40))
    rng, hits = np.random.default_rng(4), []
    for _ in range(15):
        q, (lo, hi) = x[rng.integers(200)] + 0.1, sorted(rng.integers(0, 200, 2))
        a, b = s.range(lo, hi)
        found = m.search(q, lo, hi, 5, 60, 32)
        d = np.linalg.norm(s.x[a:b] - q, axis=1)
        best = {int(s.vid[a + i]) for i in np.argsort(d, kind="stable")[:5]}
        assert {v for _, v in found} <= set(s.vid[a:b].tolist()) and found == sorted(found) and len(found) <= 5
        hits.append(len(best & {v for _, v in found}) / max(1, len(best)))
        assert m.search(q, 5.2, 5.8, 5, 60) == []
    assert np.mean(hits) > 0.55


def test_interval_edges_hold_every_prefix_and_lower_bound():
    """The graph read for a prefix is the one built for it; for a range all edges are inside, and every object beside others has some."""
    x, attr, vid, level = data(80)
    s = Shard.of(vid, x, attr, level)
    whole = METHODS["interval_edge_graph"](s, Params(m=6, ef_cons=30))
    part = METHODS["interval_edge_graph"](s.take(np.arange(50)), Params(m=6, ef_cons=30))
    for low in (0, 10, 37):
        edges = whole.edges(low, 50)
        assert edges == part.edges(low, 50) and all(low <= o < 50 for e in edges for o in e)
        assert {a for a, _ in edges} == set(range(low, 50))


def test_inclusiveness_and_work():
    x, attr, vid, level = data(320, clusters=10)
    s, p = Shard.of(vid, x, attr, level), Params(m=8, ef_cons=60)
    full, thin = METHODS["index"](s, p, segments=4), METHODS["degraded_index"](s, p, segments=4, keep=0.3)
    seg = np.searchsorted(full.cuts, s.attr, "right")
    a, n = common_edges(full.g, s, np.flatnonzero(seg < 2), p)
    b, _ = common_edges(thin.g, s, np.flatnonzero(seg < 2), p)
    assert a / n > 0.6 and b < a
    many = METHODS["multi_segment_hnsw"](s, p, segments=4)
    q = x[3]
    full.search(q, 0, 319, 5, 20, 16)
    many.search(q, 0, 319, 5, 20)
    assert many.spent[0] > 0 and full.spent[0] > 0
    level = METHODS["degraded_index"](s, p, segments=4, inclusiveness=40)
    assert abs(level.measured - 40) < 8


def test_codes():
    x = data(300, 8, clusters=5)[0]
    book = Codebook.train(x, 4, 16)
    codes = book.encode(x)
    rebuilt = np.hstack([c[codes[:, j]] for j, c in enumerate(book.books)])
    assert np.allclose(book.distances(x[0], codes), ((rebuilt - x[0]) ** 2).sum(axis=1))
    assert len(kmeans(x[:3], 10)) == 3


@settings(max_examples=50, deadline=None)
@given(st.tuples(*[st.integers(0, 15)] * 4), st.integers(4, 40))
def test_zcover(r, most):
    lo, hi = (min(r[0], r[1]), min(r[2], r[3])), (max(r[0], r[1]), max(r[2], r[3]))
    key = lambda a, b: sum((((a >> i) & 1) << 2 * i) | (((b >> i) & 1) << 2 * i + 1) for i in range(4))
    cover = zcover(lo, hi, 4, most)
    assert len(cover) <= most
    for a in range(lo[0], hi[0] + 1):
        for b in range(lo[1], hi[1] + 1):
            assert any(x <= key(a, b) <= y for x, y in cover)


def _recalls(name, how, ef, span, n=1500, d=32, k=10, m=8):
    """Mean recall of a method over ranges of ``span`` objects, vectors spread evenly."""
    x, attr, vid, level = data(n, d, seed=4)
    s = Shard.of(vid, x, attr, level)
    method, q = METHODS[name](s, Params(m=m, ef_cons=30), **how), np.random.default_rng(5).normal(size=(20, d))
    lo = np.linspace(0, n - span, 20).astype(int).astype(float)
    got, hits = method.many(q, lo, lo + span - 1, k, ef), 0
    for i, f in enumerate(got):
        a, b = s.range(lo[i], lo[i] + span - 1)
        hits += len({v for _, v in f} & {v for _, v in method._scan(q[i], np.arange(a, b), k)})
    return hits / (20 * min(k, span))


@pytest.mark.parametrize("name, how", [("pq_pre", {"rerank": 1}), ("pq_scan", {"rerank": 1}), ("ivfpq", {"probes": 2})])
def test_codes_go_on_while_nearer_objects_may_be_left(name, how):
    """The number of codes to compare again, or of cells, is where a search begins and not where it ends."""
    assert _recalls(name, {"centroids": 8, **how}, 20, 1200) >= 0.95


@pytest.mark.parametrize("n", [30, 2, 1])
def test_few_objects_are_all_found_by_code(n):
    x, attr, vid, level = data(n, 6)
    for name in ("pq_pre", "pq_scan", "ivfpq"):
        method = METHODS[name](Shard.of(vid, x, attr, level), Params(m=4), rerank=1, probes=1)
        assert {v for _, v in method.search(np.zeros(6), -1.0, 1e9, 40, 50)} == set(vid.tolist())


def test_segments_give_what_a_small_range_holds():
    assert _recalls("multi_segment_hnsw", {"segments": 4}, 10, 12) >= 0.95


def test_graphs_of_ranges_grow_from_the_ends(monkeypatch):
    """Ranges that begin at an end of the shard share one growing graph; all others are built. What they give is exact under a full beam."""
    x, attr, vid, level = data(200, 8, seed=6)
    s, inserted = Shard.of(vid, x, attr, level), []
    insert = Graph.insert
    monkeypatch.setattr(Graph, "insert", lambda g, v: (inserted.append(v), insert(g, v))[1])
    method, q = METHODS["optimal_hnsw"](s, Params(m=8, ef_cons=60)), np.random.default_rng(7).normal(size=(40, 8))
    lo, hi = np.concatenate([np.full(20, -5.0), np.arange(15) * 9 + 3.0, [50, 50, 50, 300, 199]]), np.concatenate([np.arange(20) * 9 + 10.0, np.full(15, 500.0), [80, 80, 80, 400, 199]])
    got = method.many(q, lo, hi, 10, 200)
    for i, f in enumerate(got):
        a, b = s.range(lo[i], hi[i])
        assert [v for _, v in f] == [v for _, v in method._scan(q[i], np.arange(a, b), 10)]
    assert len(inserted) <= 2 * 200 + 31


def test_graphs_of_runs_are_built_once(monkeypatch):
    """A thinned index is measured twice against the same graphs."""
    x, attr, vid, level = data(160, 8, seed=8)
    inserted, insert = [], Graph.insert
    monkeypatch.setattr(Graph, "insert", lambda g, v: (inserted.append(v), insert(g, v))[1])
    method = METHODS["degraded_index"](Shard.of(vid, x, attr, level), Params(m=8, ef_cons=30), segments=4, inclusiveness=40)
    assert abs(method.measured - 40) < 15 and len(inserted) == 160 + 3 * 80


def test_growth_goes_on_until_results_stay():
    """A beam that has just k results in range has not found the nearest ones."""
    x, attr, vid, level = data(1500, 24, seed=9)
    g = build(x, attr, vid, np.zeros(1500, np.int64), level, 1, Params(m=6, ef_cons=30))
    q = np.random.default_rng(10).normal(size=(20, 24))
    lo, hi = np.full(20, 0.0), np.full(20, 1200.0)
    got, beams = g.post_many(q, lo, hi, 10, 14, True), [g.post_many(q, lo, hi, 10, 14 << i) for i in range(8)]
    for b, f in enumerate(got):
        assert len(f) == 10 and any(one[b] == two[b] == f for one, two in zip(beams, beams[1:], strict=False))
