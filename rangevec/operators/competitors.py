"""Re-creations of the ideas that the index is compared with, over the same kernel, so that counts of distances compare."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from .kernel import DIST, Graph, Params, estimated, histogram

Found = list[tuple[float, int]]


@dataclass
class Shard:
    """Arrays of a shard, objects in attribute order."""

    vid: np.ndarray
    x: np.ndarray
    attr: np.ndarray
    level: np.ndarray

    @classmethod
    def of(cls, vid, x, attr, level) -> Shard:
        order = np.lexsort([vid, attr])
        return cls(np.asarray(vid)[order], np.asarray(x, np.float64)[order], np.asarray(attr, np.float64)[order], np.asarray(level)[order])

    def range(self, lo: float, hi: float) -> tuple[int, int]:
        return int(np.searchsorted(self.attr, lo, "left")), int(np.searchsorted(self.attr, hi, "right"))

    def take(self, ids: np.ndarray) -> Shard:
        return Shard(self.vid[ids], self.x[ids], self.attr[ids], self.level[ids])

    def by_id(self) -> np.ndarray:
        return np.argsort(self.vid, kind="stable")


def _graph(s: Shard, params: Params, segments: np.ndarray | None = None, cls: type[Graph] = Graph, **more) -> Graph:
    order = s.by_id()
    seg = np.zeros(len(s.vid), np.int64) if segments is None else segments
    g = cls(s.x[order], s.attr[order], s.vid[order], seg[order], s.level[order], int(seg.max()) + 1 if len(seg) else 1, params, **more)
    for v in range(len(g.vid)):
        g.insert(v)
    return g


class Method:
    """``many`` gives for each query the (distance, id) of at most k objects in range, nearest first; ``spent`` holds the distances that each of them took."""

    name = ""

    def __init__(self, s: Shard, params: Params, **how):
        self.s, self.params, self.how, self.spent, self.build_dist = s, params, how, np.zeros(0), 0
        self.prepare()

    def prepare(self) -> None: ...

    def size(self) -> int:
        """Bytes beside the vectors, with 32-bit edges."""
        return 0

    def _scan(self, q: np.ndarray, ids: np.ndarray, k: int) -> Found:
        d = np.sqrt(((self.s.x[ids] - q) ** 2).sum(axis=1))
        best = np.lexsort([self.s.vid[ids], d])[:k]
        return [(float(d[i]), int(self.s.vid[ids[i]])) for i in best]

    def one(self, q: np.ndarray, lo: float, hi: float, k: int, ef: int, m: int) -> tuple[Found, float]:
        """Results of one query and the distances that it took, for methods that don't search side by side."""
        raise NotImplementedError

    def many(self, q: np.ndarray, lo: np.ndarray, hi: np.ndarray, k: int, ef: int = 100, m: int = 16) -> list[Found]:
        got = [self.one(*a, k, ef, m) for a in zip(q, lo, hi, strict=True)]
        self.spent = np.array([n for _, n in got])
        return [f for f, _ in got]

    def search(self, q: np.ndarray, lo: float, hi: float, k: int, ef: int = 100, m: int = 16) -> Found:
        return self.many(np.asarray(q)[None], np.array([lo], np.float64), np.array([hi], np.float64), k, ef, m)[0]


class OrderedScan(Method):
    """An ordered attribute index, then distances to all objects of the range."""

    name = "btree_pre"

    def one(self, q, lo, hi, k, ef, m):
        a, b = self.s.range(lo, hi)
        return self._scan(q, np.arange(a, b), k), b - a


class Segmented(Method):
    """The index itself; ``strategy`` pre, post, hybrid or auto, which goes by the estimated share of a range."""

    name = "index"

    def prepare(self):
        n, s = len(self.s.vid), self.how.get("segments", 8)
        starts = sorted({-(-j * n // s) for j in range(1, s)} - {0, n})
        self.cuts = sorted({float(self.s.attr[i]) for i in starts} - {float(self.s.attr[0])}) if n else []
        self.g = _graph(self.s, self.params, np.searchsorted(self.cuts, self.s.attr, "right"))
        self.hist, self.build_dist = histogram(self.s.attr), self.g.dist

    def size(self):
        return self.g.bytes()

    def many(self, q, lo, hi, k, ef=100, m=16):
        g, out = self.g, [[] for _ in q]
        share = estimated(self.hist, lo, hi) / max(1, g.size)
        given = self.how.get("strategy", "auto")
        how = np.where(share <= self.how.get("tau_a", 0.01), "pre", np.where(share >= self.how.get("tau_b", 0.5), "post", "hybrid")) if given == "auto" else np.full(len(q), given)
        hit = (np.arange(g.segments) >= np.searchsorted(self.cuts, lo, "right")[:, None]) & (np.arange(g.segments) <= np.searchsorted(self.cuts, hi, "right")[:, None])
        self.spent = np.zeros(len(q))
        for name in np.unique(how):
            at = np.flatnonzero(how == name)
            if name == "pre":
                found = g.pre_many(q[at], lo[at], hi[at], k)
            elif name == "post":
                found = g.post_many(q[at], lo[at], hi[at], k, ef)
            else:
                found = g.hybrid_many(q[at], lo[at], hi[at], k, ef, hit[at], m, self.how.get("pick", "chunk"))
            self.spent[at] = g.spent[:, DIST]
            for i, f in zip(at, found, strict=True):
                out[i] = [(d, int(g.vid[v])) for d, v in f]
        return out


class Layered(Method):
    """One layered graph of all objects, filter afterwards."""

    name = "hnsw_post"

    def prepare(self):
        self.g = _graph(self.s, self.params)
        self.build_dist = self.g.dist

    def size(self):
        return 4 * self.g.edge_count()

    def _layered(self, q, ef) -> tuple[np.ndarray, np.ndarray]:
        g = self.g
        d, found = [np.zeros((0, ef))], [np.zeros((0, ef), np.int64)]
        self.spent = np.zeros(len(q))
        for at in g.blocks(len(q)):
            g.spent = np.zeros((len(at), 5), np.int64)
            one, two = g.layered(q[at], np.full(len(at), g.entry[0]), ef, lambda layer, n=len(at): g.chunks(layer, np.zeros(n, np.int64)))
            self.spent[at] = g.spent[:, DIST]
            d.append(one)
            found.append(two)
        return np.concatenate(d), np.concatenate(found)

    def many(self, q, lo, hi, k, ef=100, m=16):
        g = self.g
        if g.entry[0] < 0:
            self.spent = np.zeros(len(q))
            return [[] for _ in q]
        d, found = self._layered(q, ef)
        ok = (found >= 0) & (g.attr[found] >= lo[:, None]) & (g.attr[found] <= hi[:, None])
        return [[(float(x), int(g.vid[v])) for x, v in zip(d[i][ok[i]][:k], found[i][ok[i]][:k], strict=True)] for i in range(len(q))]

    def all_of(self, q, lo, hi, k, ef=100, m=16):
        """The same, but the beam of a query that misses some of its k objects, or of fewer that its range holds, doubles until it has them or has met all nodes."""
        there = np.minimum(k, np.searchsorted(self.s.attr, hi, "right") - np.searchsorted(self.s.attr, lo, "left"))
        out, spent, todo = [[] for _ in q], np.zeros(len(q)), np.arange(len(q))
        while len(todo):
            for i, f in zip(todo, self.many(q[todo], lo[todo], hi[todo], k, ef, m), strict=True):
                out[i] = f
            spent[todo] += self.spent
            todo = np.array([i for i in todo if len(out[i]) < there[i] and ef < len(self.s.vid)], np.int64)
            ef *= 2
        self.spent = spent
        return out


class VectorStore(Layered):
    """A vector retrieval system: the same, with the beam enlarged by ``widen``."""

    name = "vecdb_postfilter"

    def many(self, q, lo, hi, k, ef=100, m=16):
        return super().many(q, lo, hi, k, ef * self.how.get("widen", 2), m)


class FlatGraph(Method):
    """Nearest-neighbour graph made mutual and pruned, searched from the nearest of some fixed starts, filter afterwards."""

    name = "graph_postfilter"

    def prepare(self):
        n, k = len(self.s.vid), self.how.get("k", 2 * self.params.m)
        self.g = Graph(self.s.x, self.s.attr, self.s.vid, np.zeros(n, np.int64), np.zeros(n, np.int64), 1, self.params)
        links: list[dict[int, float]] = [{} for _ in range(n)]
        for v in range(n):
            d = np.sqrt(((self.s.x - self.s.x[v]) ** 2).sum(axis=1))
            d[v] = np.inf
            for o in np.argsort(d, kind="stable")[:k]:
                if np.isfinite(d[o]):
                    links[v][int(o)] = links[int(o)][v] = float(d[o])
        self.build_dist, self.adj = n * n, np.full((n, k), -1, np.int64)
        for v, own in enumerate(links):
            near = sorted((d, o) for o, d in own.items())
            if near:
                ids = np.array([o for _, o in near])
                kept = ids[self.g.prune(np.array([[d for d, _ in near]]), ids[None], k)[0]]
                self.adj[v, : len(kept)] = kept
        self.heads = np.arange(0, n, max(1, n // 8))[:8]

    def size(self):
        return 4 * int((self.adj >= 0).sum())

    def many(self, q, lo, hi, k, ef=100, m=16):
        self.spent, out = np.zeros(len(q)), []
        if not len(self.heads):
            return [[] for _ in q]
        for at in self.g.blocks(len(q)):
            d = np.sqrt(((self.s.x[self.heads][None] - q[at][:, None]) ** 2).sum(axis=2))
            near = d.argmin(axis=1)
            self.g.spent = np.zeros((len(at), 5), np.int64)
            d, found = self.g.spread(q[at], self.heads[near], d.min(axis=1), ef, lambda rows, nodes: self.adj[nodes])
            self.spent[at] = self.g.spent[:, DIST] + len(self.heads)
            ok = (found >= 0) & (self.s.attr[found] >= lo[at][:, None]) & (self.s.attr[found] <= hi[at][:, None])
            out += [[(float(x), int(self.s.vid[v])) for x, v in zip(d[i][ok[i]][:k], found[i][ok[i]][:k], strict=True)] for i in range(len(at))]
        return out


class _Fused(Graph):
    """The last coordinate is the attribute over its spread; gaps count beyond each query's ``slack``."""

    def __init__(self, *a, weight: float = 1.0):
        super().__init__(*a)
        self.weight, self.slack = weight, None

    def lengths(self, d, rows=None):
        v, gap = d[..., :-1], np.abs(d[..., -1])
        if self.slack is not None and rows is not None:
            gap = np.maximum(gap - self.slack[rows], 0)
        return np.sqrt(np.einsum("...j,...j->...", v, v)) + self.weight * gap

    def closer(self, ids, own):
        x = self.x[ids]
        v, a = x[..., :-1], x[..., -1]
        square = np.einsum("...j,...j->...", v, v)
        d2 = square[:, :, None] + square[:, None, :] - 2 * np.matmul(v, np.swapaxes(v, 1, 2))
        return np.sqrt(np.maximum(d2, 0)) + self.weight * np.abs(a[:, :, None] - a[:, None, :]) < own[:, None, :] - 1e-12

    def beside(self, x, square, own, at):
        return self.lengths(x - x[np.arange(len(x)), at][:, None]) < own - 1e-12


class FusedDistance(Layered):
    """One graph over vector distance plus weighted attribute gap; a range asks for its middle, gaps inside it are free."""

    name = "fused_distance_graph"

    def prepare(self):
        a = self.s.attr
        self.spread = float(a.max() - a.min()) or 1.0 if len(a) else 1.0
        wide = Shard(self.s.vid, np.hstack([self.s.x, a[:, None] / self.spread]), a, self.s.level)
        self.g = _graph(wide, self.params, cls=_Fused, weight=self.how.get("weight", 1.0))
        self.build_dist = self.g.dist

    def many(self, q, lo, hi, k, ef=100, m=16):
        g, out, spent = self.g, [], np.zeros(len(q))
        if g.entry[0] < 0:
            self.spent = spent
            return [[] for _ in q]
        low, high = np.maximum(lo, self.s.attr[0]), np.minimum(hi, self.s.attr[-1])
        wide = np.hstack([q, ((low + high) / 2 / self.spread)[:, None]])
        for at in g.blocks(len(q)):
            g.slack = np.maximum(0.0, (high[at] - low[at]) / 2 / self.spread)
            _, found = self._layered(wide[at], ef)
            spent[at] = self.spent
            for i, ids in zip(at, found, strict=True):
                ids = ids[ids >= 0]
                ids = ids[(g.attr[ids] >= lo[i]) & (g.attr[ids] <= hi[i])]
                d = np.sqrt(((g.x[ids][:, :-1] - q[i]) ** 2).sum(axis=1))
                out.append(sorted((float(x), int(g.vid[v])) for x, v in zip(d, ids, strict=True))[:k])
        g.slack, self.spent = None, spent
        return out


class IntervalEdges(Method):
    """Many graphs in one: that of every range of the attribute order can be read from the edges' intervals.

    Objects arrive in attribute order. A new one looks for neighbours among all objects from a lower bound on, the bound being the first object at first;
    the edges it keeps hold for lower bounds from there up to their ends, and the bound then leaps beyond the last of them, so that it keeps
    edges for every lower bound. Edges back are born with the new object, and one that a later object's edge crowds out dies with that object's arrival: that is the
    interval of upper bounds. A range reads the edges whose two intervals hold its ends. An object that arrives out of order asks for a new build.
    """

    name = "interval_edge_graph"

    def prepare(self):
        n, m = len(self.s.vid), self.params.m
        self.g = Graph(self.s.x, self.s.attr, self.s.vid, np.zeros(n, np.int64), np.zeros(n, np.int64), 1, self.params)
        # Target, first and last lower bound, birth and death of each edge, and its length.
        self.to, self.low, self.high = np.full((n, 4 * m), -1, np.int64), np.zeros((n, 4 * m), np.int64), np.zeros((n, 4 * m), np.int64)
        self.born, self.died, self.far, self.count = np.zeros((n, 4 * m), np.int64), np.zeros((n, 4 * m), np.int64), np.zeros((n, 4 * m)), np.zeros(n, np.int64)
        total = 0
        for v in range(1, n):
            at = 0
            while at < v:
                start = np.array([at + (v - at) // 2])
                self.g.spent = np.zeros((1, 5), np.int64)
                d, found = self.g.spread(self.s.x[v][None], start, self.g.lengths(self.s.x[start] - self.s.x[v]), self.params.ef_cons, self._alive(np.array([at]), np.array([v])), wave=self.params.waves(self.params.ef_cons))
                keep = self.g.prune(d, found, m)
                ends = found[keep]
                for o, far in zip(ends.tolist(), d[keep].tolist(), strict=True):
                    self._add(v, o, at, o, v, far)
                    self._add(o, v, at, o, v, far)
                    self._crowd(o, v)
                total += self.g.dist + 1
                at = int(ends.max()) + 1
        self.build_dist = total

    def _add(self, a: int, b: int, low: int, high: int, born: int, far: float) -> None:
        i = self.count[a]
        if i == self.to.shape[1]:
            for name in ("to", "low", "high", "born", "died", "far"):
                old = getattr(self, name)
                setattr(self, name, np.concatenate([old, np.full_like(old, -1)], axis=1))
        self.to[a, i], self.low[a, i], self.high[a, i], self.born[a, i], self.died[a, i], self.far[a, i] = b, low, high, born, np.iinfo(np.int64).max, far
        self.count[a] += 1

    def _crowd(self, o: int, v: int) -> None:
        """Of the living edges to later objects, m stay."""
        n = self.count[o]
        late = np.flatnonzero((self.to[o, :n] > o) & (self.died[o, :n] > v))
        # One target may have edges for several lower bounds.
        order = late[np.argsort(self.far[o, late], kind="stable")]
        _, first = np.unique(self.to[o, order], return_index=True)
        own = order[np.sort(first)]
        if len(own) > self.params.m:
            keep = self.g.prune(self.far[o, own][None], self.to[o, own][None], self.params.m)[0]
            gone = np.isin(self.to[o, late], self.to[o, own[~keep]])
            self.died[o, late[gone]] = v

    def _alive(self, low: np.ndarray, high: np.ndarray):
        """Neighbours in the graph of objects ``low`` to ``high`` - 1 of each row."""

        def look(rows, nodes):
            a, b = low[rows][:, None], high[rows][:, None]
            ok = (self.to[nodes] >= a) & (self.to[nodes] < b) & (self.low[nodes] <= a) & (a <= self.high[nodes]) & (self.born[nodes] < b) & (b <= self.died[nodes])
            return np.where(ok, self.to[nodes], -1)

        return look

    def edges(self, low: int, high: int) -> set[tuple[int, int]]:
        nodes = np.arange(low, high)
        near = self._alive(np.full(len(nodes), low), np.full(len(nodes), high))(np.arange(len(nodes)), nodes)
        r, c = np.nonzero(near >= 0)
        return set(zip(nodes[r].tolist(), near[r, c].tolist(), strict=True))

    def size(self):
        return 20 * int(self.count.sum())

    def many(self, q, lo, hi, k, ef=100, m=16):
        a, b = np.searchsorted(self.s.attr, lo, "left"), np.searchsorted(self.s.attr, hi, "right")
        self.spent, out, some = np.zeros(len(q)), [[] for _ in q], np.flatnonzero(a < b)
        for part in self.g.blocks(len(some)):
            at = some[part]
            start = (a[at] + b[at]) // 2
            self.g.spent = np.zeros((len(at), 5), np.int64)
            d, found = self.g.spread(q[at], start, self.g.lengths(self.s.x[start] - q[at]), ef, self._alive(a[at], b[at]))
            self.spent[at] = self.g.spent[:, DIST] + 1
            for i, x, v in zip(at, d, found, strict=True):
                out[i] = [(float(y), int(self.s.vid[w])) for y, w in zip(x[:k], v[:k], strict=True) if w >= 0]
        return out


class ManyGraphs(Method):
    """One layered graph per segment; the segments of a range are searched one by one and merged."""

    name = "multi_segment_hnsw"

    def prepare(self):
        n, s = len(self.s.vid), self.how.get("segments", 8)
        edges = np.linspace(0, n, s + 1).astype(int)
        self.parts = [(a, b, Layered(self.s.take(np.arange(a, b)), self.params)) for a, b in zip(edges[:-1], edges[1:], strict=True) if b > a]
        self.build_dist = sum(p.build_dist for _, _, p in self.parts)

    def size(self):
        return sum(p.size() for _, _, p in self.parts)

    def many(self, q, lo, hi, k, ef=100, m=16):
        a, b = np.searchsorted(self.s.attr, lo, "left"), np.searchsorted(self.s.attr, hi, "right")
        spent, out = np.zeros(len(q)), [[] for _ in q]
        for x, y, p in self.parts:
            at = np.flatnonzero((x < b) & (a < y))
            if len(at):
                # A range may hold little of a segment.
                for i, f, n in zip(at, p.all_of(q[at], lo[at], hi[at], k, ef, m), p.spent, strict=True):
                    out[i] += f
                    spent[i] += n
        self.spent = spent
        return [sorted(f)[:k] for f in out]


class _Held(Layered):
    """A layered graph that is there already."""

    def prepare(self):
        self.g = self.how["graph"]


class BuiltPerQuery(Method):
    """The layered graph of just the range's objects: what an ideal index would hold ready. Its build isn't counted.

    Objects are inserted in attribute order, or against it. A graph that grows so from one end of the shard is that of every range which begins there, once it has met the
    range's other end; a range that touches neither end has a graph built for it alone.
    """

    name = "optimal_hnsw"

    def _growing(self, back: bool) -> Graph:
        s, n = self.s, len(self.s.vid)
        order = np.arange(n)[::-1] if back else np.arange(n)
        return Graph(s.x[order], s.attr[order], s.vid[order], np.zeros(n, np.int64), s.level[order], 1, self.params)

    def many(self, q, lo, hi, k, ef=100, m=16):
        a, b, n = np.searchsorted(self.s.attr, lo, "left"), np.searchsorted(self.s.attr, hi, "right"), len(self.s.vid)
        spent, out = np.zeros(len(q)), [[] for _ in q]

        def ask(at: np.ndarray, own: Layered) -> None:
            for i, f, d in zip(at, own.many(q[at], lo[at], hi[at], k, ef, m), own.spent, strict=True):
                out[i], spent[i] = f, d

        some = a < b
        first, last = some & (a == 0), some & (a > 0) & (b == n)
        for whose, size, back in ((first, b, False), (last, n - a, True)):
            g = self._growing(back) if whose.any() else None
            for upto in np.unique(size[whose]):
                while g.size < upto:
                    g.insert(g.size)
                ask(np.flatnonzero(whose & (size == upto)), _Held(self.s, self.params, graph=g))
        inner = np.flatnonzero(some & ~first & ~last)
        for x, y in sorted(set(zip(a[inner].tolist(), b[inner].tolist(), strict=True))):
            ask(inner[(a[inner] == x) & (b[inner] == y)], Layered(self.s.take(np.arange(x, y)), self.params))
        self.spent = spent
        return out


class Dedicated(Method):
    """Three indexes, chosen by range: ordered scan, interval edges, layered graph."""

    name = "dedicated"

    def prepare(self):
        self.parts = [OrderedScan(self.s, self.params), IntervalEdges(self.s, self.params), Layered(self.s, self.params)]
        self.build_dist = sum(p.build_dist for p in self.parts)

    def size(self):
        return sum(p.size() for p in self.parts)

    def many(self, q, lo, hi, k, ef=100, m=16):
        share = (np.searchsorted(self.s.attr, hi, "right") - np.searchsorted(self.s.attr, lo, "left")) / max(1, len(self.s.vid))
        which = np.where(share <= self.how.get("tau_a", 0.01), 0, np.where(share >= self.how.get("tau_b", 0.5), 2, 1))
        spent, out = np.zeros(len(q)), [[] for _ in q]
        for i, p in enumerate(self.parts):
            at = np.flatnonzero(which == i)
            if len(at):
                for j, f, n in zip(at, p.many(q[at], lo[at], hi[at], k, ef, m), p.spent, strict=True):
                    out[j], spent[j] = f, n
        self.spent = spent
        return out


class Degraded(Segmented):
    """The index with a share of its edges dropped by a hash. With ``inclusiveness`` the share is chosen so that, measured over runs of half of the segments, about so many percent
    of the edges of these runs' own graphs remain; ``measured`` is what does."""

    name = "degraded_index"

    def prepare(self):
        super().prepare()
        self.runs = None
        keep, aim = self.how.get("keep", 0.5), self.how.get("inclusiveness")
        if aim is not None:
            keep = min(1.0, aim / max(1e-9, self.inclusiveness()))
        for g in self.g.layers:
            v, o = g.node[:, None, None].astype(np.int64), g.ids.astype(np.int64)
            gone = (v * 2654435761 + o * 40503 + 12345) % 1000003 / 1000003 >= keep
            order = np.argsort(gone | (g.ids < 0), axis=2, kind="stable")
            for name, empty in (("ids", -1), ("dist", np.inf), ("mask", False)):
                setattr(g, name, np.take_along_axis(np.where(gone, empty, getattr(g, name)), order, axis=2))
        self.measured = self.inclusiveness() if aim is not None else None

    def inclusiveness(self) -> float:
        """Percent of the edges of graphs built for some runs of segments alone that this one has."""
        seg, s = np.searchsorted(self.cuts, self.s.attr, "right"), self.g.segments
        half = max(1, s // 2)
        if self.runs is None:
            # The runs' own graphs don't change when this one is thinned.
            self.runs = [own_edges(self.s, np.flatnonzero((seg >= a) & (seg < a + half)), self.params) for a in sorted({0, (s - half) // 2, s - half})]
        have = edge_ids(self.g)
        return 100.0 * sum(len(own & have) for own in self.runs) / max(1, sum(map(len, self.runs)))


# Product quantisation.
def kmeans(x: np.ndarray, k: int, rounds: int = 10) -> np.ndarray:
    """Centroids started from evenly spaced rows; empty ones stay where they are."""
    k = min(k, len(x))
    c = x[np.linspace(0, len(x) - 1, k).astype(int)].copy()
    for _ in range(rounds):
        near = ((x**2).sum(axis=1)[:, None] - 2 * x @ c.T + (c**2).sum(axis=1)).argmin(axis=1)
        for i in np.unique(near):
            c[i] = x[near == i].mean(axis=0)
    return c


@dataclass
class Codebook:
    """Sub-vectors and their centroids, at most 256 each."""

    cuts: list[tuple[int, int]]
    books: list[np.ndarray]

    @classmethod
    def train(cls, x: np.ndarray, parts: int = 8, centroids: int = 64) -> Codebook:
        edges = np.linspace(0, x.shape[1], min(parts, x.shape[1]) + 1).astype(int)
        cuts = [(int(a), int(b)) for a, b in zip(edges[:-1], edges[1:], strict=True)]
        return cls(cuts, [kmeans(x[:, a:b], min(centroids, 256)) for a, b in cuts])

    def encode(self, x: np.ndarray) -> np.ndarray:
        out = np.zeros((len(x), len(self.cuts)), np.uint8)
        for j, ((a, b), c) in enumerate(zip(self.cuts, self.books, strict=True)):
            out[:, j] = ((x[:, a:b] ** 2).sum(axis=1)[:, None] - 2 * x[:, a:b] @ c.T + (c**2).sum(axis=1)).argmin(axis=1)
        return out

    def decode(self, codes: np.ndarray) -> np.ndarray:
        return np.hstack([c[codes[:, j]] for j, c in enumerate(self.books)]) if len(codes) else np.zeros((0, self.cuts[-1][1] if self.cuts else 0))

    def distances(self, q: np.ndarray, codes: np.ndarray) -> np.ndarray:
        """Squared distances of a query to coded vectors, from one table per sub-vector."""
        tables = [((c - q[a:b]) ** 2).sum(axis=1) for (a, b), c in zip(self.cuts, self.books, strict=True)]
        return sum(t[codes[:, j]] for j, t in enumerate(tables))


#: A true neighbour's angle to its centroid is measured on so many objects of a shard with their ``NEAREST`` neighbours; ``SURE`` of them lie inside the bound kept.
MEASURED, NEAREST, SURE = 64, 10, 0.99


def _squares(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return np.maximum((x**2).sum(axis=1)[:, None] - 2 * x @ y.T + (y**2).sum(axis=1), 0)


def _lower(near: np.ndarray, far: np.ndarray, t: float) -> np.ndarray:
    """Least squared distance to objects ``far`` from a centroid at squared distance ``near``, if the cosine between both directions is ``t`` at most; with 1 it holds for all."""
    return near + far**2 - 2 * t * np.sqrt(near) * far


class Coded(Method):
    """Codes and exact re-ranking of the ``rerank`` * k best, and of all others that may be nearer than the last of these: an object's code and its distance from it bound its
    distance to a query. ``plan``: ``pre`` filters first, ``post`` scans all codes for an enlarged k first, ``exact`` filters and
    scans vectors, ``cost`` takes the cheapest of them whose recall, measured on objects of the shard, meets ``target``."""

    name = "pq_cost_planner"

    def prepare(self):
        self.book = Codebook.train(self.s.x, self.how.get("parts", 8), self.how.get("centroids", 64))
        self.codes = self.book.encode(self.s.x)
        self.rest = np.sqrt(((self.s.x - self.book.decode(self.codes)) ** 2).sum(axis=1)).astype(np.float32)
        self.angle = self._angle(self.book.decode(self.codes))
        self.good = {"exact": 1.0}
        if self.how.get("plan", "cost") == "cost":
            n = len(self.s.vid)
            for plan in ("pre", "post"):
                hits = total = 0
                for i in range(0, n, max(1, n // 16)):
                    lo, hi = self.s.attr[max(0, i - n // 8)], self.s.attr[min(n - 1, i + n // 8)]
                    a, b = self.s.range(lo, hi)
                    best = {v for _, v in self._scan(self.s.x[i], np.arange(a, b), 10)}
                    hits += len(best & {v for _, v in self._run(plan, self.s.x[i], a, b, 10)[0]})
                    total += len(best)
                self.good[plan] = hits / max(1, total)

    def _angle(self, centre: np.ndarray) -> float:
        """Cosine, between the directions from an object's centroid to a query and to the object, that ``SURE`` of the true neighbours don't exceed; 1 where there are few objects."""
        n, x = len(self.s.vid), self.s.x
        if n < MEASURED * NEAREST:
            return 1.0
        got = []
        for i in np.linspace(0, n - 1, MEASURED).astype(int):
            d = ((x - x[i]) ** 2).sum(axis=1)
            d[i] = np.inf
            near = np.argpartition(d, NEAREST)[:NEAREST]
            u, v = x[i] - centre[near], x[near] - centre[near]
            size = np.sqrt((u**2).sum(axis=1) * (v**2).sum(axis=1))
            got.append((u * v).sum(axis=1)[size > 0] / size[size > 0])
        flat = np.concatenate(got)
        return float(np.clip(np.quantile(flat, SURE), 0.0, 1.0)) if len(flat) else 1.0

    def size(self):
        return self.codes.nbytes + self.rest.nbytes + sum(b.nbytes for b in self.book.books)

    def _bounds(self, q: np.ndarray, ids: np.ndarray) -> np.ndarray:
        return _lower(self.book.distances(q, self.codes[ids]), self.rest[ids].astype(np.float64), self.angle)

    def _ranked(self, q: np.ndarray, ids: np.ndarray, low: np.ndarray, width: int, a: int, b: int, k: int) -> tuple[Found, float]:
        """The k best of [a, b) among ``ids`` and the vectors compared: first those in range of the ``width`` with the lowest bounds, then all others whose bound is below the kth distance."""
        inside = (ids >= a) & (ids < b)
        first = np.zeros(len(ids), bool)
        first[np.argpartition(low, width - 1)[:width] if width < len(low) else slice(None)] = True
        got = self._scan(q, ids[first & inside], k)
        more = ids[~first & inside & (low <= (got[-1][0] ** 2 if len(got) == k else np.inf))]
        return sorted(got + self._scan(q, more, k))[:k], int((first & inside).sum()) + len(more)

    def _run(self, plan, q, a, b, k) -> tuple[Found, float]:
        n, width = len(self.s.vid), self.how.get("rerank", 4) * k
        if plan == "exact":
            return self._scan(q, np.arange(a, b), k), b - a
        ids = np.arange(a, b) if plan == "pre" else np.arange(n)
        if plan == "post":
            width = int(np.ceil(width * n / max(1, b - a)))
        found, spent = self._ranked(q, ids, self._bounds(q, ids), width, a, b, k)
        return found, spent + len(ids) * len(self.book.cuts) / max(1, self.s.x.shape[1])

    def cost(self, plan, y):
        n, d, p, r = len(self.s.vid), self.s.x.shape[1], len(self.book.cuts), self.how.get("rerank", 4) * 10
        return {"exact": y * d, "pre": y * p + r * d, "post": n * p + r * d * n / max(1, y)}[plan]

    def one(self, q, lo, hi, k, ef, m):
        a, b = self.s.range(lo, hi)
        if a >= b:
            return [], 0
        plan = self.how.get("plan", "cost")
        if plan == "cost":
            fit = [p for p, r in self.good.items() if r >= self.how.get("target", 0.9)]
            plan = min(fit, key=lambda p: self.cost(p, b - a))
        return self._run(plan, q, a, b, k)


class CodedPre(Coded):
    """Filter, then codes."""

    name = "pq_pre"

    def __init__(self, s, params, **how):
        super().__init__(s, params, **{"plan": "pre", **how})


class CodedScan(Coded):
    """Codes of all objects, then the filter."""

    name = "pq_scan"

    def __init__(self, s, params, **how):
        super().__init__(s, params, **{"plan": "post", **how})


class PartitionedCodes(Method):
    """Attribute partitions, each with its own codes; those that the range meets are searched and merged."""

    name = "partitioned_pq"

    def prepare(self):
        edges = np.linspace(0, len(self.s.vid), self.how.get("partitions", 8) + 1).astype(int)
        self.parts = [(a, b, Coded(self.s.take(np.arange(a, b)), self.params, **self.how)) for a, b in zip(edges[:-1], edges[1:], strict=True) if b > a]

    def size(self):
        return sum(p.size() for _, _, p in self.parts)

    def one(self, q, lo, hi, k, ef, m):
        a, b = self.s.range(lo, hi)
        spent, found = 0, []
        for x, y, p in self.parts:
            if x < b and a < y:
                got, n = p.one(q, lo, hi, k, ef, m)
                found += got
                spent += n
        return sorted(found)[:k], spent


class CellCodes(Coded):
    """Coarse cells, of which the ``probes`` nearest are scanned by code, filter afterwards; then those cells, and of each cell those codes beyond the ``ef`` best, that may hold a nearer object."""

    name = "ivfpq"

    def prepare(self):
        self.how["plan"] = "post"
        super().prepare()
        self.cells = kmeans(self.s.x, self.how.get("cells", max(1, int(len(self.s.vid) ** 0.5))))
        self.cell = _squares(self.s.x, self.cells).argmin(axis=1)
        away, n = np.sqrt(((self.s.x - self.cells[self.cell]) ** 2).sum(axis=1)), len(self.cells)
        self.inner, self.outer, self.cell_angle = np.full(n, np.inf), np.zeros(n), self._angle(self.cells[self.cell])
        np.minimum.at(self.inner, self.cell, away)
        np.maximum.at(self.outer, self.cell, away)

    def one(self, q, lo, hi, k, ef, m):
        a, b = self.s.range(lo, hi)
        d = ((self.cells - q) ** 2).sum(axis=1)
        near = np.zeros(len(d), bool)
        near[np.argsort(d, kind="stable")[: self.how.get("probes", 8)]] = True
        # The distance from the centroid at which a cell's objects may come nearest.
        low = np.where(self.outer >= self.inner, _lower(d, np.clip(self.cell_angle * np.sqrt(d), np.minimum(self.inner, self.outer), self.outer), self.cell_angle), np.inf)
        ids = np.flatnonzero(near[self.cell])
        found, spent = self._ranked(q, ids, self._bounds(q, ids), ef, a, b, k)
        last = found[-1][0] ** 2 if len(found) == k else np.inf
        more = np.flatnonzero((~near & (low <= last))[self.cell])
        bound = self._bounds(q, more)
        left = more[(bound <= last) & (more >= a) & (more < b)]
        found = sorted(found + self._scan(q, left, k))[:k]
        return found, len(self.cells) + (len(ids) + len(more)) * len(self.book.cuts) / max(1, self.s.x.shape[1]) + spent + len(left)


METHODS: dict[str, type[Method]] = {c.name: c for c in (Segmented, OrderedScan, Layered, VectorStore, FlatGraph, FusedDistance, IntervalEdges, ManyGraphs, BuiltPerQuery, Dedicated, Degraded, Coded, CodedPre, CodedScan, PartitionedCodes, CellCodes)}


def edge_ids(g: Graph, layer: int = 0) -> set[tuple[int, int]]:
    return {(int(g.vid[a]), int(g.vid[b])) for a, b in g.edges(layer)}


def own_edges(s: Shard, ids: np.ndarray, params: Params, layer: int = 0) -> set[tuple[int, int]]:
    """Edges of the layered graph of some objects, built with the same order, levels and parameters."""
    return edge_ids(Layered(s.take(ids), params).g, layer)


def common_edges(g: Graph, s: Shard, ids: np.ndarray, params: Params, layer: int = 0) -> tuple[int, int]:
    """Edges of the layered graph of some objects, built with the same order, levels and parameters, and how many of them ``g`` has."""
    mine = own_edges(s, ids, params, layer)
    return len(mine & edge_ids(g, layer)), len(mine)
