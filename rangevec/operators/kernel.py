"""The graph of one shard in flat arrays: incremental build and the three searches, many queries side by side. Runs inside one task; shards bound its memory."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np

Edge = tuple[float, int]
#: Places of a row of ``Graph.spent``.
DIST, VISITED, BRIDGE, HOPS, EDGES = range(5)
#: Marks of searches that run side by side take a byte for each of their queries and nodes, so many at most.
MARKS = 1 << 27


@dataclass
class Params:
    """``base_degree`` is the capacity of a chunk on layer 0, ``mask_degree`` that of a node's edges in the graph of all nodes; both are m unless given.

    ``candidates``: ``beam`` searches the graph for a new node's neighbours, ``exact`` takes the nearest earlier nodes of each segment by distance. While
    building, a beam expands its ``wave`` nearest candidates at once, an eighth of its width unless given; 1 expands them one by one.
    """

    m: int = 16
    ef_cons: int = 500
    base_degree: int = 0
    mask_degree: int = 0
    candidates: str = "beam"
    wave: int = 0
    entry: str = "first"

    def cap(self, layer: int) -> int:
        return (self.base_degree or self.m) if layer == 0 else self.m

    def masked(self) -> int:
        return self.mask_degree or self.m

    def waves(self, width: int) -> int:
        return self.wave or max(1, width // 8)


@dataclass
class Layer:
    """Rows of the nodes of one layer. ``ids[r, j]`` is the chunk of a node's edges into segment j, nearest first, -1 behind them; ``mask`` marks those in the graph of
    all nodes, ``next`` is the successor in attribute order on this layer, -1 behind the last, and ``head`` the first."""

    row: np.ndarray
    node: np.ndarray
    ids: np.ndarray
    dist: np.ndarray
    mask: np.ndarray
    next: np.ndarray
    head: int = -1

    @classmethod
    def empty(cls, at: int, level: np.ndarray, segments: int, cap: int) -> Layer:
        on = level >= at
        node = np.flatnonzero(on).astype(np.int32)
        shape = (len(node), segments, cap)
        return cls(np.where(on, np.cumsum(on) - 1, -1).astype(np.int32), node, np.full(shape, -1, np.int32), np.full(shape, np.inf), np.zeros(shape, bool), np.full(len(node), -1, np.int32))


class Graph:
    """Nodes are numbered in the order in which they are inserted."""

    def __init__(self, x: np.ndarray, attr: np.ndarray, vid: np.ndarray, seg: np.ndarray, level: np.ndarray, segments: int, params: Params):
        self.segments, self.params, self.size = segments, params, 0
        self.x, self.attr, self.vid = np.ascontiguousarray(x, np.float64), np.asarray(attr, np.float64), np.asarray(vid, np.int64)
        self.seg, self.level = np.asarray(seg, np.int64), np.asarray(level, np.int64)
        self.square = np.einsum("ij,ij->i", self.x, self.x)
        self.entry = np.full(segments, -1, np.int64)
        self.layers = [Layer.empty(at, self.level, segments, params.cap(at)) for at in range(int(self.level.max()) + 1 if len(self.level) else 0)]
        self.spent = np.zeros((1, 5), np.int64)

    @property
    def dist(self) -> int:
        """Distances taken since ``spent`` was set."""
        return int(self.spent[:, DIST].sum())

    # Distances. A search's query q may be wider than the metric needs; ``rows`` says whose search each difference belongs to.
    def lengths(self, d: np.ndarray, rows: np.ndarray | None = None) -> np.ndarray:
        return np.sqrt(np.einsum("...j,...j->...", d, d))

    def closer(self, ids: np.ndarray, own: np.ndarray) -> np.ndarray:
        """``out[b, p, c]``: whether candidate c is nearer to candidate p than ``own[b, c]``; by products, and where these are too close to tell by differences."""
        d, own2 = self.x.shape[1], own**2
        # |p|^2 - 2 p c + |c|^2 - own^2 as one product of longer vectors.
        left, right = np.empty((*ids.shape, d + 2)), np.empty((*ids.shape, d + 2))
        right[..., :d] = self.x[ids]
        np.multiply(right[..., :d], -2.0, out=left[..., :d])
        square = self.square[ids]
        left[..., d], left[..., d + 1] = 1.0, square
        right[..., d], right[..., d + 1] = square - own2, 1.0
        over = np.matmul(left, np.swapaxes(right, 1, 2))
        out = over < 0
        tight = np.nonzero(np.abs(over, out=over) <= 1e-9 * (2 * square.max(axis=1) + own2.max(axis=1))[:, None, None])
        if len(tight[0]):
            b, p, c = tight
            out[tight] = self.lengths(self.x[ids[b, c]] - self.x[ids[b, p]]) < own[b, c]
        return out

    def beside(self, x: np.ndarray, square: np.ndarray, own: np.ndarray, at: np.ndarray) -> np.ndarray:
        """The row of ``closer`` for candidate ``at`` of each group."""
        rows = np.arange(len(x))
        p = x[rows, at]
        both = square + square[rows, at][:, None]
        d2, own2 = both - 2 * np.matmul(x, p[:, :, None])[..., 0], own**2
        out = d2 < own2
        tight = np.nonzero(np.abs(d2 - own2) <= 1e-9 * (own2 + both))
        if len(tight[0]):
            out[tight] = self.lengths(x[tight] - p[tight[0]]) < own[tight]
        return out

    def prune(self, own: np.ndarray, ids: np.ndarray, m: int) -> np.ndarray:
        """Which candidates of each row are kept, m at most: nearest first, one goes if it is nearer to a kept one than to the row's node. Rows rise by ``own``; inf ends them."""
        open_ = np.isfinite(own)
        width = int(open_.sum(axis=1).max()) if len(own) else 0
        keep = np.zeros(own.shape, bool)
        if not width:
            return keep
        open_ = open_[:, :width].copy()
        own, ids = np.where(open_, own[:, :width], 0.0), np.where(open_, ids[:, :width], 0)
        few = width <= 64
        if few:
            near = self.closer(ids, own)
        else:
            x, square = self.x[ids], self.square[ids]
        rows = np.arange(len(own))
        for _ in range(m):
            some = open_.any(axis=1)
            if not some.any():
                break
            # Each row's next one is the first that none has closed; rows without any stay as they are.
            at = open_.argmax(axis=1)
            keep[rows[some], at[some]] = True
            open_[rows, at] = False
            self.spent[0, DIST] += int(open_.sum())
            open_ &= ~(near[rows, at] if few else self.beside(x, square, own, at))
        return keep

    def spread(self, q: np.ndarray, start: np.ndarray, first: np.ndarray, width: int, look: Callable, accept: Callable | None = None, stop: str = "full", wave: int = 1) -> tuple[np.ndarray, np.ndarray]:
        """Best-first searches, one per row of q from its start at distance ``first``: (distances, nodes) of the nearest ``width`` accepted nodes that each meets, sorted, inf and -1 behind them.

        ``look(rows, nodes)`` gives the neighbours of an expanded node of each row, padded by -1; ``accept(rows, nodes)`` which nodes may be results. A search expands
        its ``wave`` nearest candidates at a time. With ``stop='full'`` it ends once its nearest candidate is farther than the worst of ``width`` results, with
        ``'worst'`` as soon as that is farther than the worst result however few there are. What is spent goes to the rows of ``self.spent``.
        """
        b, n = len(q), len(self.vid)
        spent = self.spent if len(self.spent) == b else np.zeros((b, 5), np.int64)
        seen = np.zeros((b, n), bool)
        best_d, best = np.full((b, width), np.inf), np.full((b, width), -1, np.int64)
        room = max(64, 2 * wave)
        cand_d, cand, fill = np.full((b, room), np.inf), np.full((b, room), -1, np.int64), np.ones(b, np.int64)
        rows = np.arange(b)
        seen[rows, start], cand_d[:, 0], cand[:, 0] = True, first, start
        ok = np.ones(b, bool) if accept is None else accept(rows, start)
        best_d[ok, 0], best[ok, 0] = first[ok], start[ok]
        # The worst result while a row is full, and the worst of any number.
        worst = best_d.max(axis=1)
        bound = worst.copy() if stop == "full" else np.where(ok, first, np.inf)
        live = rows
        while len(live):
            c = cand_d[live]
            if wave == 1:
                at = c.argmin(axis=1)[:, None]
            else:
                at = np.argpartition(c, wave - 1, axis=1)[:, :wave] if wave < c.shape[1] else np.broadcast_to(np.arange(c.shape[1]), c.shape)
            d = np.take_along_axis(c, at, axis=1)
            go = np.isfinite(d) & (d <= bound[live][:, None])
            a, w = np.nonzero(go)
            if not len(a):
                break
            whose, place = live[a], at[a, w]
            node = cand[whose, place]
            cand_d[whose, place] = np.inf
            live = live[go.any(axis=1)]
            near = look(whose, node)
            hit = near >= 0
            spent[:, HOPS] += np.bincount(whose, minlength=b)
            r, new = whose[np.nonzero(hit)[0]], near[hit].astype(np.int64)
            spent[:, EDGES] += np.bincount(r, minlength=b)
            fresh = ~seen[r, new]
            r, new = r[fresh], new[fresh]
            if wave > 1 and len(r):
                key = np.unique(r * n + new)
                r, new = key // n, key % n
            if not len(r):
                continue
            seen[r, new] = True
            d = self.lengths(self.x[new] - q[r], r)
            met = np.bincount(r, minlength=b)
            spent[:, DIST] += met
            spent[:, VISITED] += met
            good = d < worst[r]
            r, new, d = r[good], new[good], d[good]
            if not len(r):
                continue
            met = np.bincount(r, minlength=b)
            if int((fill + met).max()) > cand_d.shape[1]:
                cand_d[cand_d > bound[:, None]] = np.inf
                order = np.argsort(cand_d, axis=1, kind="stable")
                cand_d, cand = np.take_along_axis(cand_d, order, axis=1), np.take_along_axis(cand, order, axis=1)
                fill = np.isfinite(cand_d).sum(axis=1)
                need = int((fill + met).max())
                if need > cand_d.shape[1] // 2:
                    more = max(need, cand_d.shape[1])
                    cand_d, cand = np.pad(cand_d, ((0, 0), (0, more)), constant_values=np.inf), np.pad(cand, ((0, 0), (0, more)), constant_values=-1)
            begin = np.cumsum(met) - met
            place = fill[r] + np.arange(len(r)) - begin[r]
            cand_d[r, place], cand[r, place] = d, new
            fill = fill + met
            if accept is not None:
                ok = accept(r, new)
                spent[:, BRIDGE] += np.bincount(r[~ok], minlength=b)
                r, new, d = r[ok], new[ok], d[ok]
                if not len(r):
                    continue
                met = np.bincount(r, minlength=b)
                begin = np.cumsum(met) - met
            some = np.flatnonzero(met)
            most = int(met.max())
            back = np.full(b, -1, np.int64)
            back[some] = np.arange(len(some))
            all_d, all_n = np.full((len(some), width + most), np.inf), np.full((len(some), width + most), -1, np.int64)
            all_d[:, :width], all_n[:, :width] = best_d[some], best[some]
            place = width + np.arange(len(r)) - begin[r]
            all_d[back[r], place], all_n[back[r], place] = d, new
            top = np.argpartition(all_d, width - 1, axis=1)[:, :width]
            best_d[some], best[some] = np.take_along_axis(all_d, top, axis=1), np.take_along_axis(all_n, top, axis=1)
            worst[some] = best_d[some].max(axis=1)
            if stop == "full":
                bound = worst
            else:
                bound[some] = np.where(np.isfinite(best_d[some]), best_d[some], -np.inf).max(axis=1)
        order = np.lexsort((self.vid[best], best_d), axis=1)
        return np.take_along_axis(best_d, order, axis=1), np.take_along_axis(best, order, axis=1)

    # Construction.
    def insert(self, v: int) -> None:
        """Add node v: in every segment descend to its level, link on each layer from there, then the chain and the masks. The segments are searched side by side."""
        p, q, i, top = self.params, self.x[v], int(self.seg[v]), int(self.level[v])
        j = np.flatnonzero(self.entry >= 0)
        if len(j) and p.candidates == "exact":
            for layer in range(top, -1, -1):
                have = self.layers[layer].node
                have = have[: np.searchsorted(have, v)]
                d = self.lengths(self.x[have] - q)
                self.spent[0, DIST] += len(have)
                for s in j:
                    own = np.flatnonzero(self.seg[have] == s)
                    own = own[np.lexsort((self.vid[have[own]], d[own]))][: p.ef_cons]
                    if len(own):
                        self.link(layer, v, np.array([s]), d[own][None], have[own][None].astype(np.int64))
        elif len(j):
            start = self.entry[j]
            high, first = self.level[start], self.lengths(self.x[start] - q)
            self.spent[0, DIST] += len(j)
            for layer in range(int(high.max()), -1, -1):
                at = np.flatnonzero(high >= layer)
                width = p.ef_cons if layer <= top else 1
                self.spent, kept = np.zeros((len(at), 5), np.int64), self.spent
                d, found = self.spread(np.broadcast_to(q, (len(at), len(q))), start[at], first[at], width, self.chunks(layer, j[at]), wave=p.waves(width))
                self.spent = kept + self.spent.sum(axis=0)
                start[at], first[at] = found[:, 0], d[:, 0]
                if layer <= top:
                    self.link(layer, v, j[at], d, found)
        if self.entry[i] < 0 or top > self.level[self.entry[i]] or p.entry == "last" and top == self.level[self.entry[i]]:
            self.entry[i] = v
        self.thread(v)
        for layer in range(top + 1):
            self.set_mask(layer, v)
        self.size += 1

    def chunks(self, layer: int, segs: np.ndarray) -> Callable:
        """Neighbours inside one segment for each row."""
        g = self.layers[layer]
        return lambda rows, nodes: g.ids[g.row[nodes], segs[rows]]

    def link(self, layer: int, v: int, segs: np.ndarray, d: np.ndarray, found: np.ndarray) -> None:
        """Mutual edges between v and the pruned candidates of each segment; full chunks are pruned again, and what they lose leaves the masks."""
        g, i, m, cap = self.layers[layer], int(self.seg[v]), self.params.m, self.params.cap(layer)
        keep = self.prune(d, found, m)
        r, c = np.nonzero(keep)
        if not len(r):
            return
        n = keep.sum(axis=1)
        place = np.arange(len(r)) - (np.cumsum(n) - n)[r]
        mine = g.row[v]
        g.ids[mine, segs[r], place], g.dist[mine, segs[r], place] = found[r, c], d[r, c]
        ends = g.row[found[r, c]]
        ids = np.concatenate([g.ids[ends, i], np.full((len(ends), 1), v, np.int32)], axis=1)
        dist = np.concatenate([g.dist[ends, i], d[r, c][:, None]], axis=1)
        mask = np.concatenate([g.mask[ends, i], np.zeros((len(ends), 1), bool)], axis=1)
        order = np.argsort(dist, axis=1, kind="stable")
        ids, dist, mask = (np.take_along_axis(a, order, axis=1) for a in (ids, dist, mask))
        full = np.flatnonzero(np.isfinite(dist[:, cap]))
        if len(full):
            stay = self.prune(dist[full], ids[full], cap)
            order = np.argsort(~stay, axis=1, kind="stable")
            stay = np.take_along_axis(stay, order, axis=1)
            ids[full] = np.where(stay, np.take_along_axis(ids[full], order, axis=1), -1)
            dist[full] = np.where(stay, np.take_along_axis(dist[full], order, axis=1), np.inf)
            mask[full] = stay & np.take_along_axis(mask[full], order, axis=1)
        g.ids[ends, i], g.dist[ends, i], g.mask[ends, i] = ids[:, :cap], dist[:, :cap], mask[:, :cap]

    def _masked(self, layer: int, rows: np.ndarray) -> None:
        """Of each row's edges over all chunks those that pruning keeps."""
        g = self.layers[layer]
        dist = g.dist[rows].reshape(len(rows), -1)
        order = np.argsort(dist, axis=1, kind="stable")
        keep = self.prune(np.take_along_axis(dist, order, axis=1), np.take_along_axis(g.ids[rows].reshape(len(rows), -1), order, axis=1), self.params.masked())
        out = np.zeros(keep.shape, bool)
        np.put_along_axis(out, order, keep, axis=1)
        g.mask[rows] = out.reshape(g.mask[rows].shape)

    def set_mask(self, layer: int, v: int) -> None:
        g, mine = self.layers[layer], self.layers[layer].row[v]
        self._masked(layer, np.array([mine]))
        ends = g.row[g.ids[mine][g.mask[mine]]]
        back = g.ids[ends, int(self.seg[v])] == v
        ends, back = ends[back.any(axis=1)], back[back.any(axis=1)]
        g.mask[ends, int(self.seg[v])] |= back
        over = ends[g.mask[ends].sum(axis=(1, 2)) > self.params.masked()]
        if len(over):
            self._masked(layer, over)

    # The chain.
    def _before(self, attr: float, vid: int) -> tuple[list[int], int]:
        """On each layer the last node before (attr, vid), -1 if it is the first, from the sparsest layer down; and the steps taken."""
        cur, out, steps = -1, [-1] * len(self.layers), 0
        for layer in range(len(self.layers) - 1, -1, -1):
            g = self.layers[layer]
            after = g.next[g.row[cur]] if cur >= 0 else g.head
            while after >= 0 and (self.attr[after], self.vid[after]) < (attr, vid):
                cur, steps = int(after), steps + 1
                after = g.next[g.row[cur]]
            out[layer] = cur
        return out, steps

    def thread(self, v: int) -> None:
        """Put v into the chain of each of its layers."""
        before, _ = self._before(self.attr[v], self.vid[v])
        for layer in range(int(self.level[v]) + 1):
            g, o = self.layers[layer], before[layer]
            if o >= 0:
                g.next[g.row[v]], g.next[g.row[o]] = g.next[g.row[o]], v
            else:
                g.next[g.row[v]], g.head = g.head, v

    def chain(self, layer: int = 0) -> list[int]:
        """Nodes of a layer in attribute order."""
        out, v = [], self.layers[layer].head if self.layers else -1
        while v >= 0:
            out.append(int(v))
            v = self.layers[layer].next[self.layers[layer].row[v]]
        return out

    # Searches of many queries side by side. ``also`` (rows, nodes) tests further conditions on results.
    def blocks(self, n: int) -> list[np.ndarray]:
        """Queries in groups whose marks stay bounded."""
        return np.array_split(np.arange(n), max(1, -(-n * max(1, len(self.vid)) // MARKS), -(-n // 256))) if n else []

    def first_from(self, lo: float) -> tuple[int | None, int]:
        """The id of the first object at or above ``lo``, by descending the chain, and the steps taken."""
        if not self.layers:
            return None, 0
        before, steps = self._before(lo, -(1 << 62))
        v = self.layers[0].next[self.layers[0].row[before[0]]] if before[0] >= 0 else self.layers[0].head
        return (int(self.vid[v]) if v >= 0 else None), steps

    def in_range(self, lo: float, hi: float) -> tuple[np.ndarray, int]:
        """Nodes of a range: descend the chain to the first, then follow it; and the steps taken."""
        if not self.layers:
            return np.zeros(0, np.int64), 0
        before, steps = self._before(lo, -(1 << 62))
        g, out = self.layers[0], []
        v = g.next[g.row[before[0]]] if before[0] >= 0 else g.head
        while v >= 0 and self.attr[v] <= hi:
            out.append(int(v))
            v = g.next[g.row[v]]
        return np.array(out, np.int64), steps + len(out)

    def pre_many(self, q: np.ndarray, lo: np.ndarray, hi: np.ndarray, k: int, also: Callable | None = None) -> list[list[Edge]]:
        """All objects of each range, found along the chain: exact."""
        out, self.spent, same = [], np.zeros((len(q), 5), np.int64), (None, None)
        for b in np.lexsort((hi, lo)):
            # Queries of one range follow the chain once.
            if same[0] != (lo[b], hi[b]):
                same = (lo[b], hi[b]), self.in_range(lo[b], hi[b])
            ids, steps = same[1]
            if also is not None:
                ids = ids[also(np.full(len(ids), b), ids)]
            d = self.lengths(self.x[ids] - q[b], np.full(len(ids), b))
            self.spent[b, [DIST, VISITED, HOPS]] = len(ids), len(ids), steps
            order = np.lexsort((self.vid[ids], d))[:k]
            out.append((int(b), [(float(d[i]), int(ids[i])) for i in order]))
        return [found for _, found in sorted(out, key=lambda one: one[0])]

    def layered(self, q: np.ndarray, ep: np.ndarray, width: int, look: Callable[[int], Callable], accept: Callable | None = None, stop: str = "full") -> tuple[np.ndarray, np.ndarray]:
        """Descend from each row's entry with a beam of one, then search layer 0. ``self.spent`` has a row for each query."""
        start, high = ep.copy(), self.level[ep]
        first = self.lengths(self.x[ep] - q, np.arange(len(q)))
        spent = self.spent
        spent[:, DIST] += 1
        for layer in range(int(high.max()), 0, -1):
            at = np.flatnonzero(high >= layer)
            self.spent = np.zeros((len(at), 5), np.int64)
            step = look(layer)
            d, found = self.spread(q[at], start[at], first[at], 1, lambda rows, nodes: step(at[rows], nodes))
            spent[at] += self.spent
            start[at], first[at] = found[:, 0], d[:, 0]
        self.spent = np.zeros((len(q), 5), np.int64)
        out = self.spread(q, start, first, width, look(0), accept, stop)
        spent += self.spent
        self.spent = spent
        return out

    def masked(self, layer: int) -> Callable:
        """Neighbours in the graph of all nodes."""
        g = self.layers[layer]

        def look(rows: np.ndarray, nodes: np.ndarray) -> np.ndarray:
            r = g.row[nodes]
            return np.where(g.mask[r], g.ids[r], -1).reshape(len(r), -1)

        return look

    def picked(self, layer: int, hit: np.ndarray, m: int, pick: str, taken: np.ndarray) -> Callable:
        """Neighbours in the segments that each row's ``hit`` marks: the first ceil(m / segments) of each chunk, or the m nearest of all, whose distances count as ``taken``."""
        g = self.layers[layer]
        share = -(-m // np.maximum(1, hit.sum(axis=1)))
        place = np.arange(g.ids.shape[2])

        def look(rows: np.ndarray, nodes: np.ndarray) -> np.ndarray:
            r = g.row[nodes]
            if pick == "chunk":
                on = hit[rows][:, :, None] & (place < share[rows][:, None, None])
                return np.where(on, g.ids[r], -1).reshape(len(r), -1)
            ids = np.where(hit[rows][:, :, None], g.ids[r], -1).reshape(len(r), -1)
            d = np.where(ids >= 0, g.dist[r].reshape(len(r), -1), np.inf)
            # The strategy takes the distances between a node and all of these neighbours.
            np.add.at(taken, rows, (ids >= 0).sum(axis=1))
            near = np.argsort(d, axis=1, kind="stable")[:, :m]
            return np.take_along_axis(ids, near, axis=1)

        return look

    def _results(self, d: np.ndarray, found: np.ndarray, k: int, ok: np.ndarray | None = None) -> list[list[Edge]]:
        out = []
        for b in range(len(d)):
            use = found[b] >= 0 if ok is None else (found[b] >= 0) & ok[b]
            at = np.flatnonzero(use)[:k]
            out.append(list(zip(d[b, at].tolist(), found[b, at].tolist(), strict=True)))
        return out

    def post_many(self, q: np.ndarray, lo: np.ndarray, hi: np.ndarray, k: int, ef: int, grow: bool = False, also: Callable | None = None) -> list[list[Edge]]:
        """Search the graph of all nodes, then filter; ``grow`` doubles the beam of each row until it has k results that the last doubling left as they were, or has met all nodes."""
        out: list[list[Edge] | None] = [None] * len(q)
        spent = np.zeros((len(q), 5), np.int64)
        have = self.entry[self.entry >= 0]
        todo = np.arange(len(q)) if len(have) else np.zeros(0, np.int64)
        while len(todo):
            ep = have[np.lexsort((self.seg[have], -self.level[have]))[0]]
            again = []
            for part in self.blocks(len(todo)):
                at = todo[part]
                self.spent = np.zeros((len(at), 5), np.int64)
                d, found = self.layered(q[at], np.full(len(at), ep), ef, self.masked)
                ok = (self.attr[found] >= lo[at][:, None]) & (self.attr[found] <= hi[at][:, None])
                if also is not None:
                    ok &= also(np.repeat(at, found.shape[1]), found.ravel()).reshape(found.shape)
                spent[at] += self.spent
                for b, got in zip(at, self._results(d, found, k, ok), strict=True):
                    if grow and ef < self.size and (len(got) < k or got != out[b]):
                        again.append(b)
                    out[b] = got
            todo, ef = np.array(again, np.int64), 2 * ef
        self.spent = spent
        return [got or [] for got in out]

    def hybrid_many(self, q: np.ndarray, lo: np.ndarray, hi: np.ndarray, k: int, ef: int, hit: np.ndarray, m: int, pick: str = "chunk", stop: str = "full", scope: str = "hit", also: Callable | None = None) -> list[list[Edge]]:
        """Search the chunks of the segments that each range meets (``hit``, a row of marks for each query); objects outside the range lead on but aren't results.

        The start is the highest entry of these segments, or with ``scope='all'`` that of all segments."""
        out: list[list[Edge]] = [[] for _ in range(len(q))]
        spent = np.zeros((len(q), 5), np.int64)
        height = np.where(self.entry >= 0, self.level[self.entry], -1) if len(self.level) else np.full(self.segments, -1)
        reach = np.where(hit if scope == "hit" else hit.any(axis=1)[:, None], height, -1)
        some = np.flatnonzero(reach.max(axis=1) >= 0) if reach.size else np.zeros(0, np.int64)
        for part in self.blocks(len(some)):
            at = some[part]
            ep = self.entry[reach[at].argmax(axis=1)]
            self.spent = np.zeros((len(at), 5), np.int64)

            def accept(rows: np.ndarray, nodes: np.ndarray, at: np.ndarray = at) -> np.ndarray:
                whose = at[rows]
                ok = (self.attr[nodes] >= lo[whose]) & (self.attr[nodes] <= hi[whose])
                return ok & also(whose, nodes) if also is not None else ok

            marks, taken = hit[at], np.zeros(len(at), np.int64)
            d, found = self.layered(q[at], ep, ef, lambda layer, marks=marks, taken=taken: self.picked(layer, marks, m, pick, taken), accept, stop)
            spent[at] = self.spent
            spent[at, DIST] += taken
            for b, got in zip(at, self._results(d, found, k), strict=True):
                out[b] = got
        self.spent = spent
        return out

    # One query.
    def pre(self, q, lo, hi, k) -> list[Edge]:
        return self.pre_many(np.asarray(q)[None], np.array([lo]), np.array([hi]), k)[0]

    def post(self, q, lo, hi, k, ef, grow=False) -> list[Edge]:
        return self.post_many(np.asarray(q)[None], np.array([lo]), np.array([hi]), k, ef, grow)[0]

    def hybrid(self, q, lo, hi, k, ef, segs, m, pick="chunk", stop="full", scope="hit") -> list[Edge]:
        hit = np.zeros((1, self.segments), bool)
        hit[0, list(segs)] = True
        return self.hybrid_many(np.asarray(q)[None], np.array([lo]), np.array([hi]), k, ef, hit, m, pick, stop, scope)[0]

    # What is there.
    def edges(self, layer: int = 0) -> set[tuple[int, int]]:
        if layer >= len(self.layers):
            return set()
        g = self.layers[layer]
        r, j, c = np.nonzero(g.ids >= 0)
        return set(zip(g.node[r].tolist(), g.ids[r, j, c].tolist(), strict=True))

    def edge_count(self) -> int:
        return sum(int((g.ids >= 0).sum()) for g in self.layers)

    def bytes(self) -> int:
        """32-bit edges and successors, a bit of mask for each edge."""
        return int(self.edge_count() * (4 + 1 / 8) + 4 * sum(len(g.node) for g in self.layers))

    def problems(self) -> list[str]:
        """What breaks the structure; nothing, if all is well."""
        out = []
        for layer, g in enumerate(self.layers):
            for r, v in enumerate(g.node[: np.searchsorted(g.node, self.size)]):
                for j in range(self.segments):
                    ids, d = g.ids[r, j][g.ids[r, j] >= 0], g.dist[r, j][g.ids[r, j] >= 0]
                    if len(set(ids.tolist())) != len(ids) or (np.diff(d) < 0).any() or (g.ids[r, j][: len(ids)] < 0).any():
                        out.append(f"chunk {layer}/{v}/{j} is unsorted, repeats or has gaps")
                    if any(o == v or self.seg[o] != j or self.level[o] < layer for o in ids):
                        out.append(f"chunk {layer}/{v}/{j} has a wrong end")
                if (g.mask[r] & (g.ids[r] < 0)).any() or g.mask[r].sum() > self.params.masked():
                    out.append(f"mask {layer}/{v}")
            order = self.chain(layer)
            on = [int(v) for v in np.lexsort((self.vid, self.attr)) if self.level[v] >= layer and v < self.size]
            if order != on:
                out.append(f"chain {layer}")
        for j, ep in enumerate(self.entry):
            if ep >= 0 and (self.level[: self.size][self.seg[: self.size] == j] > self.level[ep]).any():
                out.append(f"entry of {j} isn't on its top layer")
        return out

    # Storage.
    def grown(self, x: np.ndarray, attr: np.ndarray, vid: np.ndarray, seg: np.ndarray, level: np.ndarray) -> Graph:
        """The same graph with room for more nodes behind its own, which are inserted next."""
        both = lambda a, b: np.concatenate([a, b])
        out = Graph(both(self.x, np.asarray(x, np.float64).reshape(len(vid), self.x.shape[1])), both(self.attr, attr), both(self.vid, vid), both(self.seg, seg), both(self.level, level), self.segments, self.params)
        out.entry, out.size = np.array(self.entry), self.size
        for old, new in zip(self.layers, out.layers, strict=False):
            r = len(old.node)
            new.ids[:r], new.dist[:r], new.mask[:r], new.next[:r], new.head = old.ids, old.dist, old.mask, old.next, old.head
        return out

    def arrays(self) -> dict[str, np.ndarray]:
        out = {"x": self.x, "attr": self.attr, "vid": self.vid, "seg": self.seg.astype(np.int32), "level": self.level.astype(np.int32), "entry": self.entry, "histogram": histogram(self.attr)}
        for i, g in enumerate(self.layers):
            out |= {f"{i}.ids": g.ids, f"{i}.dist": g.dist, f"{i}.mask": g.mask, f"{i}.next": g.next, f"{i}.head": np.array([g.head])}
        return out

    @classmethod
    def of_arrays(cls, a: dict[str, np.ndarray], segments: int, params: Params) -> Graph:
        """A graph over stored arrays; they may be read-only maps of a file, which searches touch where they go."""
        g = cls.__new__(cls)
        g.segments, g.params, g.size = segments, params, len(a["vid"])
        g.x, g.attr, g.vid, g.seg, g.level, g.entry = a["x"], a["attr"], a["vid"], a["seg"].astype(np.int64), a["level"].astype(np.int64), a["entry"]
        g.square, g.spent, g.layers = np.zeros(0), np.zeros((1, 5), np.int64), []
        while f"{len(g.layers)}.ids" in a:
            i = len(g.layers)
            on = g.level >= i
            g.layers.append(Layer(np.where(on, np.cumsum(on) - 1, -1).astype(np.int32), np.flatnonzero(on).astype(np.int32), a[f"{i}.ids"], a[f"{i}.dist"], a[f"{i}.mask"], a[f"{i}.next"], int(a[f"{i}.head"][0])))
        return g


def histogram(attr: np.ndarray, buckets: int = 64) -> np.ndarray:
    """(lo, hi, n) of about equally full buckets; equal attributes share one."""
    a = np.sort(attr)
    if not len(a):
        return np.zeros((0, 3))
    starts = sorted({int(np.searchsorted(a, a[-(-i * len(a) // buckets)])) for i in range(buckets) if -(-i * len(a) // buckets) < len(a)})
    ends = [*starts[1:], len(a)]
    return np.array([(a[s], a[e] if e < len(a) else a[-1], e - s) for s, e in zip(starts, ends, strict=True)])


def estimated(hist: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """The number of objects in each range: of each bucket the share that the range covers, as if attributes lay evenly in it."""
    a, b, n = hist[:, 0], hist[:, 1], hist[:, 2]
    wide = np.where(b > a, b - a, 1.0)
    part = (np.minimum(hi[:, None], b) - np.maximum(lo[:, None], a)) / wide
    met = (hi[:, None] >= a) & (lo[:, None] <= b)
    return (np.where(met, np.where(b > a, np.clip(part, 0, 1), 1.0), 0.0) * n).sum(axis=1)


def build(x: np.ndarray, attr: np.ndarray, vid: np.ndarray, seg: np.ndarray, level: np.ndarray, segments: int, params: Params) -> Graph:
    g = Graph(x, attr, vid, seg, level, segments, params)
    for v in range(len(g.vid)):
        g.insert(v)
    return g
