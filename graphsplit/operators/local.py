"""Kernels for graphs that fit a task: arrays, no Spark.

Rounds are supersteps as in the distributed operators: nodes of a class decide on the state at the sub-round's start,
capacity is granted in order of gain, and neighbours do not move together where the cut must not rise.
"""

from __future__ import annotations

import time
from contextlib import contextmanager
from dataclasses import dataclass, field
from heapq import heapify, heappop, heappush, heapreplace

import numpy as np

from ..functions import rules
from ..functions.hashing import mix


@dataclass
class Options:
    """Everything that varies between variants of the scheme."""

    c: int = 200
    eps: float = 0.03
    rounds: int = 5
    tries: int = 2
    repeats: int = 2
    pool: tuple[str, ...] = ("random", "bfs", "grow")
    adaptive: bool = True
    order: str = "bucket"  # bucket, degree, random, id
    classes: int = 4
    enforce: str = "strict"  # soft, strict, sampled
    active: bool = True
    two_hop: str = "pairs"  # pairs, groups, off
    final_order: str = "twice"  # once, twice
    conflict: str = "independent"  # independent, none
    slack: str = "adaptive"  # adaptive, fixed
    min_shrink: float = 0.05
    lanes: int = 1
    cores: int = 1  # counts in the attribution of phases only
    seed: int = 0
    log: list = field(default_factory=list)
    phases: dict = field(default_factory=dict)

    def spec(self) -> dict:
        """What varies, without what a run writes."""
        return {f: getattr(self, f) for f in self.__dataclass_fields__ if f not in ("log", "phases")}

    @contextmanager
    def timed(self, phase: str, n: int | None = None):
        """Add seconds to a phase; splits and refinement of graphs of at most 2 * cores * C nodes count as the bottom."""
        start = time.perf_counter()
        yield
        name = "bottom" if n is not None and n <= 2 * self.cores * self.c else phase
        self.phases[name] = self.phases.get(name, 0.0) + time.perf_counter() - start


class Csr:
    """A graph as arrays: node weights, and edges in both directions sorted by source.

    Ends and weights take four bytes each where they fit, and steps that look at all edges go by ``spans``, so that a task can hold large graphs.
    """

    def __init__(self, nw: np.ndarray, src: np.ndarray, dst: np.ndarray, w: np.ndarray):
        order = np.lexsort((dst, src))
        self._set(nw, src[order], dst[order], w[order])

    def _set(self, nw: np.ndarray, src: np.ndarray, dst: np.ndarray, w: np.ndarray, ptr: np.ndarray | None = None) -> Csr:
        self.nw = nw.astype(np.int64, copy=False)
        self.n, self.m = len(nw), len(src)
        self.dst = dst.astype(np.int32, copy=False)
        self.w = w if w.dtype == np.int32 else w.astype(np.int32 if self.m == 0 or int(w.max()) < 1 << 31 else np.int64)
        self.ptr = np.searchsorted(src, np.arange(self.n + 1)) if ptr is None else ptr
        self._src = src.astype(np.int32, copy=False) if self.m <= SPAN else None
        self.total = int(self.nw.sum())
        self.heaviest = int(self.nw.max()) if self.n else 0
        return self

    @classmethod
    def of_sorted(cls, nw: np.ndarray, src: np.ndarray, dst: np.ndarray, w: np.ndarray, ptr: np.ndarray | None = None) -> Csr:
        """From edges in both directions that are sorted by source and target."""
        return cls.__new__(cls)._set(nw, src, dst, w, ptr)

    @classmethod
    def of_pairs(cls, nw: np.ndarray, a: np.ndarray, b: np.ndarray, w: np.ndarray) -> Csr:
        """From each edge once; ranges of sources are sorted one after the other."""
        n = len(nw)
        degree = np.bincount(a, minlength=n) + np.bincount(b, minlength=n)
        ptr = np.r_[0, np.cumsum(degree)]
        dst, wgt = (np.empty(2 * len(a), dtype=t) for t in (np.int32, np.int32 if not len(w) or int(w.max()) < 1 << 31 else np.int64))
        for first, last in ranges(degree, 2 * SPAN):
            x, y = np.flatnonzero((a >= first) & (a < last)), np.flatnonzero((b >= first) & (b < last))
            s, t, v = (np.r_[p[x], q[y]].astype(np.int64) for p, q in ((a, b), (b, a), (w, w)))
            order = np.argsort(s * n + t)
            at = slice(ptr[first], ptr[last])
            dst[at], wgt[at] = t[order], v[order]
        return cls.of_sorted(nw, np.repeat(np.arange(n, dtype=np.int32), degree), dst, wgt, ptr)

    @property
    def src(self) -> np.ndarray:
        """The source of each edge; large graphs do not keep it."""
        return np.repeat(np.arange(self.n, dtype=np.int32), self.degree) if self._src is None else self._src

    @property
    def degree(self) -> np.ndarray:
        return np.diff(self.ptr)

    def edges_of(self, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Positions of the edges of ``nodes``, and how many each has."""
        start, many = self.ptr[nodes], self.ptr[nodes + 1] - self.ptr[nodes]
        before = np.cumsum(many) - many
        return np.repeat(start - before, many) + np.arange(int(many.sum())), many

    def spans(self, nodes: np.ndarray):
        """``nodes`` in runs of at most ``SPAN`` edges, or of one node."""
        for first, last in ranges(self.ptr[nodes + 1] - self.ptr[nodes], SPAN):
            yield nodes[first:last]

    def next_to(self, nodes: np.ndarray) -> np.ndarray:
        """A mask: which nodes have a neighbour among ``nodes`` (a mask)."""
        out = np.zeros(self.n, dtype=bool)
        for v in self.spans(np.flatnonzero(nodes)):
            out[self.dst[self.edges_of(v)[0]]] = True
        return out

    def near(self):
        """A function that gives the (neighbour, weight) pairs of a node; small graphs are held as lists."""
        if self.m <= SMALL:
            if not hasattr(self, "_near"):
                ptr, pairs = self.ptr.tolist(), list(zip(self.dst.tolist(), self.w.tolist(), strict=True))
                self._near = [pairs[i:j] for i, j in zip(ptr[:-1], ptr[1:], strict=True)]
            return self._near.__getitem__
        ptr, dst, w = self.ptr, self.dst, self.w
        return lambda v: zip(dst[ptr[v] : ptr[v + 1]].tolist(), w[ptr[v] : ptr[v + 1]].tolist(), strict=True)

    def gains(self, side: list[int]) -> list[int]:
        """What the cut falls by if a node changes to the other of two sides."""
        if self.m <= FEW:
            near = self.near()
            return [sum(w if side[u] != s else -w for u, w in near(v)) for v, s in enumerate(side)]
        part, out, src = np.array(side), np.zeros(self.n, dtype=np.int64), self.src
        for i in range(0, self.m, SPAN):
            at = slice(i, i + SPAN)
            out += np.bincount(src[at], weights=np.where(part[src[at]] != part[self.dst[at]], self.w[at], -self.w[at]), minlength=self.n).astype(np.int64)
        return out.tolist()

    def cut(self, part: np.ndarray) -> int:
        if self.m <= SPAN:
            return int(self.w[part[self.src] != part[self.dst]].sum()) // 2
        src = self.src
        return sum(int(self.w[at][part[src[at]] != part[self.dst[at]]].sum()) for at in (slice(i, i + SPAN) for i in range(0, self.m, SPAN))) // 2

    def block_weights(self, part: np.ndarray, k: int) -> np.ndarray:
        return np.bincount(part, weights=self.nw, minlength=k).astype(np.int64)

    def induced(self, nodes: np.ndarray) -> Csr:
        """The subgraph of ascending ``nodes``, renumbered."""
        where = np.full(self.n, -1, dtype=np.int64)
        where[nodes] = np.arange(len(nodes))
        keep = (where[self.src] >= 0) & (where[self.dst] >= 0)
        return Csr(self.nw[nodes], where[self.src[keep]], where[self.dst[keep]], self.w[keep])

    def blocks(self, part: np.ndarray, k: int):
        """(nodes, subgraph) of each block in turn, as ``induced`` gives them; all edges are dealt to blocks once."""
        order = np.argsort(part, kind="stable")
        first = np.searchsorted(part[order], np.arange(k + 1))
        place = np.empty(self.n, dtype=np.int64)
        place[order] = np.arange(self.n)
        inner = np.flatnonzero(_same(self, part))
        # Edges in order of (block, source, target): those of a source stay together, so sources are put in order of their places.
        inside = np.bincount(self.src[inner], minlength=self.n)
        begin = np.cumsum(inside) - inside
        run = inside[order]
        ends = np.r_[0, np.cumsum(run)]
        inner = inner[np.repeat(begin[order] - ends[:-1], run) + np.arange(len(inner))]
        src, dst, w = place[self.src[inner]].astype(np.int32), place[self.dst[inner]].astype(np.int32), self.w[inner]
        for b in range(k):
            i, j = int(first[b]), int(first[b + 1])
            at = slice(ends[i], ends[j])
            yield order[i:j], Csr.of_sorted(self.nw[order[i:j]], src[at] - np.int32(i), dst[at] - np.int32(i), w[at], ends[i : j + 1] - ends[i])

    def contract(self, label: np.ndarray) -> tuple[Csr, np.ndarray]:
        """Clusters as nodes, parallel edges summed, inner edges dropped; and the coarse node of each node."""
        _, parent = np.unique(label, return_inverse=True)
        n = int(parent.max()) + 1 if self.n else 0
        found = []
        order = np.argsort(parent, kind="stable")
        count = np.bincount(parent, weights=self.degree, minlength=n).astype(np.int64)
        first = np.searchsorted(parent[order], np.arange(n + 1))
        for x, y in ranges(count, SPAN):
            e, many = self.edges_of(order[first[x] : first[y]])
            a, b = np.repeat(parent[order[first[x] : first[y]]], many), parent[self.dst[e]]
            keep = a != b
            key, w = sum_by((a[keep] - x) * n + b[keep], self.w[e[keep]], (y - x) * n)
            found.append(((key // n + x).astype(np.int32), (key % n).astype(np.int32), w.astype(np.int32) if not len(w) or int(w.max()) < 1 << 31 else w))
        src, dst, w = (np.concatenate(c) if c else np.zeros(0, dtype=np.int64) for c in (list(zip(*found, strict=True)) or [(), (), ()]))
        del found
        return Csr.of_sorted(np.bincount(parent, weights=self.nw, minlength=n).astype(np.int64), src, dst, w), parent


#: Edges that a step looks at together; edges that are held as lists, and summed without arrays.
SPAN, SMALL, FEW = 1 << 19, 1 << 16, 400
#: Bits of the number of nodes that share a bound in the k-way search.
RUN = 6


def ranges(sizes: np.ndarray, most: int):
    """(first, last) of runs of rows whose sizes sum to at most ``most``, or of one row."""
    upto, first = sizes.cumsum(), 0
    if len(upto) and upto[-1] <= most:
        yield 0, len(sizes)
        return
    while first < len(sizes):
        last = max(first + 1, int(np.searchsorted(upto, (upto[first - 1] if first else 0) + most, side="right")))
        yield first, last
        first = last


def sum_by(key: np.ndarray, w: np.ndarray, keys: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys (below ``keys``) in ascending order, and the sum of their weights; where both fit a word they are sorted as one."""
    if not len(key):
        return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)
    bits = int(w.max()).bit_length()
    if int(w.min()) >= 0 and int(keys).bit_length() + bits <= 62:
        both = (key.astype(np.int64) << bits) | w
        both.sort()
        key, w = both >> bits, both & ((1 << bits) - 1)
    else:
        order = np.argsort(key, kind="stable")
        key, w = key[order], w[order].astype(np.int64)
    first = changes(key)
    return key[first], np.add.reduceat(w, first)


def _same(g: Csr, part: np.ndarray) -> np.ndarray:
    """Which edges lie inside a block."""
    out, src = np.empty(g.m, dtype=bool), g.src
    for i in range(0, g.m, SPAN):
        out[i : i + SPAN] = part[src[i : i + SPAN]] == part[g.dst[i : i + SPAN]]
    return out


# ---------------------------------------------------------------- ratings and admission

def ratings(g: Csr, label: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(node, label, weight) sums over the edges of the chosen nodes (a mask)."""
    found = list(rated(g, label, np.flatnonzero(rows)))
    return tuple(np.concatenate(c) for c in zip(*found, strict=True)) if found else (np.zeros(0, dtype=np.int64),) * 3


def rated(g: Csr, label: np.ndarray, nodes: np.ndarray):
    """The same span by span, for nodes given by their numbers."""
    many = int(label.max()) + 1 if g.n else 0
    for v in g.spans(nodes):
        e, count = g.edges_of(v)
        if len(e):
            key, rate = sum_by(np.repeat(np.arange(len(v)), count) * many + label[g.dst[e]], g.w[e], len(v) * many)
            yield v[key // many], key % many, rate


def changes(x: np.ndarray) -> np.ndarray:
    """Positions at which a run of equal values begins."""
    out = np.empty(len(x), dtype=bool)
    out[:1] = True
    np.not_equal(x[1:], x[:-1], out=out[1:])
    return out.nonzero()[0]


def best_rated(node: np.ndarray, rate: np.ndarray, tie: np.ndarray) -> np.ndarray:
    """Positions of the row of each node of largest (rate, tie), the last one of equals; rows of a node stand together."""
    at = np.arange(len(node))
    if not len(at):
        return at
    for key in (rate, tie):
        x, first = key[at], changes(node[at])
        many = np.empty_like(first)
        np.subtract(first[1:], first[:-1], out=many[:-1])
        many[-1] = len(at) - first[-1]
        at = at[x == np.maximum.reduceat(x, first).repeat(many)]
        if len(at) == len(first):
            return at
    last = changes(node[at]) - 1
    last[:-1], last[-1] = last[1:], len(at) - 1
    return at[last]


def admit(target: np.ndarray, w: np.ndarray, gain: np.ndarray, tie: np.ndarray, room: np.ndarray, how: str, seed: int) -> np.ndarray:
    """Which proposals are granted: all, those that fit in order of gain, or a share drawn by hash so that the expected weight fits."""
    if how == "soft" or not len(target):
        return np.ones(len(target), dtype=bool)
    if how == "sampled":
        demand = np.bincount(target, weights=w, minlength=len(room))
        share = np.divide(room, demand, out=np.ones(len(room)), where=demand > 0)
        return mix(tie, seed) / 2147483647 < share[target]
    order = np.lexsort((tie, -gain, target))
    t, own = target[order], w[order]
    run, first = own.cumsum(), changes(t)
    run -= (run - own)[first].repeat(np.diff(first, append=len(t)))
    out = np.zeros(len(target), dtype=bool)
    out[order] = run <= room[t]
    return out


def visit_classes(g: Csr, o: Options, seed: int) -> np.ndarray:
    """The sub-round in which each node acts."""
    ids = np.arange(g.n)
    if o.order == "id":
        return np.zeros(g.n, dtype=np.int64)
    if o.order == "random":
        return mix(ids, seed) % o.classes
    key = g.degree if o.order == "degree" else np.floor(np.log2(np.maximum(g.degree, 0.5))).astype(np.int64)
    tie = mix(ids, seed) if o.order == "degree" else mix(ids // 64, seed)
    order = np.lexsort((ids, tie, key))
    out = np.empty(g.n, dtype=np.int64)
    out[order] = np.arange(g.n) * o.classes // max(g.n, 1)
    return out


def lp_cluster(g: Csr, cap: float, o: Options, seed: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """Size-constrained label propagation from single nodes; and each node's favourite where size kept it from moving (else -1)."""
    label, favourite = np.arange(g.n), np.full(g.n, -1, dtype=np.int64)
    weight = g.nw.astype(float)
    classes, near, own = visit_classes(g, o, seed), None, np.zeros(g.n, dtype=np.int64)
    for r in range(o.rounds):
        moved, ties = np.zeros(g.n, dtype=bool), mix(np.arange(g.n), seed + r)
        for c in range(int(classes.max()) + 1 if g.n else 0):
            rows = classes == c
            if near is not None:
                rows &= near
            if not rows.any():
                continue
            wishes = []
            for node, lab, rate in rated(g, label, np.flatnonzero(rows)):
                own_label = label[node] == lab
                tie = ties[lab]
                fits = own_label | (weight[lab] + g.nw[node] <= cap)
                top = best_rated(node, rate, tie)
                own[node[own_label]] = rate[own_label]
                ok = np.flatnonzero(fits)
                best = ok[best_rated(node[ok], rate[ok], tie[ok])]
                blocked = top[~fits[top]]
                favourite[node[blocked]] = lab[blocked]
                v, t = node[best], lab[best]
                gain = rate[best] - own[v]
                own[node[own_label]] = 0
                go = (t != label[v]) & ((gain > 0) | ((gain == 0) & (tie[best] > ties[label[v]])))
                wishes.append((v[go], t[go], gain[go]))
            v, t, gain = (np.concatenate(c) for c in zip(*(wishes or [(np.zeros(0, dtype=np.int64),) * 3]), strict=True))
            yes = admit(t, g.nw[v], gain, mix(v, seed), cap - weight, o.enforce, seed + r)
            favourite[v[~yes]] = t[~yes]
            v, t = v[yes], t[yes]
            np.add.at(weight, label[v], -g.nw[v])
            np.add.at(weight, t, g.nw[v])
            label[v] = t
            moved[v] = True
        if not moved.any():
            break
        near = g.next_to(moved) if o.active else None
    return label, favourite


def two_hop(g: Csr, label: np.ndarray, favourite: np.ndarray, cap: float, o: Options, seed: int = 0) -> np.ndarray:
    """Merge clusters of one node that have the same favourite, until half the nodes are left."""
    size = np.bincount(label, minlength=g.n)
    clusters = int((size > 0).sum())
    quota = clusters - g.n // 2
    if quota <= 0 or o.two_hop == "off":
        return label
    fav = np.where(favourite >= 0, label[np.maximum(favourite, 0)], np.where(g.degree == 0, g.n, -1))
    one = np.flatnonzero((size[label] == 1) & (fav >= 0))
    order = one[np.lexsort((mix(one, seed), g.nw[one], fav[one]))]
    f = fav[order]
    first = np.r_[True, f[1:] != f[:-1]] if len(f) else np.zeros(0, dtype=bool)
    start = np.repeat(np.flatnonzero(first), np.diff(np.r_[np.flatnonzero(first), len(f)]))
    out = label.copy()
    if o.two_hop == "groups":
        run = np.cumsum(g.nw[order])
        within = run - (run - g.nw[order])[start] if len(order) else run
        bin_ = ((within - 1) // max(int(cap), 1)).astype(np.int64)
        lead = np.r_[True, (f[1:] != f[:-1]) | (bin_[1:] != bin_[:-1])] if len(f) else first
        heads = np.repeat(order[lead], np.diff(np.r_[np.flatnonzero(lead), len(order)]))
        joins = np.flatnonzero(heads != order)[:quota]
        for i in joins:
            out[order[i]] = label[heads[i]]
        return out
    rank = np.arange(len(order)) - start
    second = np.flatnonzero(rank % 2 == 1)
    a, b = order[second - 1], order[second]
    fit = g.nw[a] + g.nw[b] <= cap
    a, b = a[fit], b[fit]
    take = np.argsort(mix(a, seed + 1), kind="stable")[:quota]
    out[b[take]] = label[a[take]]
    return out


def match_heavy_edge(g: Csr, cap: float, rounds: int = 5, seed: int = 0) -> np.ndarray:
    """Mutual heaviest proposals, repeated; the rival way to coarsen."""
    mate = np.full(g.n, -1, dtype=np.int64)
    for r in range(rounds):
        to = np.full(g.n, -1, dtype=np.int64)
        for v in g.spans(np.flatnonzero(mate < 0)):
            e, many = g.edges_of(v)
            src, dst = np.repeat(v, many), g.dst[e]
            fits = np.flatnonzero((mate[dst] < 0) & (g.nw[src] + g.nw[dst] <= cap))
            src, dst = src[fits], dst[fits]
            b = best_rated(src, g.w[e[fits]], mix(src ^ dst, seed + r))
            to[src[b]] = dst[b]
        if (to < 0).all():
            break
        v = np.flatnonzero(to >= 0)
        both = v[to[to[v]] == v]
        mate[both] = to[both]
    return np.where(mate >= 0, np.minimum(np.arange(g.n), mate), np.arange(g.n))


def match_two_hop(g: Csr, label: np.ndarray, cap: float, seed: int = 0) -> np.ndarray:
    """Pair unmatched nodes that have the same heaviest neighbour."""
    favourite = np.full(g.n, -1, dtype=np.int64)
    for v in g.spans(np.arange(g.n)):
        e, many = g.edges_of(v)
        src, dst = np.repeat(v, many), g.dst[e]
        b = best_rated(src, g.w[e], -dst)
        favourite[src[b]] = dst[b]
    return two_hop(g, label, favourite, cap, Options(two_hop="pairs"), seed)


# ---------------------------------------------------------------- two-way splits of small graphs

def _fill(g: Csr, order: np.ndarray, share: float) -> np.ndarray:
    run = np.cumsum(g.nw[order])
    side = np.ones(g.n, dtype=np.int64)
    side[order[run - g.nw[order] / 2 <= share * g.total]] = 0
    return side


def pool_random(g: Csr, share: float, seed: int) -> np.ndarray:
    return _fill(g, np.random.default_rng(seed).permutation(g.n), share)


def pool_bfs(g: Csr, share: float, seed: int) -> np.ndarray:
    return _fill(g, bfs_order(g, seed), share)


def pool_grow(g: Csr, share: float, seed: int) -> np.ndarray:
    """Grow side 0 by the node of most edge weight into it, less its weight to the rest."""
    order = np.random.default_rng(seed).permutation(g.n).tolist()
    near, nw = g.near(), g.nw.tolist()
    gain: list[int | None] = [None] * g.n
    side, have, at, heap, limit = [1] * g.n, 0, 0, [], share * g.total
    for _ in range(g.n):
        while heap and (side[heap[0][1]] == 0 or gain[heap[0][1]] != -heap[0][0]):
            heappop(heap)
        if heap:
            v = heap[0][1]
        else:
            while side[order[at]] == 0:
                at += 1
            v = order[at]
        if have + nw[v] / 2 > limit:
            break
        side[v] = 0
        have += nw[v]
        for u, w in near(v):
            if side[u]:
                if gain[u] is None:
                    gain[u] = -sum(x for _, x in near(u))
                gain[u] += 2 * w
                heappush(heap, (-gain[u], u))
    return np.array(side, dtype=np.int64)


POOL = {"random": pool_random, "bfs": pool_bfs, "grow": pool_grow}


def two_way_fm(g: Csr, side: np.ndarray, caps: tuple[float, float], passes: int = 4, patience: int = 60) -> np.ndarray:
    """Moves by best gain, each node once a pass, back to the best prefix; less overload comes before less cut.

    Each side has a heap of its free nodes; entries whose gain is out of date are dropped when they surface, and nodes that do not fit the other
    side are held until it has more room.
    """
    caps, nw, near, side = (float(caps[0]), float(caps[1])), g.nw.tolist(), g.near(), side.tolist()
    lightest = min(nw, default=0)
    cap0, cap1 = caps
    for _ in range(passes):
        gain, weight = g.gains(side), [0, 0]
        heaps, held, free = ([], []), ([], []), [True] * g.n
        for v, s in enumerate(side):
            weight[s] += nw[v]
            heaps[s].append((-gain[v], v))
        heapify(heaps[0])
        heapify(heaps[1])
        start = best = (max(weight[0] - cap0, 0.0) + max(weight[1] - cap1, 0.0), 0)
        moves, best_at, total, idle = [], 0, 0, 0
        while idle < patience:
            must = 0 if weight[0] > cap0 else 1 if weight[1] > cap1 else -1
            found = None
            for s in (0, 1) if must < 0 else (must,):
                heap, room = heaps[s], caps[1 - s] - weight[1 - s]
                if must < 0 and room < lightest:
                    continue
                if must >= 0 and held[s]:
                    for x in held[s]:
                        heappush(heap, x)
                    held[s].clear()
                while heap:
                    loss, v = heap[0]
                    if not free[v] or gain[v] != -loss:
                        heappop(heap)
                    elif must < 0 and weight[1 - s] + nw[v] > caps[1 - s]:
                        held[s].append(heappop(heap))
                    else:
                        if found is None or heap[0] < found:
                            found = heap[0]
                        break
            if found is None:
                break
            v, s = found[1], side[found[1]]
            free[v] = False
            total -= gain[v]
            weight[s] -= nw[v]
            side[v] = t = 1 - s
            weight[t] += nw[v]
            moves.append(v)
            for u, w in near(v):
                if free[u]:
                    gain[u] += -2 * w if side[u] == t else 2 * w
                    heappush(heaps[side[u]], (-gain[u], u))
            if held[t]:
                for x in held[t]:
                    heappush(heaps[t], x)
                held[t].clear()
            over0, over1 = weight[0] - cap0, weight[1] - cap1
            now = ((over0 if over0 > 0 else 0.0) + (over1 if over1 > 0 else 0.0), total)
            if now < best:
                best, best_at, idle = now, len(moves), 0
            else:
                idle += 1
        for v in moves[best_at:]:
            side[v] = 1 - side[v]
        if best >= start:
            break
    return np.array(side, dtype=np.int64)


def bisect(g: Csr, f0: int, f1: int, eps: float, o: Options, seed: int) -> np.ndarray:
    """Sides 0 and 1 with weights near f0 : f1: coarsen as far as possible, a pool of starts at the bottom, two-way search on the way up."""
    if g.n <= 1:
        return np.zeros(g.n, dtype=np.int64)
    share = f0 / (f0 + f1)
    caps = tuple(max(rules.limit_two_way(g.total, eps, s), g.total * s + g.heaviest) for s in (share, 1 - share))
    best, best_key = None, None
    for t in range(o.tries):
        s = seed * 31 + t
        levels, now = [], g
        while now.n > 40:
            label, _ = lp_cluster(now, max(min(caps) / 12, 1), Options(rounds=3, order=o.order, enforce="strict"), s + len(levels))
            coarse, parent = now.contract(label)
            if coarse.n > 0.95 * now.n or coarse.n < 2:
                break
            levels.append((now, parent))
            now = coarse
        found = None
        for name in o.pool:
            cuts = []
            for r in range(o.repeats):
                if o.adaptive and found and len(cuts) >= 2 and np.mean(cuts) - 2 * np.std(cuts) > found[0][1]:
                    break
                side = two_way_fm(now, POOL[name](now, share, s * 1009 + r), caps)
                w = now.block_weights(side, 2)
                key = (float(np.maximum(w - np.array(caps), 0).sum()), now.cut(side))
                cuts.append(key[1])
                if found is None or key < found[0]:
                    found = (key, side)
        side = found[1]
        for fine, parent in reversed(levels):
            side = two_way_fm(fine, side[parent], caps)
        w = g.block_weights(side, 2)
        key = (bool((w > np.array(caps)).any()), float(np.maximum(w - np.array(caps), 0).sum()), g.cut(side), t)
        if best is None or key < best_key:
            best, best_key = side, key
    return best


# ---------------------------------------------------------------- blocks of a level

@dataclass
class Blocks:
    """Blocks of a partition: how many final blocks each will become."""

    f: np.ndarray

    def caps(self, g: Csr, k: int, eps: float) -> np.ndarray:
        return np.maximum((1 + eps) * g.total * self.f / k, g.total * self.f / k + g.heaviest)


def bisect_blocks(g: Csr, part: np.ndarray, blocks: Blocks, k: int, o: Options, total: int, seed: int) -> tuple[np.ndarray, Blocks]:
    """Split every block that is to become two or more."""
    out, f, nxt = np.empty_like(part), [], 0
    for b, (nodes, sub) in enumerate(g.blocks(part, len(blocks.f))):
        count = int(blocks.f[b])
        if count < 2:
            out[nodes], nxt = nxt, nxt + 1
            f.append(count)
            continue
        f0, f1 = rules.split_count(count)
        eps = rules.eps_adaptive(o.eps, total, k, sub.total, count) if o.slack == "adaptive" else o.eps
        side = keep_enough(sub, bisect(sub, f0, f1, eps, o, seed * 7919 + b), f0, f1)
        out[nodes] = nxt + side
        f += [f0, f1]
        nxt += 2
    return out, Blocks(np.array(f, dtype=np.int64))


def keep_enough(g: Csr, side: np.ndarray, f0: int, f1: int) -> np.ndarray:
    """At least as many nodes on a side as final blocks it must become, where there are enough."""
    side = side.copy()
    for s, need in ((0, f0), (1, f1)):
        lack = min(need, g.n) - int((side == s).sum())
        if lack > 0:
            give = np.flatnonzero(side != s)
            side[give[np.argsort(g.nw[give], kind="stable")[:lack]]] = s
    return side


def occupy(g: Csr, part: np.ndarray, k: int) -> np.ndarray:
    """Each block without a node gets the node least tied to the heaviest block of several, so that all k blocks are used where there are nodes enough.

    A block that shrank to fewer nodes than the blocks it was to become leaves such blocks when it is split.
    """
    size = np.bincount(part, minlength=k)
    empty = np.flatnonzero(size == 0)
    if not len(empty):
        return part
    part, weight, inner = part.copy(), g.block_weights(part, k), _same(g, part)
    inside = np.bincount(g.src[inner], weights=g.w[inner], minlength=g.n)
    for b in empty:
        a = int(np.argmax(np.where(size > 1, weight, -1)))
        if size[a] < 2:
            break
        nodes = np.flatnonzero(part == a)
        v = nodes[np.argmin(inside[nodes])]
        part[v], inside[v] = b, 0
        to = slice(g.ptr[v], g.ptr[v + 1])
        near = part[g.dst[to]] == a
        inside[g.dst[to][near]] -= g.w[to][near]
        for x, sign in ((a, -1), (b, 1)):
            size[x] += sign
            weight[x] += sign * g.nw[v]
    return part


def balance(g: Csr, part: np.ndarray, caps: np.ndarray, shares: np.ndarray, o: Options, seed: int = 0) -> np.ndarray:
    """Overloaded blocks give nodes of best relative gain to blocks with room; what is left goes to the lightest blocks."""
    part, k = part.copy(), len(caps)
    tried = np.zeros(g.n, dtype=bool)
    for r in range(8):
        weight = g.block_weights(part, k)
        over = weight - caps
        if (over <= 0).all():
            return part
        rows = (over[part] > 0) & ~tried
        if not rows.any():
            break
        node, lab, rate = ratings(g, part, rows)
        own = np.zeros(g.n, dtype=np.int64)
        same = lab == part[node]
        own[node[same]] = rate[same]
        fits = ~same & (weight[lab] + g.nw[node] <= caps[lab])
        ok = np.flatnonzero(fits)
        best = ok[best_rated(node[ok], rate[ok], mix(lab[ok], seed + r))]
        target, d = np.full(g.n, -1, dtype=np.int64), -own.astype(float)
        target[node[best]] = lab[best]
        d[node[best]] = rate[best] - own[node[best]]
        v = np.flatnonzero(rows)
        lone = v[target[v] < 0]
        room = np.flatnonzero(weight < caps)
        if len(lone) and len(room):
            pick = room[mix(lone, seed + r) % len(room)]
            good = weight[pick] + g.nw[lone] <= caps[pick]
            target[lone[good]] = pick[good]
        v = v[target[v] >= 0]
        if not len(v):
            break
        key = np.where(d[v] >= 0, d[v] * g.nw[v], d[v] / g.nw[v])
        order = v[np.lexsort((mix(v, seed), -key, part[v]))]
        b = part[order]
        run = np.cumsum(g.nw[order])
        first = np.r_[True, b[1:] != b[:-1]]
        before = run - g.nw[order] - np.repeat((run - g.nw[order])[first], np.diff(np.r_[np.flatnonzero(first), len(b)]))
        chosen = order[before < over[b]]
        yes = admit(target[chosen], g.nw[chosen], np.where(d[chosen] >= 0, d[chosen] * g.nw[chosen], d[chosen] / g.nw[chosen]), mix(chosen, seed), caps - weight, "strict", seed)
        moved = chosen[yes]
        if not len(moved):
            break
        part[moved] = target[moved]
        tried[moved] = True
    weight = g.block_weights(part, k).astype(float)
    heavy = np.flatnonzero(weight > caps)
    if not len(heavy):
        return part
    # Nodes only go to blocks with room, so what lies inside the heavy blocks can be summed once for all of them.
    inner = _same(g, part)
    inside = np.bincount(g.src[inner], weights=g.w[inner], minlength=g.n)
    light = [(x, t) for t, x in enumerate((weight / shares).tolist())]
    heapify(light)
    for b in heavy:
        nodes = np.flatnonzero(part == b)
        for v in nodes[np.lexsort((nodes, inside[nodes] / g.nw[nodes]))]:
            if weight[b] <= caps[b]:
                break
            while light and (light[0][1] == b or light[0][0] != weight[light[0][1]] / shares[light[0][1]]):
                heappop(light)
            t = light[0][1] if light else 0
            if t != b and weight[t] + g.nw[v] <= caps[t]:
                part[v] = t
                weight[b] -= g.nw[v]
                weight[t] += g.nw[v]
                heappush(light, (weight[t] / shares[t], t))
        heappush(light, (weight[b] / shares[b], b))
    return part


def refine(g: Csr, part: np.ndarray, caps: np.ndarray, o: Options, seed: int = 0) -> np.ndarray:
    """Label propagation among blocks with strict limits; neighbours do not move together, so gains add up and the cut never rises."""
    part, k = part.copy(), len(caps)
    classes, near, own, rank = visit_classes(g, o, seed), None, np.zeros(g.n, dtype=np.int64), np.full(g.n, -1, dtype=np.int64)
    for r in range(o.rounds):
        moved, ties = np.zeros(g.n, dtype=bool), mix(np.arange(k), seed + r)
        for c in range(int(classes.max()) + 1 if g.n else 0):
            rows = classes == c
            if near is not None:
                rows &= near
            if not rows.any():
                continue
            weight = g.block_weights(part, k)
            wishes = []
            for node, lab, rate in rated(g, part, np.flatnonzero(rows)):
                same = lab == part[node]
                own[node[same]] = rate[same]
                ok = np.flatnonzero(~same & (weight[lab] + g.nw[node] <= caps[lab]))
                best = ok[best_rated(node[ok], rate[ok], ties[lab[ok]])]
                v, t = node[best], lab[best]
                gain = rate[best] - own[v]
                own[node[same]] = 0
                go = (gain > 0) | ((gain == 0) & (weight[t] + g.nw[v] < weight[part[v]]))
                wishes.append((v[go], t[go], gain[go]))
            v, t, gain = (np.concatenate(x) for x in zip(*(wishes or [(np.zeros(0, dtype=np.int64),) * 3]), strict=True))
            if o.conflict == "independent" and len(v):
                rank[v[np.lexsort((v, mix(v, seed + r), gain))]] = np.arange(len(v))
                stay = np.ones(g.n, dtype=bool)
                for x in g.spans(v):
                    e, many = g.edges_of(x)
                    before = np.repeat(x, many)
                    stay[before[rank[g.dst[e]] > rank[before]]] = False
                rank[v] = -1
                yes = stay[v]
                v, t, gain = v[yes], t[yes], gain[yes]
            yes = admit(t, g.nw[v], gain, mix(v, seed), caps - weight, "strict", seed)
            v, t = v[yes], t[yes]
            members = np.bincount(part, minlength=k)
            leaving = np.bincount(part[v], minlength=k)
            hold = members[part[v]] <= leaving[part[v]]
            v, t = v[~hold], t[~hold]
            part[v] = t
            moved[v] = True
        if not moved.any():
            break
        near = g.next_to(moved) | moved if o.active else None
    return part


# ---------------------------------------------------------------- whole schemes

def coarsen(g: Csr, cap: float, o: Options, seed: int) -> tuple[Csr, np.ndarray]:
    label, favourite = lp_cluster(g, cap, o, seed)
    return g.contract(two_hop(g, label, favourite, cap, o, seed))


def descend(g: Csr, k: int, o: Options, least: int, how: str = "lp", seed: int = 0) -> tuple[list, Csr]:
    """Levels (graph, parent) from fine to coarse, until ``least`` nodes are left or a level hardly shrinks."""
    levels, now, n0, total = [], g, g.n, g.total
    while now.n > least:
        cap = max(rules.cluster_cap(o.eps, total, k, o.c, n0, now.n), 1)
        if how == "match":
            label = match_heavy_edge(now, max(cap, 2 * now.heaviest), seed=seed + len(levels))
            coarse, parent = now.contract(match_two_hop(now, label, max(cap, 2 * now.heaviest), seed))
        else:
            coarse, parent = coarsen(now, cap, o, seed + len(levels))
        if coarse.n > (1 - o.min_shrink) * now.n:
            break
        levels.append((now, parent))
        now = coarse
    return levels, now


def _level(g: Csr, part: np.ndarray, blocks: Blocks, wanted: int, k: int, o: Options, total: int, seed: int, do_refine: bool = True) -> tuple[np.ndarray, Blocks]:
    with o.timed("initial", g.n):
        while len(blocks.f) < wanted and (blocks.f > 1).any():
            part, blocks = bisect_blocks(g, part, blocks, k, o, total, seed + len(blocks.f))
    with o.timed("refinement", g.n):
        caps = blocks.caps(g, k, o.eps)
        if (g.block_weights(part, len(caps)) > caps).any():
            part = balance(g, part, caps, blocks.f / k, o, seed)
        if do_refine:
            part = refine(g, part, caps, o, seed)
    return part, blocks


def partition(g: Csr, k: int, o: Options) -> np.ndarray:
    """The one-cycle scheme: coarsen once, split the smallest graph, double the blocks on the way up."""
    if k < 1 or k > max(g.n, 1):
        raise ValueError("k must lie between 1 and the number of nodes")
    if k == 1 or g.n == 0:
        return np.zeros(g.n, dtype=np.int64)
    if k == g.n:
        return np.arange(g.n)
    with o.timed("coarsening"):
        levels, now = descend(g, k, o, 2 * o.c, seed=o.seed)
    part, blocks = _bottom(now, k, o, g.total)
    for depth, (fine, parent) in reversed(list(enumerate(levels))):
        part = part[parent]
        wanted = rules.level_blocks(fine.n, o.c, k)
        part, blocks = _level(fine, part, blocks, wanted, k, o, g.total, o.seed + depth, depth > 0 or o.final_order == "twice")
        o.log.append((depth, fine.n, fine.m // 2, len(blocks.f), fine.cut(part)))
    if len(blocks.f) < k:
        part, blocks = _level(g, part, blocks, k, k, o, g.total, o.seed + 977)
    elif o.final_order == "once":
        part = refine(g, part, blocks.caps(g, k, o.eps), o, o.seed)
    return occupy(g, part, k)


def _bottom(g: Csr, k: int, o: Options, total: int) -> tuple[np.ndarray, Blocks]:
    """The smallest graph's blocks; with lanes, the best of copies that coarsen on and search with other seeds."""
    start = np.zeros(g.n, dtype=np.int64), Blocks(np.array([k]))
    if o.lanes <= 1:
        return _level(g, *start, rules.level_blocks(g.n, o.c, k), k, o, total, o.seed)
    found = []
    for lane in range(2):
        own = Options(**{**o.spec(), "lanes": o.lanes // 2, "seed": 2 * o.seed + 1 + lane})
        coarse, parent = coarsen(g, max(rules.cluster_cap(o.eps, total, k, o.c, g.n, g.n), 1), own, own.seed)
        part, blocks = _bottom(coarse, k, own, total) if coarse.n >= 2 else _level(g, *start, 2, k, own, total, own.seed)
        part = part[parent] if coarse.n >= 2 else part
        part, blocks = _level(g, part, blocks, rules.level_blocks(g.n, o.c, k), k, own, total, own.seed)
        over = bool((g.block_weights(part, len(blocks.f)) > blocks.caps(g, k, o.eps)).any())
        found.append(((over, g.cut(part), lane), part, blocks))
    return min(found, key=lambda x: x[0])[1:]


def recursive_bisection(g: Csr, k: int, o: Options, how: str = "lp") -> np.ndarray:
    """Split in two, then each part again: log2 k full cycles; slack fixed or adaptive."""
    part, blocks = np.zeros(g.n, dtype=np.int64), Blocks(np.array([k]))
    step = 0
    while (blocks.f > 1).any():
        part, blocks = bisect_blocks(g, part, blocks, k, o, g.total, o.seed + step)
        step += 1
    return part


def direct_kway(g: Csr, k: int, o: Options, how: str = "lp", search: str = "lp", rebalance: bool = False) -> np.ndarray:
    """Coarsen to k * C nodes, start there by recursive bisection, refine upwards; no repair of balance unless asked."""
    levels, now = descend(g, k, o, min(max(k * o.c, 2 * k), max(g.n - 1, 1)), how, o.seed)
    part = recursive_bisection(now, k, o)
    for fine, parent in [*reversed(levels)]:
        part = part[parent]
        caps = np.full(k, rules.limit_strict(fine.total, k, o.eps) if not rebalance else rules.limit_relaxed(fine.total, k, o.eps, fine.heaviest))
        part = refine(fine, part, caps, o, o.seed)
        if search == "fm":
            part = kway_fm(fine, part, caps)
        if rebalance:
            part = balance(fine, part, caps, np.full(k, 1 / k), o, o.seed)
    return part


def kway_fm(g: Csr, part: np.ndarray, caps: np.ndarray) -> np.ndarray:
    """Passes of best moves of boundary nodes to any block with room, losses included, each back to its best prefix; until a pass gains nothing."""
    part = part.copy()
    while g.n:
        moves, best_at = _kway_pass(g, part, caps)
        if not best_at:
            break
        for v, t in moves[:best_at]:
            part[v] = t
    return part


def _kway_pass(g: Csr, part: np.ndarray, caps: np.ndarray) -> tuple[list[tuple[int, int]], int]:
    """Moves (node, block) until no free boundary node fits another block, each node once; and the length of the prefix of most gain.

    The next move is the one of most gain, of the least block and then the least node among equals, however the gains are kept.
    """
    return _kway_pass_table(g, part, caps) if len(caps) * g.n <= g.m else _kway_pass_heaps(g, part, caps)


def _kway_pass_table(g: Csr, part: np.ndarray, caps: np.ndarray) -> tuple[list[tuple[int, int]], int]:
    """The pass over a table of each node's gain into each block, for graphs with at least as many edges as it has cells.

    Nodes stand in runs.  Each block has a bound for each run, never below the best gain of a node there that fits: rising gains lift it at once,
    falling ones when the run comes to the front.
    """
    k, n, many, size = len(caps), g.n, -(-g.n >> RUN), 1 << RUN
    own, ptr, dst, wgt, nw = part.astype(np.int32), g.ptr.tolist(), g.dst, g.w, g.nw
    room, weigh, lightest, even = (caps - g.block_weights(part, k)).tolist(), nw.tolist(), int(nw.min()), int(nw.min()) == int(nw.max())
    # Small weights take cells of four bytes.  ``none`` marks a node's own block and nodes that have moved, which lose too much anywhere.
    kind, none = (np.int32, -(1 << 29)) if int(g.degree.max()) * int(wgt.max()) < 1 << 26 else (np.int64, -(1 << 60))
    gone, gains = none // 2, np.empty((n, k), dtype=kind)
    for first, last in ranges(g.degree, SPAN):
        at, rows = slice(ptr[first], ptr[last]), last - first
        key = np.repeat(np.arange(rows) * k, g.degree[first:last]) + part[dst[at]]
        gains[first:last] = np.bincount(key, weights=wgt[at], minlength=k * rows).reshape(rows, k)
    mine = gains[np.arange(n), own]
    apart = gains == 0
    gains -= mine[:, None]
    gains[np.arange(n), own] = none
    bound, full, wait = np.full((k, many), none, dtype=kind), np.full((k, many), none, dtype=kind), np.full((k, many), 1 << 60)
    for r in range(many):
        at = slice(r * size, (r + 1) * size)
        bound[:, r] = np.where(apart[at], none, gains[at]).max(axis=0)
    del apart
    flat, shift, cells, columns, bounds = bound.reshape(-1), np.arange(k) * many, gains.reshape(-1), [gains[:, t] for t in range(k)], list(bound)
    top, open_ = bound.max(axis=1), np.array(room) >= lightest

    def settle(t: int) -> int:
        """The least node of best gain into t that fits, or -1; ``top`` and the bound of its run hold then."""
        runs, column = bounds[t], columns[t]
        while True:
            r = int(runs.argmax())
            believed = int(runs[r])
            if believed <= gone:
                top[t] = none
                return -1
            at = slice(r * size, (r + 1) * size)
            gain = column[at]
            i = int(gain.argmax())
            found = int(gain[i])
            if found > gone and (not even or found + mine[r * size + i] == 0):
                gain = np.where(gain + mine[at] > 0, gain, none)  # nodes without an edge into t do not go there
                if not even:
                    heavy = (nw[at] > room[t]) & (gain > gone)
                    if heavy.any():
                        full[t, r], wait[t, r] = gain.max(), nw[at][heavy].min()
                        gain[heavy] = none
                    else:
                        wait[t, r] = 1 << 60
                i = int(gain.argmax())
                found = int(gain[i])
            if found == believed:
                top[t] = found
                return r * size + i
            runs[r] = found

    moves, total, best, best_at = [], 0, 0, 0
    while True:
        could = np.where(open_, top, none)
        t = int(could.argmax())
        believed = int(could[t])
        if believed <= gone:
            break
        v = settle(t)
        gain = int(top[t])
        if gain < believed:
            continue
        a = int(own[v])
        total += gain
        own[v] = t
        gains[v] = none
        room[a] += weigh[v]
        room[t] -= weigh[v]
        open_[a], open_[t] = room[a] >= lightest, room[t] >= lightest
        moves.append((v, t))
        if total > best:
            best, best_at = total, len(moves)
        i, j = ptr[v], ptr[v + 1]
        u, w = dst[i:j].astype(np.int64), wgt[i:j].astype(kind)
        where, cell = own.take(u), u * k
        left, came = (where == a).nonzero()[0], (where == t).nonzero()[0]
        cells[cell + a] -= w
        cell += t
        into = cells.take(cell)
        into += w
        cells[cell] = into
        if len(came):
            y, less = u.take(came), w.take(came)
            gains[y] -= less[:, None]
            mine[y] += less
        u >>= RUN
        np.maximum.at(bounds[t], u, into)
        top[t] = max(gain, int(into.max()))
        if len(left):
            x, more = dst[i:j].take(left), w.take(left)
            gain = gains.take(x, axis=0)
            gain += more[:, None]
            gains[x] = gain
            mine[x] -= more
            np.maximum.at(flat, np.add.outer(u.take(left), shift).reshape(-1), gain.reshape(-1))
            np.maximum(top, gain.max(axis=0), out=top)
        if not even:
            again = wait[a] <= room[a]
            if again.any():
                bound[a, again], wait[a, again] = np.maximum(bound[a, again], full[a, again]), 1 << 60
                top[a] = bound[a].max()
    return moves, best_at


def _kway_pass_heaps(g: Csr, part: np.ndarray, caps: np.ndarray) -> tuple[list[tuple[int, int]], int]:
    """The pass over a heap for each block of nodes that could come.

    Rising gains are pushed at once and falling ones when they surface, so ``top`` is never below the best gain into a block.
    """
    k, own, nw = len(caps), part.tolist(), g.nw.tolist()
    ptr, dst, wgt = g.ptr.tolist(), g.dst.tolist(), g.w.tolist()
    key, inverse = np.unique(g.src.astype(np.int64) * k + part[g.dst], return_inverse=True)
    near: list[dict[int, int]] = [{} for _ in range(g.n)]
    for x, w in zip(key.tolist(), np.bincount(inverse, weights=g.w, minlength=len(key)).astype(np.int64).tolist(), strict=True):
        near[x // k][x % k] = w
    room, lightest = (caps - g.block_weights(part, k)).tolist(), min(nw)
    free, heaps, held, top = [True] * g.n, [[] for _ in range(k)], [[] for _ in range(k)], np.full(k, -np.inf)
    for v, have in enumerate(near):
        mine = have.get(own[v], 0)
        for t, w in have.items():
            if t != own[v]:
                heaps[t].append((mine - w, v))

    def settle(t: int) -> None:
        """The best entry that holds and fits comes to the front of the heap of t; entries too heavy for now are held."""
        heap = heaps[t]
        while heap and room[t] >= lightest:
            loss, v = heap[0]
            if not free[v] or own[v] == t or not near[v].get(t):
                heappop(heap)
            elif (now := near[v].get(own[v], 0) - near[v][t]) != loss:
                heapreplace(heap, (now, v)) if now > loss else heappop(heap)  # a better entry of v lies elsewhere in the heap
            elif nw[v] > room[t]:
                held[t].append(heappop(heap))
            else:
                top[t] = -loss
                return
        top[t] = -np.inf

    for t in range(k):
        heapify(heaps[t])
        settle(t)
    moves, total, best, best_at = [], 0, 0, 0
    while True:
        t = int(np.argmax(top))
        believed = top[t]
        if believed == -np.inf:
            break
        settle(t)
        if top[t] < believed:
            continue
        loss, v = heappop(heaps[t])
        a = own[v]
        free[v], own[v] = False, t
        room[a] += nw[v]
        room[t] -= nw[v]
        moves.append((v, t))
        total -= loss
        if total > best:
            best, best_at = total, len(moves)
        for u, w in zip(dst[ptr[v] : ptr[v + 1]], wgt[ptr[v] : ptr[v + 1]], strict=True):
            have = near[u]
            have[a] -= w
            have[t] = have.get(t, 0) + w
            if not have[a]:
                del have[a]
            if not free[u] or own[u] == t:
                continue
            mine = have.get(own[u], 0)
            for b in have if own[u] == a else (t,):
                if b != own[u]:
                    heappush(heaps[b], (mine - have[b], u))
                    if have[b] - mine > top[b] and room[b] >= lightest:
                        top[b] = have[b] - mine
        for x in held[a]:
            heappush(heaps[a], x)
        held[a] = []
        settle(a)
        settle(t)
    return moves, best_at


def single_level(g: Csr, k: int, o: Options, init: str = "bfs") -> np.ndarray:
    """Blocks on the input graph only: a start, then propagation and repair in turn."""
    if init == "hash":
        part = mix(np.arange(g.n), o.seed) % k
    else:
        order = np.random.default_rng(o.seed).permutation(g.n) if init == "random" else bfs_order(g, o.seed)
        run = np.cumsum(g.nw[order]) - g.nw[order] / 2
        part = np.empty(g.n, dtype=np.int64)
        part[order] = np.minimum((run * k / max(g.total, 1)).astype(np.int64), k - 1)
    caps = np.full(k, rules.limit_relaxed(g.total, k, o.eps, g.heaviest))
    for r in range(3):
        part = balance(g, part, caps, np.full(k, 1 / k), o, o.seed + r)
        part = refine(g, part, caps, o, o.seed + r)
    return part


def bfs_order(g: Csr, seed: int) -> np.ndarray:
    """Nodes front by front from random starts; a front is in order of numbers."""
    seen, out = np.zeros(g.n, dtype=bool), []
    if g.m <= SMALL:
        near, seen = g.near(), [False] * g.n
        for s in np.random.default_rng(seed).permutation(g.n).tolist():
            if seen[s]:
                continue
            front, seen[s] = [s], True
            while front:
                out += front
                front = sorted({u for v in front for u, _ in near(v) if not seen[u]})
                for u in front:
                    seen[u] = True
        return np.array(out, dtype=np.int64)
    for s in np.random.default_rng(seed).permutation(g.n):
        if seen[s]:
            continue
        front = np.array([s])
        seen[s] = True
        while len(front):
            out.append(front)
            reached = np.zeros(g.n, dtype=bool) if len(front) > 64 else None
            if reached is None:
                found = np.unique(g.dst[g.edges_of(front)[0]])
            else:
                for v in g.spans(front):
                    reached[g.dst[g.edges_of(v)[0]]] = True
                found = np.flatnonzero(reached)
            front = found[~seen[found]].astype(np.int64)
            seen[front] = True
    return np.concatenate(out) if out else np.zeros(0, dtype=np.int64)


def exact(g: Csr, k: int, cap: float) -> int:
    """Least cut of any partition into k blocks within the cap; for at most 16 nodes."""
    if g.n > 16:
        raise ValueError("too many nodes to enumerate")
    best = [g.w.sum() // 2 + 1]
    part, weight = np.full(g.n, -1), np.zeros(k)

    def place(v: int, used: int, cut: int) -> None:
        if cut >= best[0] or k - used > g.n - v:
            return
        if v == g.n:
            best[0] = cut
            return
        to, w = g.dst[g.ptr[v] : g.ptr[v + 1]], g.w[g.ptr[v] : g.ptr[v + 1]]
        known = part[to] >= 0
        for b in range(min(used + 1, k)):
            if weight[b] + g.nw[v] <= cap:
                part[v] = b
                weight[b] += g.nw[v]
                place(v + 1, max(used, b + 1), cut + int(w[known & (part[to] != b)].sum()))
                weight[b] -= g.nw[v]
                part[v] = -1

    place(0, 0, 0)
    return int(best[0])


SCHEMES = {
    "one_cycle": partition,
    "direct_kway": lambda g, k, o: direct_kway(g, k, o, "match"),
    "recursive_fixed": lambda g, k, o: recursive_bisection(g, k, Options(**{**o.__dict__, "slack": "fixed"})),
    "recursive_adaptive": lambda g, k, o: recursive_bisection(g, k, o),
    "kway_fm": lambda g, k, o: direct_kway(g, k, o, "lp", "fm"),
    "single_level_lp": lambda g, k, o: single_level(g, k, o),
    "local_matching": lambda g, k, o: direct_kway(g, k, o, "match", rebalance=True),
    "local_lp": lambda g, k, o: direct_kway(g, k, o, "lp", rebalance=True),
}
