import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from graphsplit.functions import rules
from graphsplit.operators import local
from graphsplit.operators.local import Blocks, Csr, Options


def graph(n, pairs, nw=None):
    p = np.array([(*x, 1) if len(x) == 2 else x for x in pairs], dtype=np.int64).reshape(-1, 3)
    return Csr(np.ones(n) if nw is None else np.array(nw), np.r_[p[:, 0], p[:, 1]], np.r_[p[:, 1], p[:, 0]], np.r_[p[:, 2], p[:, 2]])


def grid(r, c):
    return graph(r * c, [(i, i + 1) for i in range(r * c) if i % c < c - 1] + [(i, i + c) for i in range((r - 1) * c)])


def relaxed(g, part, k, eps=0.03):
    return (g.block_weights(part, k) <= rules.limit_relaxed(g.total, k, eps, g.heaviest) + 1e-6).all()


@pytest.mark.parametrize("k", [2, 3, 5, 7, 8, 16, 100, 512])
def test_any_k_is_feasible_and_uses_all_blocks(k):
    g = grid(24, 24)
    part = local.partition(g, k, Options(c=40, tries=1, repeats=1))
    assert len(np.unique(part)) == k and relaxed(g, part, k)


def test_known_optima():
    cliques = graph(80, [(a, b) for a in range(80) for b in range(a + 1, 80) if a // 10 == b // 10])
    assert cliques.cut(local.partition(cliques, 8, Options(c=10))) == 0
    path = graph(64, [(i, i + 1) for i in range(63)])
    assert [path.cut(local.partition(path, k, Options(c=10))) for k in (2, 4, 8)] == [1, 3, 7]
    assert local.exact(grid(3, 4), 2, 6) == 3


def test_edge_cases():
    g = grid(4, 4)
    assert (local.partition(g, 1, Options()) == 0).all()
    assert len(set(local.partition(g, 16, Options()).tolist())) == 16
    with pytest.raises(ValueError):
        local.partition(g, 17, Options())
    assert len(local.partition(graph(0, []), 1, Options())) == 0
    lone = graph(10, [])
    assert relaxed(lone, local.partition(lone, 3, Options()), 3)
    giant = graph(9, [(i, i + 1) for i in range(8)], [8, 1, 1, 1, 1, 1, 1, 1, 1])
    assert relaxed(giant, local.partition(giant, 4, Options(c=2)), 4)


def test_two_cliques_become_two_clusters():
    pairs = [(a, b, 2) for a in range(8) for b in range(a + 1, 8) if a // 4 == b // 4] + [(3, 4, 1)]
    g = graph(8, pairs)
    label, _ = local.lp_cluster(g, 4, Options())
    coarse, _ = g.contract(label)
    assert coarse.n == 2 and coarse.nw.tolist() == [4, 4] and coarse.w.tolist() == [1, 1]
    label, _ = local.lp_cluster(g, 3, Options())
    assert np.bincount(label).max() <= 3


def test_two_hop_halves_a_star():
    g = graph(101, [(0, i) for i in range(1, 101)])
    label, favourite = local.lp_cluster(g, 3, Options())
    before = len(np.unique(label))
    after = len(np.unique(local.two_hop(g, label, favourite, 3, Options())))
    assert before > 90 and after == 50


def test_balance_moves_the_node_of_best_relative_gain():
    g = graph(6, [(i, i + 1) for i in range(5)])
    part = local.balance(g, np.array([0, 0, 0, 0, 0, 1]), np.array([4.0, 4.0]), np.array([0.5, 0.5]), Options())
    assert g.cut(part) == 1 and g.block_weights(part, 2).max() <= 4


@settings(max_examples=40, deadline=None)
@given(st.integers(4, 40), st.integers(0, 2**31), st.integers(2, 5))
def test_invariants_on_random_graphs(n, seed, k):
    rng = np.random.default_rng(seed)
    a, b = rng.integers(0, n, 3 * n), rng.integers(0, n, 3 * n)
    key = np.unique(np.minimum(a, b) * n + np.maximum(a, b))
    pairs = [(int(x // n), int(x % n), int(rng.integers(1, 5))) for x in key if x // n != x % n]
    if not pairs:
        return
    g = graph(n, pairs, rng.integers(1, 6, n))
    k = min(k, n)
    label, _ = local.lp_cluster(g, 6, Options(enforce="strict"))
    weights = np.bincount(label, weights=g.nw)
    assert (weights[np.bincount(label) > 1] <= 6).all()
    coarse, parent = g.contract(label)
    part = rng.integers(0, k, coarse.n)
    assert coarse.cut(part) == g.cut(part[parent]) and coarse.total == g.total
    start = rng.integers(0, k, n)
    caps = Blocks(np.full(k, 1)).caps(g, k, 0.03)
    fixed = local.balance(g, start, caps, np.full(k, 1 / k), Options())
    assert (g.block_weights(fixed, k) <= caps + 1e-6).all()
    better = local.refine(g, fixed, caps, Options())
    assert g.cut(better) <= g.cut(fixed) and (g.block_weights(better, k) <= caps + 1e-6).all()
    assert relaxed(g, local.partition(g, k, Options(c=4, tries=1, repeats=1)), k)


@pytest.mark.parametrize("scheme", list(local.SCHEMES))
def test_rivals_give_k_blocks(scheme):
    g = grid(16, 16)
    part = local.SCHEMES[scheme](g, 8, Options(c=30, tries=1, repeats=1))
    assert len(np.unique(part)) == 8 and g.cut(part) < g.cut(np.arange(g.n) % 8)


def test_same_seed_same_result_and_lanes():
    g = grid(12, 12)
    a, b = (local.partition(g, 4, Options(c=20, lanes=4)) for _ in range(2))
    assert (a == b).all() and relaxed(g, a, 4)


def test_kway_search_ends_where_no_move_gains():
    g, k = grid(60, 60), 4
    start = np.arange(g.n) * 7919 % 1009 % k
    caps = np.full(k, 1.1 * g.n / k)
    part = local.kway_fm(g, start, caps)
    weight = g.block_weights(part, k)
    assert (weight <= caps).all() and (part != start).sum() > 300
    node, lab, rate = local.ratings(g, part, np.ones(g.n, dtype=bool))
    own = np.zeros(g.n, dtype=np.int64)
    own[node[lab == part[node]]] = rate[lab == part[node]]
    assert not ((lab != part[node]) & (weight[lab] + g.nw[node] <= caps[lab]) & (rate > own[node])).any()


@pytest.mark.parametrize("seed", range(4))
def test_kway_search_takes_the_best_move_each_time(seed):
    rng = np.random.default_rng(seed)
    n, k = 40, 5
    pairs = {(int(a), int(b)) for a, b in rng.integers(0, n, (150, 2)) if a < b}
    g = graph(n, [(a, b, int(rng.integers(1, 5))) for a, b in sorted(pairs)], rng.integers(1, 4, n))
    part = rng.integers(0, k, n)
    caps = g.block_weights(part, k) + rng.integers(0, 4, k).astype(float)
    moves, best_at = local._kway_pass(g, part, caps)
    now, free, cuts = part.copy(), np.ones(n, dtype=bool), [g.cut(part)]

    def possible():
        """Gain of each move to a neighbouring block with room, by the definition."""
        out, weight = {}, g.block_weights(now, k)
        for v in np.flatnonzero(free):
            to, w = g.dst[g.ptr[v] : g.ptr[v + 1]], g.w[g.ptr[v] : g.ptr[v + 1]]
            for t in set(now[to].tolist()) - {int(now[v])}:
                if weight[t] + g.nw[v] <= caps[t]:
                    out[int(v), t] = int(w[now[to] == t].sum() - w[now[to] == now[v]].sum())
        return out

    for v, t in moves:
        can = possible()
        assert can[v, t] == max(can.values())
        now[v], free[v] = t, False
        cuts.append(g.cut(now))
    assert not possible() and cuts[best_at] == min(cuts)


@pytest.mark.parametrize("seed", range(12))
def test_kway_search_moves_alike_over_table_and_heaps(seed, monkeypatch):
    monkeypatch.setattr(local, "RUN", 2 + seed % 5)
    rng = np.random.default_rng(seed)
    n, k = 90, 2 + seed % 4
    scale = 1 << 40 if seed == 5 else 1
    pairs = {(int(a), int(b)) for a, b in rng.integers(0, n, (200 + 150 * (seed % 3), 2)) if a < b}
    g = graph(n, [(a, b, scale * int(rng.integers(1, 5))) for a, b in sorted(pairs)], rng.integers(1, 2 if seed % 2 else 6, n))
    part = rng.integers(0, k, n)
    caps = g.block_weights(part, k) + rng.integers(-3, 5, k).astype(float)
    assert local._kway_pass_table(g, part, caps) == local._kway_pass_heaps(g, part, caps)


def test_dense_graphs_are_searched_over_a_table(monkeypatch):
    monkeypatch.setattr(local, "_kway_pass_heaps", lambda *_: pytest.fail("a heap entry for each rise of a gain"))
    n = 24
    g = graph(n, [(a, b, 1 + (a * b) % 3) for a in range(n) for b in range(a + 1, n)], np.ones(n, dtype=np.int64))
    part = local.kway_fm(g, np.arange(n) % 3, np.full(3, 10.0))
    assert g.block_weights(part, 3).max() <= 10


def test_matching_looks_at_spans(monkeypatch):
    g = grid(16, 16)
    whole = local.match_heavy_edge(g, 2, seed=3)
    monkeypatch.setattr(local.Csr, "src", property(lambda _: pytest.fail("the sources of all edges")))
    monkeypatch.setattr(local, "SPAN", 50)
    found = local.match_heavy_edge(g, 2, seed=3)
    assert (found == whole).all() and (np.bincount(found) <= 2).all() and len(np.unique(found)) < 0.7 * g.n
    assert len(np.unique(local.match_two_hop(g, found, 2, 3))) <= len(np.unique(found))


def test_direct_kway_coarsens_to_k_times_c_nodes(monkeypatch):
    asked, descend = [], local.descend
    monkeypatch.setattr(local, "descend", lambda g, k, o, least, *rest: asked.append(least) or descend(g, k, o, least, *rest))
    local.direct_kway(grid(30, 30), 4, Options(c=50, tries=1, repeats=1))
    assert asked == [200]


@pytest.mark.parametrize("seed", range(6))
def test_two_way_search_takes_the_best_move_each_time(seed):
    rng = np.random.default_rng(seed)
    n = 30
    pairs = {(int(a), int(b)) for a, b in rng.integers(0, n, (90, 2)) if a < b}
    g = graph(n, [(a, b, int(rng.integers(1, 5))) for a, b in sorted(pairs)], rng.integers(1, 4, n))
    start = rng.integers(0, 2, n) if seed % 2 else np.zeros(n, dtype=np.int64)
    caps = (g.total * 0.55, g.total * 0.55)

    def plain(side):
        """One pass by the definition: the best of all moves allowed, the least node of equals."""
        side, free, moves = side.copy(), np.ones(n, dtype=bool), []
        state = lambda: (float(np.maximum(g.block_weights(side, 2) - np.array(caps), 0).sum()), g.cut(side))
        first = best = state()
        best_at = idle = 0
        while idle < 60:
            weight = g.block_weights(side, 2)
            must = 0 if weight[0] > caps[0] else 1 if weight[1] > caps[1] else None
            can = []
            for v in np.flatnonzero(free):
                if must is None and weight[1 - side[v]] + g.nw[v] <= caps[1 - side[v]] or side[v] == must:
                    to, w = g.dst[g.ptr[v] : g.ptr[v + 1]], g.w[g.ptr[v] : g.ptr[v + 1]]
                    can.append((-int(np.where(side[to] != side[v], w, -w).sum()), int(v)))
            if not can:
                break
            v = min(can)[1]
            side[v], free[v] = 1 - side[v], False
            moves.append(v)
            if state() < best:
                best, best_at, idle = state(), len(moves), 0
            else:
                idle += 1
        side[moves[best_at:]] = 1 - side[moves[best_at:]]
        return side, best < first

    side, better, left = start, True, 4
    while better and left:
        side, better = plain(side)
        left -= 1
    assert (local.two_way_fm(g, start, caps) == side).all()


def test_blocks_are_dealt_once(monkeypatch):
    monkeypatch.setattr(local.Csr, "induced", lambda *_: pytest.fail("a pass over all edges for one block"))
    g = grid(20, 20)
    part = np.arange(g.n) * 7919 % 1009 % 37
    part[part == 5] = 4
    found = list(g.blocks(part, 37))
    monkeypatch.undo()
    for b, (nodes, sub) in enumerate(found):
        own = g.induced(np.flatnonzero(part == b))
        assert (nodes == np.flatnonzero(part == b)).all() and (sub.ptr == own.ptr).all()
        assert all((getattr(sub, x) == getattr(own, x)).all() for x in ("nw", "src", "dst", "w"))
    monkeypatch.setattr(local.Csr, "induced", lambda *_: pytest.fail("a pass over all edges for one block"))
    assert len(np.unique(local.partition(g, 128, Options(c=40, tries=1, repeats=1)))) == 128


def test_spans_do_not_change_results(monkeypatch):
    g = grid(16, 16)
    whole = {s: local.SCHEMES[s](g, 8, Options(c=30, tries=1, repeats=1)) for s in local.SCHEMES}
    monkeypatch.setattr(local, "SPAN", 50)
    for s, part in whole.items():
        assert (local.SCHEMES[s](g, 8, Options(c=30, tries=1, repeats=1)) == part).all()
    a = g.src < g.dst
    h = local.Csr.of_pairs(g.nw, g.dst[a], g.src[a], g.w[a])
    assert (h.src == g.src).all() and (h.dst == g.dst).all() and (h.ptr == g.ptr).all()


@pytest.mark.parametrize(("n", "edges", "k", "c", "seed"), [(242, 5082, 121, 7, 206), (114, 1368, 57, 13, 211), (280, 4200, 70, 16, 232), (395, 4345, 197, 10, 245)])
def test_blocks_that_shrank_still_become_all_they_were_to(n, edges, k, c, seed):
    rng = np.random.default_rng(seed)
    g = graph(n, sorted({(int(min(x)), int(max(x))) for x in rng.integers(0, n, (edges, 2)) if x[0] != x[1]}))
    part = local.partition(g, k, Options(c=c, tries=1, repeats=1))
    assert len(np.unique(part)) == k and relaxed(g, part, k)
    held = local.occupy(g, np.zeros(n, dtype=np.int64), 5)
    assert len(np.unique(held)) == 5 and (held != 0).sum() == 4
