"""Kernels against brute force on small random multigraphs, and the laws that certificates obey."""

import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from sparsecert.baselines.per_edge import run_steps
from sparsecert.functions.bounds import ackermann, inv_ackermann
from sparsecert.kernels import answers, fold
from sparsecert.kernels.certs import EDGE_KERNELS, FOREST_KERNELS, VERTEX_KERNELS, Edges, cascade, max_back
from sparsecert.kernels.fold import GroupPolicy
from sparsecert.kernels.forest import labels_of
from tests import brute


def edges_of(pairs, weights=None):
    n = len(pairs)
    return Edges(np.array([a for a, _ in pairs], dtype=np.int64), np.array([b for _, b in pairs], dtype=np.int64), np.array(weights or [0] * n, dtype=np.int64), np.arange(n))


def graphs(count, seed):
    draw = random.Random(seed)
    for _ in range(count):
        n = draw.randint(4, 7)
        yield n, [tuple(draw.sample(range(n), 2)) for _ in range(draw.randint(n, 4 * n))], draw.randint(1, 4)


def test_k_vertex_verdicts_and_separators():
    for n, pairs, k in graphs(250, 1):
        want = brute.k_vertex(range(n), pairs, k)
        for kernel in VERTEX_KERNELS:
            cert = fold.fold_all(edges_of(pairs), fold.of("vertex", k, kernel=kernel), GroupPolicy.linear(), n).cert
            got, gone = answers.k_vertex_connected(cert, np.arange(n), k)
            assert got == want, (pairs, k, kernel)
            if not got:
                assert len(gone) < k
                assert brute.parts([v for v in range(n) if v not in gone], pairs) > 1


def test_k_edge_verdicts_and_cuts():
    for n, pairs, k in graphs(250, 2):
        want = min(brute.local_edge(range(n), pairs, 0, y) for y in range(1, n)) >= k
        for kernel in EDGE_KERNELS:
            cert = fold.fold_all(edges_of(pairs), fold.of("edge", k, kernel=kernel), GroupPolicy.linear(), n).cert
            got, side = answers.k_edge_connected(cert, np.arange(n), k)
            assert got == want, (pairs, k, kernel)
            if not got:
                assert 0 < len(side) < n
                assert brute.cut(pairs, set(side.tolist())) < k


def test_certificates_keep_capped_connectivity_of_all_pairs():
    for n, pairs, k in graphs(60, 3):
        e = edges_of(pairs)
        vertex = fold.fold_all(e, fold.of("vertex", k), GroupPolicy.linear(), n).cert
        edge = fold.fold_all(e, fold.of("edge", k), GroupPolicy.linear(), n).cert
        for x in range(n):
            for y in range(x):
                assert answers.local_vertex(vertex, x, y, k)[0] == brute.local_vertex(range(n), pairs, x, y, k)
                assert answers.local_edge(edge, x, y, k)[0] == min(k, brute.local_edge(range(n), pairs, x, y))


def test_small_separators_leave_the_same_parts_in_certificate_and_graph():
    for n, pairs, k in graphs(120, 4):
        e = edges_of(pairs)
        cert = fold.fold_all(e, fold.of("vertex", k), GroupPolicy.linear(), n).cert
        held = list(zip(cert.u.tolist(), cert.v.tolist(), strict=True))
        for gone in [(), *((v,) for v in range(n))]:
            if len(gone) < k:
                left = [v for v in range(n) if v not in gone]
                if brute.parts(left, held) > 1:
                    assert brute.parts(left, held) == brute.parts(left, pairs)


def test_low_points():
    for n, pairs, _ in graphs(200, 5):
        cuts, bridges = answers.low_points(edges_of(pairs))
        whole = brute.parts(range(n), pairs)
        seen = {v for p in pairs for v in p}
        assert set(cuts) == {v for v in seen if brute.parts([x for x in range(n) if x != v], pairs) > whole}
        assert set(bridges) == {i for i in range(len(pairs)) if brute.parts(range(n), pairs[:i] + pairs[i + 1 :]) > whole}


@given(st.lists(st.tuples(st.integers(0, 12), st.integers(0, 12), st.integers(0, 4)), max_size=60), st.integers(1, 9))
@settings(max_examples=150, deadline=None)
def test_forests_are_the_same_by_all_kernels_and_groups(rows, r):
    rows = [x for x in rows if x[0] != x[1]]
    e = edges_of([(a, b) for a, b, _ in rows], [w for *_, w in rows])
    found = [set(kernel(e).tolist()) for kernel in FOREST_KERNELS.values()]
    assert found[0] == found[1] == found[2]
    for options in ({}, {"prefilter": True}, {"pad_tail": True}, {"kernel": "grow"}):
        cert = fold.fold_all(e, fold.of("min_forest", **options), GroupPolicy.edges(r), 13).cert
        assert set(cert.eid.tolist()) == found[0]


@given(st.lists(st.tuples(st.integers(0, 9), st.integers(0, 9)), max_size=40))
@settings(max_examples=150, deadline=None)
def test_odd_cycles(pairs):
    pairs = [p for p in pairs if p[0] != p[1]]
    e = edges_of(pairs)
    cycle = answers.odd_cycle(e)
    cert = fold.fold_all(e, fold.of("bipartite"), GroupPolicy.edges(4), 10).cert
    assert bool(cycle) == bool(answers.odd_cycle(cert))
    if cycle:
        there = {frozenset(p) for p in pairs}
        assert len(cycle) % 2 == 1
        assert all(frozenset((a, b)) in there for a, b in zip(cycle, cycle[1:] + cycle[:1], strict=True))
    double = [x for a, b in pairs for x in ((2 * a, 2 * b + 1), (2 * a + 1, 2 * b))]
    if pairs:
        ids, label = labels_of(*(np.array(c) for c in zip(*double, strict=True)))
        place = dict(zip(ids.tolist(), label.tolist(), strict=True))
        assert bool(cycle) == any(place[2 * a] == place[2 * a + 1] for a, _ in pairs)


def test_union_and_transitivity_are_strong():
    """The certificate united with any other graph answers as the graph united with it does."""
    draw = random.Random(6)
    for n, pairs, k in graphs(150, 7):
        extra = [tuple(draw.sample(range(n), 2)) for _ in range(draw.randint(0, 5))]
        for name, ask in (("vertex", answers.k_vertex_connected), ("edge", answers.k_edge_connected)):
            prop = fold.of(name, k)
            cert = fold.fold_all(edges_of(pairs), prop, GroupPolicy.linear(), n).cert
            again = cert.take(prop.keep(cert))
            want = ask(edges_of(pairs + extra), np.arange(n), k)[0]
            assert ask(Edges.join(cert, edges_of(extra)) if extra else cert, np.arange(n), k)[0] == want
            assert ask(Edges.join(again, edges_of(extra)) if extra else again, np.arange(n), k)[0] == want


def test_copies_crowd_out_a_needed_edge_unless_dropped():
    """Doubled s-a and s-b and a single a-b: without dropping copies the 2-vertex certificate loses a-b."""
    pairs = [(0, 1), (0, 1), (0, 2), (0, 2), (1, 2)]
    e = edges_of(pairs)
    assert 4 not in max_back(e, 2)
    assert brute.k_vertex(range(3), pairs, 2)
    cert = fold.fold_all(e, fold.of("vertex", 2), GroupPolicy.linear(), 3).cert
    assert answers.k_vertex_connected(cert, np.arange(3), 2)[0]
    kept = fold.fold_all(e, fold.of("edge", 2), GroupPolicy.linear(), 3).cert
    assert answers.k_edge_connected(kept, np.arange(3), 2)[0]


def test_bounds_of_sizes_and_memory():
    for n, pairs, k in graphs(150, 8):
        e = edges_of(pairs)
        for name in ("components", "bipartite", "vertex", "edge"):
            prop = fold.of(name, k, tail="resolve")
            f = fold.fold_all(e, prop, GroupPolicy.linear(), n)
            assert len(f.cert) <= prop.bound(n)
            assert f.peak <= prop.bound(n) + n
            assert len(f.groups) == -(-len(e) // n)
            assert f.edges_read == len(e)
            assert set(f.cert.eid.tolist()) <= set(range(len(e)))
        f = fold.fold_all(e, fold.of("min_forest"), GroupPolicy.nlogn(), n)
        assert all(g["merged"] < 2 * GroupPolicy.nlogn().size(n) for g in f.groups)


def test_last_group_is_appended_or_solved():
    e = edges_of([(0, 1), (1, 2), (2, 0), (0, 1)])
    assert len(fold.fold_all(e, fold.of("components"), GroupPolicy.edges(3), 3).cert) == 3
    assert len(fold.fold_all(e, fold.of("components", tail="resolve"), GroupPolicy.edges(3), 3).cert) == 2


def test_small_and_complete_graphs():
    triangle = edges_of([(0, 1), (1, 2), (2, 0)])
    assert answers.k_vertex_connected(triangle, np.arange(3), 3)[0]
    assert not answers.k_vertex_connected(triangle, np.arange(3), 3, strict=True)[0]
    assert answers.k_vertex_connected(Edges.empty(), np.arange(1), 2)[0]
    assert not answers.k_vertex_connected(Edges.empty(), np.arange(2), 1)[0]
    assert answers.k_edge_connected(Edges.empty(), np.arange(1), 3)[0]
    with pytest.raises(ValueError):
        answers.k_vertex_connected(triangle, None, 0)


def test_golden_graphs():
    doubled_path = edges_of([(0, 1), (0, 1), (1, 2), (1, 2)])
    assert answers.k_edge_connected(doubled_path, None, 2)[0]
    assert not answers.k_vertex_connected(doubled_path, np.arange(3), 2)[0]
    two_cliques = [(a, b) for a in range(4) for b in range(a)] + [(a, b) for a in range(3, 7) for b in range(3, a)]
    assert answers.low_points(edges_of(two_cliques))[0] == [3]
    grid = [(3 * r + c, 3 * r + c + 1) for r in range(3) for c in range(2)] + [(3 * r + c, 3 * r + c + 3) for r in range(2) for c in range(3)]
    assert answers.k_vertex_connected(edges_of(grid), np.arange(9), 2)[0]
    assert not answers.k_vertex_connected(edges_of(grid), np.arange(9), 3)[0]


def test_cascade_is_not_for_vertex_connectivity():
    draw, wrong = random.Random(9), 0
    for _ in range(4000):
        n = draw.randint(5, 8)
        pairs = list({tuple(sorted(draw.sample(range(n), 2))) for _ in range(draw.randint(2 * n, 4 * n))})
        draw.shuffle(pairs)
        k = draw.randint(2, 3)
        e = edges_of(pairs)
        wrong += answers.k_vertex_connected(e, np.arange(n), k)[0] != answers.k_vertex_connected(e.take(cascade(e, k)), np.arange(n), k)[0]
    assert wrong > 0


def test_per_edge_methods_answer_alike():
    for n, pairs, k in graphs(200, 11):
        e = edges_of(pairs, [(7 * i) % 5 for i in range(len(pairs))])
        cert = e.take(run_steps(e, "vertex", k)[0])
        assert answers.k_vertex_connected(cert, np.arange(n), k)[0] == brute.k_vertex(range(n), pairs, k)
        want = min(brute.local_edge(range(n), pairs, 0, y) for y in range(1, n)) >= k
        for step in ("edge_flow", "edge_cascade"):
            assert answers.k_edge_connected(e.take(run_steps(e, step, k)[0]), np.arange(n), k)[0] == want
        best = set(FOREST_KERNELS["sort"](e).tolist())
        assert set(run_steps(e, "min_forest_walk")[0].tolist()) == best == set(run_steps(e, "min_forest_linkcut")[0].tolist())
        assert len(run_steps(e, "components")[0]) == n - brute.parts(range(n), pairs)
        assert bool(answers.odd_cycle(e.take(run_steps(e, "bipartition")[0]))) == bool(answers.odd_cycle(e))


def test_inverse_ackermann():
    assert [inv_ackermann(n, n) for n in (1, 3, 4, 15, 16, 65535, 65536, 1 << 40)] == [1, 1, 2, 2, 3, 3, 4, 4]
    assert ackermann(2, 2) == 16
    assert all(inv_ackermann(n * n.bit_length(), n) == 1 for n in (10, 1000, 10**6))
