import random
from itertools import combinations

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from patternwalk.operators.canon import code_text, decode_code, dfs_code, edge_list_code, perm_code, wl_key
from patternwalk.operators.kernel import Graph, Scores, Walk, accepts, bits, connected, mh_accept, plain_choices, plain_move
from tests.toy import graph, mask

SCORES = Scores("s2", [3, 2, 3, 2], [0b111, 0b101, 0b111, 0b011])


def test_counts_of_the_toy():
    g = [graph(i) for i in (1, 2, 3)]
    assert [len(list(x.enumerate(3))) for x in g] == [15, 4, 3]
    assert [len(list(x.enumerate(4))) for x in g] == [22, 3, 1]
    assert len(list(g[0].enumerate(2))) == 10
    assert sum(len(list(g[0].spanning_subsets(s))) for s in g[0].enumerate(4)) == 35
    assert len({dfs_code(x.raw(s)) for x in g for s in x.enumerate(3)}) == 8
    assert len({dfs_code(x.raw(s)) for x in g for s in x.enumerate(4)}) == 17


def test_boxes_before_and_after_a_move():
    g = graph(1)
    s = mask([0, 1, 2, 3])
    boxes = g.boxes(s)
    assert {u: list(bits(m)) for u, m in boxes} == {0: [4, 5], 1: [4, 5, 7], 2: [], 3: [5, 7]}
    after, updated = g.update_boxes(boxes, s, 3, 5)
    assert after == mask([0, 1, 2, 5]) and sorted(updated) == sorted(g.boxes(after))
    for state in g.enumerate(4):
        for u, m in g.boxes(state):
            for w in bits(m):
                there, boxes = g.update_boxes(g.boxes(state), state, u, w)
                assert sorted(boxes) == sorted(g.boxes(there))


@pytest.mark.parametrize(("vs", "d", "s1", "s2"), [((0, 1, 2, 3), 7, (11, 4), 2), ((0, 1, 2, 5), 9, (12, 4), 3), ((0, 1, 2, 7), 6, (11, 4), 2), ((1, 2, 3, 5), 8, (8, 3), 2)])
def test_degrees_and_scores(vs, d, s1, s2):
    g, s = graph(1), mask(vs)
    t = g.types(g.induced(s))
    assert sum(m.bit_count() for _, m in g.boxes(s)) == d
    assert Scores("s1", [3, 2, 3, 2]).of(t) == s1 and SCORES.of(t) == (s2, 1)


def test_acceptance():
    assert accepts(1.0, 7, (2, 1), 9, (3, 1))
    assert accepts(6 / 7 - 1e-12, 9, (3, 1), 7, (2, 1)) and not accepts(6 / 7 + 1e-9, 9, (3, 1), 7, (2, 1))
    assert mh_accept(2, 3, 1 / 7, 1 / 9, 1.0) and not mh_accept(3, 2, 1 / 9, 1 / 7, 0.9)


def test_one_state_and_too_small():
    w = Walk(graph(3), 4, SCORES, (0, 0, 3))
    assert w.start() and w.degree == 0 and w.sample() == 0
    assert not Walk(graph(3), 5, SCORES, (0, 0, 3)).start()


def test_plain_neighbours_are_symmetric_and_counted():
    g = graph(1)
    states = [(s, frozenset(e)) for s in g.enumerate(4) for e in g.spanning_subsets(s)]
    near = {}
    for s, e in states:
        d = sum(c[3] for c in plain_choices(g, s, e))
        moves = [plain_move(g, s, e, n) for n in range(d)]
        assert len(set(moves)) == d and all(connected(t, f) and t.bit_count() == 4 for t, f in moves)
        near[s, e] = set(moves)
    assert all((s, e) in near[y] for (s, e), ys in near.items() for y in ys)


def test_exact_law_of_both_emissions():
    """The lazy chain keeps the target; the accepted moves alone keep the target times the acceptance rate."""
    g = graph(1)
    states = list(g.enumerate(4))
    f = {s: SCORES.of(g.types(g.induced(s)))[0] for s in states}
    near = {s: [s & ~(1 << u) | 1 << w for u, m in g.boxes(s) for w in bits(m)] for s in states}
    p = {s: {y: min(1.0, len(near[s]) * f[y] / (len(near[y]) * f[s])) / len(near[s]) for y in near[s]} for s in states}
    rate = {s: sum(p[s].values()) for s in states}
    z = sum(f.values())
    lazy = {y: sum(f[x] / z * p[x].get(y, 0.0) for x in states) + f[y] / z * (1 - rate[y]) for y in states}
    assert max(abs(lazy[s] - f[s] / z) for s in states) < 1e-12
    w = {s: f[s] * rate[s] for s in states}
    jump = {y: sum(w[x] * p[x].get(y, 0.0) / rate[x] for x in states) for y in states}
    assert max(abs(jump[s] - w[s]) for s in states) < 1e-12


def test_visits_approach_the_target():
    g = graph(1)
    walk = Walk(g, 4, SCORES, (5, 0, 1), emit="lazy")
    walk.start()
    n, seen = 40_000, {}
    for _ in range(n):
        walk.sample()
        seen[walk.state] = seen.get(walk.state, 0) + 1
    f = {s: SCORES.of(g.types(g.induced(s)))[0] for s in g.enumerate(4)}
    z = sum(f.values())
    assert sum(abs(seen.get(s, 0) / n - f[s] / z) for s in f) / 2 < 0.03


@st.composite
def pieces(draw):
    n = draw(st.integers(2, 6))
    labels = draw(st.lists(st.sampled_from("AB"), min_size=n, max_size=n))
    edges = [(draw(st.integers(0, i - 1)), i, draw(st.sampled_from("xy"))) for i in range(1, n)]
    have = {(a, b) for a, b, _ in edges}
    for a, b in combinations(range(n), 2):
        if (a, b) not in have and draw(st.booleans()):
            edges.append((a, b, draw(st.sampled_from("xy"))))
    return labels, edges, draw(st.permutations(range(n)))


@settings(max_examples=150, deadline=None)
@given(pieces())
def test_codes_name_the_class(piece):
    labels, edges, order = piece
    moved = [None] * len(labels)
    for i, c in enumerate(labels):
        moved[order[i]] = c
    renamed = [(min(order[a], order[b]), max(order[a], order[b]), x) for a, b, x in edges]
    code = code_text(labels, edges)
    assert code == code_text(moved, renamed) and wl_key(labels, edges) == wl_key(moved, renamed)
    if len(labels) <= 5:
        assert perm_code(*decode_code(code)) == perm_code(labels, edges)


def test_dfs_and_permutation_codes_part_pieces_alike():
    rng = random.Random(2)
    by = {}
    for _ in range(400):
        n = rng.randrange(2, 5)
        labels = [rng.choice("AB") for _ in range(n)]
        edges = [(rng.randrange(i), i, rng.choice("xy")) for i in range(1, n)]
        by.setdefault(code_text(labels, edges), set()).add(perm_code(labels, edges))
    assert all(len(x) == 1 for x in by.values()) and len({next(iter(x)) for x in by.values()}) == len(by)
    assert edge_list_code(["b", "a", "c"], [(0, 1, "x"), (1, 2, "y")]) == "a,x,b;a,y,c"


def test_enumeration_against_all_subsets():
    rng = random.Random(6)
    for _ in range(10):
        n = 9
        es = [(a, b) for a, b in combinations(range(n), 2) if rng.random() < 0.25]
        g = Graph(range(n), ["A"] * n, [a for a, _ in es], [b for _, b in es], ["x"] * len(es), [0] * len(es))
        for p in (1, 2, 3, 5):
            want = {mask(c) for c in combinations(range(n), p) if len(g.parts(mask(c))) == 1}
            got = list(g.enumerate(p))
            assert len(got) == len(set(got)) and set(got) == want
