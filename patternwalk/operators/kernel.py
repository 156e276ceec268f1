"""One graph in a worker: neighbour sets, scores, enumeration and the walk, on bit masks.

A vertex set is a Python integer with one bit per vertex. The replacements of a vertex
``u`` of a piece are the outside vertices that touch every component of what remains,
which is an intersection of unions of adjacency masks; degrees are bit counts.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

from patternwalk.functions.rng import uniform
from patternwalk.operators.canon import raw_code


def bits(mask: int) -> Iterator[int]:
    while mask:
        low = mask & -mask
        yield low.bit_length() - 1
        mask ^= low


def nth_bit(mask: int, n: int) -> int:
    for _ in range(n):
        mask &= mask - 1
    return (mask & -mask).bit_length() - 1


class Graph:
    """A packed row: local vertex numbers ``0..n-1`` in order of ``vids``."""

    def __init__(self, vids, vlab, ea, eb, elab, etyp) -> None:
        self.vids, self.labels = [int(v) for v in vids], list(vlab)
        self.adj = [0] * len(self.vids)
        self.near: list[dict[int, tuple[str, int]]] = [{} for _ in self.vids]
        self.edges = [(int(a), int(b)) for a, b in zip(ea, eb)]
        for (a, b), x, t in zip(self.edges, elab, etyp):
            self.adj[a] |= 1 << b
            self.adj[b] |= 1 << a
            self.near[a][b] = self.near[b][a] = (x, int(t))

    def parts(self, rest: int) -> list[int]:
        """The components of a vertex set, as masks."""
        out = []
        while rest:
            grown = rest & -rest
            frontier = grown
            while frontier:
                reach = 0
                for v in bits(frontier):
                    reach |= self.adj[v]
                frontier = reach & rest & ~grown
                grown |= frontier
            out.append(grown)
            rest &= ~grown
        return out

    def around(self, mask: int) -> int:
        out = 0
        for v in bits(mask):
            out |= self.adj[v]
        return out

    def boxes(self, state: int) -> list[tuple[int, int]]:
        """Each vertex of a piece with the mask of its replacements.

        What all others touch comes from running unions from both ends. A vertex with one
        neighbour in the piece never holds it together, so most rests need no search.
        """
        adj, vs = self.adj, list(bits(state))
        after = [0] * (len(vs) + 1)
        for i in range(len(vs) - 1, -1, -1):
            after[i] = after[i + 1] | adj[vs[i]]
        out, before = [], 0
        for i, u in enumerate(vs):
            rest = state & ~(1 << u)
            if (adj[u] & rest).bit_count() <= 1 or self._whole(rest):
                can = (before | after[i + 1]) & ~state
            else:
                can = ~state & ((1 << len(adj)) - 1)
                for part in self.parts(rest):
                    can &= self.around(part)
                    if not can:
                        break
            out.append((u, can))
            before |= adj[u]
        return out

    def _whole(self, state: int) -> bool:
        """Whether a vertex set is connected."""
        grown = new = state & -state
        while new:
            v = new.bit_length() - 1
            more = self.adj[v] & state & ~grown
            grown |= more
            new = (new & ~(1 << v)) | more
        return grown == state

    def update_boxes(self, boxes: list[tuple[int, int]], state: int, u: int, w: int) -> tuple[int, list[tuple[int, int]]]:
        """State and boxes after ``u`` was replaced by ``w``. The box of ``w`` is the old box of ``u`` with ``w`` and ``u`` exchanged; the others are drawn afresh where they must be."""
        after = state & ~(1 << u) | 1 << w
        old = dict(boxes)
        out = []
        for v in bits(after):
            if v == w:
                out.append((w, (old[u] & ~(1 << w)) | (1 << u)))
                continue
            can = ~after & ((1 << len(self.adj)) - 1)
            for part in self.parts(after & ~(1 << v)):
                can &= self.around(part)
            out.append((v, can))
        return after, out

    def induced(self, state: int) -> list[tuple[int, int]]:
        return [(a, b) for a in bits(state) for b in bits(self.adj[a] & state) if a < b]

    def types(self, pairs) -> list[int]:
        return [self.near[a][b][1] for a, b in pairs]

    def raw(self, state: int, pairs=None) -> str:
        order = list(bits(state))
        place = {v: i for i, v in enumerate(order)}
        pairs = self.induced(state) if pairs is None else pairs
        return raw_code([self.labels[v] for v in order], [(place[a], place[b], self.near[a][b][0]) for a, b in pairs])

    def enumerate(self, p: int) -> Iterator[int]:
        """Every connected vertex set of size ``p`` once: a set grows only by vertices above its first one that no earlier member touches."""
        if p == 1:
            yield from (1 << v for v in range(len(self.adj)))
            return
        for root in range(len(self.adj)):
            above = ~((1 << (root + 1)) - 1)
            todo = [(1 << root, self.adj[root] & above, (1 << root) | self.adj[root])]
            while todo:
                state, open_, touched = todo.pop()
                size = state.bit_count()
                while open_:
                    low = open_ & -open_
                    open_ ^= low
                    v = low.bit_length() - 1
                    if size + 1 == p:
                        yield state | low
                    else:
                        todo.append((state | low, open_ | (self.adj[v] & above & ~touched), touched | self.adj[v]))

    def spanning_subsets(self, state: int) -> Iterator[list[tuple[int, int]]]:
        """All connected edge subsets that reach every vertex of a set."""
        pairs = self.induced(state)
        for pick in range(1, 1 << len(pairs)):
            some = [e for i, e in enumerate(pairs) if pick >> i & 1]
            if connected(state, some):
                yield some


def connected(state: int, pairs) -> bool:
    grown = state & -state
    while True:
        more = grown
        for a, b in pairs:
            if (more >> a & 1) != (more >> b & 1):
                more |= 1 << a | 1 << b
        if more == grown:
            return grown == state
        grown = more


def plain_parts(state: int, pairs: frozenset, u: int) -> list[int]:
    """Components of a non-induced piece without ``u``."""
    rest, out = state & ~(1 << u), []
    while rest:
        grown = rest & -rest
        changed = True
        while changed:
            changed = False
            for a, b in pairs:
                if u not in (a, b) and (grown >> a & 1) != (grown >> b & 1):
                    grown |= 1 << a | 1 << b
                    changed = True
        out.append(grown)
        rest &= ~grown
    return out


def plain_choices(g: Graph, state: int, pairs: frozenset) -> list[tuple[int, int, list[int], int]]:
    """``(u, w, links per component, ways)``: replacing ``u`` by ``w`` with a non-empty set of edges to each component."""
    out = []
    for u in bits(state):
        parts = plain_parts(state, pairs, u)
        can = ~state & ((1 << len(g.adj)) - 1)
        for part in parts:
            can &= g.around(part)
        for w in bits(can):
            links = [g.adj[w] & part for part in parts]
            ways = 1
            for x in links:
                ways *= (1 << x.bit_count()) - 1
            out.append((u, w, links, ways))
    return out


def plain_move(g: Graph, state: int, pairs: frozenset, n: int) -> tuple[int, frozenset]:
    """The ``n``-th neighbour of a non-induced piece."""
    for u, w, links, ways in plain_choices(g, state, pairs):
        if n >= ways:
            n -= ways
            continue
        kept = {e for e in pairs if u not in e}
        for x in links:
            ends = list(bits(x))
            n, pick = divmod(n, (1 << len(ends)) - 1)
            kept |= {(min(w, v), max(w, v)) for i, v in enumerate(ends) if pick + 1 >> i & 1}
        return state & ~(1 << u) | 1 << w, frozenset(kept)
    raise IndexError(n)


@dataclass
class Scores:
    """The target: ``uniform``, ``s1`` (mean support of the edges), ``s2`` (graphs that have all the edges' types), or a function of the types.

    ``support`` has a number per edge type and ``ids`` a mask of graphs per edge type. Scores are ratios of integers.
    """

    name: str
    support: list[int] = field(default_factory=list)
    ids: list[int] = field(default_factory=list)
    custom: Callable | None = None
    memo: dict = field(default_factory=dict)

    def of(self, types: list[int]) -> tuple[int, int]:
        if self.name == "uniform":
            return 1, 1
        if self.name == "s1":
            return sum(self.support[t] for t in types), len(types)
        key = frozenset(types)
        found = self.memo.get(key)
        if found is None:
            if self.name == "s2":
                mask = -1
                for t in key:
                    mask &= self.ids[t]
                found = (max(1, mask.bit_count()), 1)
            elif self.name == "s2_bound":
                found = (min(self.support[t] for t in key), 1)
            else:
                value = self.custom(types)
                return (value, 1) if isinstance(value, int) else value
            if len(self.memo) > 1 << 18:
                self.memo.clear()
            self.memo[key] = found
        return found


def thinned(g: Graph, state: int, pairs: frozenset, key: tuple) -> frozenset:
    """A random connected part of an induced piece's edges that reaches all its vertices: edges in a drawn order, those that join parts kept, each other one by a coin."""
    order = sorted(pairs, key=lambda e: uniform(*key, g.vids[e[0]], g.vids[e[1]]))
    root = {v: v for v in bits(state)}

    def top(v: int) -> int:
        while root[v] != v:
            root[v] = v = root[root[v]]
        return v

    kept = set()
    for a, b in order:
        x, y = top(a), top(b)
        if x != y or uniform(*key, g.vids[a], g.vids[b], "coin") < 0.5:
            root[y] = x
            kept.add((a, b))
    return frozenset(kept)


def accepts(u: float, dx: int, sx: tuple[int, int], dy: int, sy: tuple[int, int]) -> bool:
    """The Metropolis-Hastings test for uniform proposals over neighbours, without a division."""
    return u * (dy * sx[0] * sy[1]) <= dx * sy[0] * sx[1]


def mh_accept(f_x: float, f_y: float, q_xy: float, q_yx: float, u: float) -> bool:
    """The test for any target and proposal."""
    return u * f_x * q_xy <= f_y * q_yx


class Walk:
    """One chain on one graph. ``attempts`` counts proposals since the start; with the key it fixes every draw."""

    def __init__(self, g: Graph, p: int, scores: Scores, key: tuple, induced: bool = True, emit: str = "accepted") -> None:
        self.g, self.p, self.scores, self.key, self.is_induced, self.emit = g, p, scores, key, induced, emit
        self.state = self.pairs = None
        self.attempts = 0

    def start(self) -> bool:
        """Grow a first piece from a random edge; false if the graph is too small."""
        g = self.g
        if len(g.vids) < self.p or not g.edges:
            return False
        a, b = g.edges[int(uniform(*self.key, 0, 0) * len(g.edges))]
        state, pairs = 1 << a | 1 << b, {(min(a, b), max(a, b))}
        for k in range(1, self.p - 1):
            edge = g.around(state) & ~state
            if not edge:
                return False
            w = nth_bit(edge, int(uniform(*self.key, 0, k) * edge.bit_count()))
            ends = list(bits(g.adj[w] & state))
            pairs |= {(min(v, w), max(v, w)) for v in ends}
            state |= 1 << w
        self.set(state, frozenset(pairs))
        return True

    def set(self, state: int, pairs: frozenset | None = None) -> None:
        self.state = state
        self.pairs = frozenset(self.g.induced(state)) if self.is_induced else pairs
        self._measure()

    def _measure(self) -> None:
        self.degree, self.choices = self._degree(self.state, self.pairs)
        self.score = self.scores.of(self.g.types(self.pairs))

    def _degree(self, state: int, pairs: frozenset):
        if self.is_induced:
            boxes = self.g.boxes(state)
            return sum(m.bit_count() for _, m in boxes), boxes
        choices = plain_choices(self.g, state, pairs)
        return sum(c[3] for c in choices), None

    def propose(self, u: float) -> tuple[int, frozenset]:
        n = int(u * self.degree)
        if not self.is_induced:
            return plain_move(self.g, self.state, self.pairs, n)
        for v, mask in self.choices:
            c = mask.bit_count()
            if n < c:
                after = self.state & ~(1 << v) | 1 << nth_bit(mask, n)
                return after, frozenset(self.g.induced(after))
            n -= c
        raise IndexError(n)

    def sample(self) -> int:
        """Move until a proposal is accepted (or propose once, with ``emit='lazy'``); returns the number of proposals."""
        if not self.degree:
            return 0
        tried = 0
        while True:
            tried += 1
            self.attempts += 1
            y, pairs = self.propose(uniform(*self.key, self.attempts, 0))
            dy, choices = self._degree(y, pairs)
            sy = self.scores.of(self.g.types(pairs))
            if accepts(uniform(*self.key, self.attempts, 1), self.degree, self.score, dy, sy):
                self.state, self.pairs, self.degree, self.choices, self.score = y, pairs, dy, choices, sy
                return tried
            if self.emit == "lazy":
                return tried
