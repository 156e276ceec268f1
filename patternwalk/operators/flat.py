"""All pieces of many packed graphs at once, as arrays: enumeration, names, neighbours, scores.

Pieces and pairs of pieces stay in the worker that holds their graph; only what a query
counts of them leaves it. Vertices are numbered over all graphs of a chunk, in order of
``vids`` within a graph, so a piece is a row of rising numbers.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from patternwalk.operators.canon import raw_code

#: About so many pieces are held at once, and so many pairs of pieces; one graph's pieces and one core's pairs are not divided.
PIECES, PAIRS = 60_000, 2_000_000


def spread(counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For runs of these lengths: the run and the place in it of each of their items."""
    run = np.repeat(np.arange(len(counts)), counts)
    return run, np.arange(len(run)) - np.repeat(np.cumsum(counts) - counts, counts)


def key_of(columns: list[np.ndarray], size: int) -> np.ndarray:
    """One number for each row of numbers from -1 to below ``size``: equal rows, equal numbers, in the order of the rows."""
    key, bound = columns[0].astype(np.int64) + 1, size + 1
    for c in columns[1:]:
        if bound * (size + 1) >= 1 << 62:
            key = np.unique(key, return_inverse=True)[1].astype(np.int64)
            bound = len(key) + 1
        key, bound = key * (size + 1) + c + 1, bound * (size + 1)
    return key


def lists(rows: np.ndarray, kind=np.int64) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.arange(0, rows.size + 1, max(1, rows.shape[1]), dtype=np.int32)), pa.array(rows.ravel().astype(kind)))


@dataclass
class Chunk:
    """Graphs with their vertices and edges; ``a < b`` are vertex numbers, labels are places in ``names`` and ``links``, which are in order."""

    gids: np.ndarray
    graph: np.ndarray
    vids: np.ndarray
    label: np.ndarray
    names: list[str]
    a: np.ndarray
    b: np.ndarray
    elabel: np.ndarray
    links: list[str]

    def __post_init__(self) -> None:
        n = len(self.vids)
        ends, others = np.concatenate([self.a, self.b]), np.concatenate([self.b, self.a])
        order = np.argsort(ends, kind="stable")
        self.other, self.edge_at = others[order], order % max(1, len(self.a))
        self.first = np.concatenate([[0], np.cumsum(np.bincount(ends, minlength=n))]).astype(np.int64)
        code = self.a * n + self.b
        self.by_code = np.argsort(code)
        self.code = code[self.by_code]
        self.simple = not (self.code[1:] == self.code[:-1]).any()

    def edge_between(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """The edge of each pair ``x < y``, or -1."""
        if not len(self.code):
            return np.full(len(x), -1, np.int64)
        want = x * len(self.vids) + y
        at = np.minimum(np.searchsorted(self.code, want), len(self.code) - 1)
        return np.where(self.code[at] == want, self.by_code[at], -1)

    def pieces(self, p: int) -> np.ndarray:
        """Every connected vertex set of size ``p``, once, in order."""
        n = len(self.vids)
        if p == 1:
            return np.arange(n)[:, None]
        sets = [self.a, self.b]
        for k in range(2, p):  # a set grows from its least vertex on, by vertices above it
            found = []
            for at in range(k):
                ends = sets[at]
                run, place = spread(self.first[ends + 1] - self.first[ends])
                new = self.other[self.first[ends][run] + place]
                above = np.flatnonzero(new > sets[0][run])
                run, new = run[above], new[above]
                rows, fresh = [], np.ones(len(new), bool)
                for c in sets:
                    own = c[run]
                    fresh &= own != new
                    rows.append(np.minimum(own, new))
                    new = np.maximum(own, new)
                found.append([c[fresh] for c in (*rows, new)])
            grown = [np.concatenate(c) for c in zip(*found)]
            key = key_of(grown, n)
            if (n + 1) ** (k + 1) < 1 << 62:
                key, sets = np.unique(key), []
                for _ in range(k + 1):
                    key, c = np.divmod(key, n + 1)
                    sets.insert(0, c - 1)
            else:
                at = np.unique(key, return_index=True)[1]
                sets = [c[at] for c in grown]
        return np.stack(sets, axis=1)

    def edges_of(self, sets: np.ndarray) -> np.ndarray:
        """The edge, or -1, between each two places of each piece."""
        return np.stack([self.edge_between(sets[:, i], sets[:, j]) for i, j in combinations(range(sets.shape[1]), 2)], axis=1) if sets.shape[1] > 1 else np.empty((len(sets), 0), np.int64)

    def of_edges(self, values: np.ndarray, edges: np.ndarray, none: int = -1) -> np.ndarray:
        return np.append(values, none)[edges]

    def named(self, sets: np.ndarray, edges: np.ndarray, name: Callable[[str], str]) -> tuple[np.ndarray, list[str]]:
        """Each piece's pattern as a place in a list of names; ``name`` is called once a spelling."""
        p = sets.shape[1]
        labels, links = self.label[sets], self.of_edges(self.elabel, edges)
        key = key_of([*labels.T, *links.T], max(len(self.names), len(self.links)))
        _, at, spelling = np.unique(key, return_index=True, return_inverse=True)
        places: dict[str, int] = {}
        which = np.empty(len(at), np.int64)
        for k, i in enumerate(at):
            own = [(x, y, self.links[e]) for (x, y), e in zip(combinations(range(p), 2), links[i]) if e >= 0]
            which[k] = places.setdefault(name(raw_code([self.names[v] for v in labels[i]], own)), len(places))
        return which[spelling], list(places)

    def types(self, number: dict[tuple[str, str, str], int], other: int | None = None) -> np.ndarray:
        """Each edge's type as numbered: its end labels in order and its own. Without ``other``, the number of all further types, these are an error."""
        x, y = self.label[self.a], self.label[self.b]
        key = key_of([x, self.elabel, y], max(len(self.names), len(self.links)))
        _, at, kind = np.unique(key, return_index=True, return_inverse=True)
        ends = [sorted((self.names[x[i]], self.names[y[i]])) for i in at]
        kinds = [(la, self.links[self.elabel[i]], lb) for i, (la, lb) in zip(at, ends)]
        found = [number[k] if other is None else number.get(k, other) for k in kinds]
        return np.array(found, np.int64)[kind] if len(at) else np.empty(0, np.int64)

    def scores(self, edges: np.ndarray, number: dict, scores) -> tuple[np.ndarray, np.ndarray]:
        """Numerator and denominator of each piece's score; a set of types is scored once."""
        if scores.name == "uniform":
            return np.ones(len(edges), np.int64), np.ones(len(edges), np.int64)
        kinds = np.sort(self.of_edges(self.types(number), edges), axis=1)
        _, at, kind = np.unique(key_of(list(kinds.T), len(number)), return_index=True, return_inverse=True)
        found = np.array([scores.of([int(t) for t in kinds[i] if t >= 0]) for i in at], np.int64).reshape(-1, 2)
        return found[kind, 0], found[kind, 1]

    def cores(self, sets: np.ndarray) -> Cores:
        n, p = sets.shape
        keys = [key_of([self.graph[sets[:, 0]], *(sets[:, i] for i in range(p) if i != j)], len(self.vids)) for j in range(p)] if n else []
        if p > 1 and n and (len(self.vids) + 1) ** p >= 1 << 62:  # numbers of their own for each column: compare all at once
            rows = np.stack([np.delete(sets, j, axis=1) for j in range(p)], axis=1).reshape(n * p, p - 1)
            keys = key_of([self.graph[rows[:, 0]], *rows.T], len(self.vids)).reshape(n, p).T
        flat = np.stack(list(keys), axis=1).ravel() if n else np.empty(0, np.int64)
        _, core = np.unique(flat, return_inverse=True)
        return Cores(sets, core.astype(np.int64))


    def grown(self, sets: list[np.ndarray], live: np.ndarray, max_size: int | None) -> list[np.ndarray]:
        """Connected edge sets, a column for each rising edge, with one live edge more that touches them, once each; ``max_size`` caps their vertices."""
        k, found = len(sets), []
        ends = np.sort(np.stack([self.a[c] for c in sets] + [self.b[c] for c in sets], axis=1), axis=1)
        fresh_end = np.concatenate([np.ones((len(ends), 1), bool), ends[:, 1:] != ends[:, :-1]], axis=1)
        n_ends = fresh_end.sum(axis=1)
        full = np.full(len(ends), False) if max_size is None or not self.simple else n_ends >= max_size

        def add(run, new):
            columns, fresh = [], np.ones(len(new), bool)
            for c in sets:
                own = c[run]
                fresh &= own != new
                columns.append(np.minimum(own, new))
                new = np.maximum(own, new)
            found.append([c[fresh] for c in (*columns, new)])

        for i, j in combinations(range(2 * k), 2) if full.any() else ():  # no vertex more: only edges between those that are there
            run = np.flatnonzero(full & fresh_end[:, i] & fresh_end[:, j])
            new = self.edge_between(ends[run, i], ends[run, j])
            fits = (new >= 0) & live[new]
            add(run[fits], new[fits])
        for at in range(2 * k):
            rows = np.flatnonzero(fresh_end[:, at] & ~full)
            v = ends[rows, at]
            run, place = spread(self.first[v + 1] - self.first[v])
            slot = self.first[v][run] + place
            run, new, far = rows[run], self.edge_at[slot], self.other[slot]
            fits = live[new]
            if max_size is not None and not self.simple:
                inside = np.zeros(len(new), bool)
                for i in range(2 * k):
                    inside |= ends[run, i] == far
                fits = fits & (inside | (n_ends[run] < max_size))
            add(run[fits], new[fits])
        grown = [np.concatenate(c) for c in zip(*found)]
        at = np.unique(key_of(grown, max(1, len(self.a))), return_index=True)[1]
        return [c[at] for c in grown]

    def named_edges(self, sets: list[np.ndarray], name: Callable[[str], str]) -> tuple[np.ndarray, list[str]]:
        """Each edge set's pattern as a place in a list of names."""
        k = len(sets)
        x, y = np.stack([self.a[c] for c in sets], axis=1), np.stack([self.b[c] for c in sets], axis=1)
        ends = np.sort(np.concatenate([x, y], axis=1), axis=1)
        fresh = np.concatenate([np.ones((len(ends), 1), bool), ends[:, 1:] != ends[:, :-1]], axis=1)
        labels = np.full((len(ends), k + 1), -1, np.int64)
        rows, at = np.nonzero(fresh)
        labels[rows, (np.cumsum(fresh, axis=1) - 1)[rows, at]] = self.label[ends[rows, at]]
        rank = lambda v: sum((fresh[:, i] & (ends[:, i] < v)).astype(np.int64) for i in range(2 * k))
        columns = [c for i in range(k) for c in (rank(x[:, i]), rank(y[:, i]), self.elabel[sets[i]])]
        _, first, spelling = np.unique(key_of([*labels.T, *columns], max(len(self.names), len(self.links), 2 * k)), return_index=True, return_inverse=True)
        places: dict[str, int] = {}
        which = np.empty(len(first), np.int64)
        for j, i in enumerate(first):
            own = [(int(columns[3 * e][i]), int(columns[3 * e + 1][i]), self.links[columns[3 * e + 2][i]]) for e in range(k)]
            which[j] = places.setdefault(name(raw_code([self.names[v] for v in labels[i] if v >= 0], own)), len(places))
        return which[spelling], list(places)


@dataclass
class Cores:
    """What is left of each piece without each of its vertices: pieces with a core in common are neighbours, over one core at most."""

    sets: np.ndarray
    core: np.ndarray

    def __post_init__(self) -> None:
        self.p = self.sets.shape[1]
        self.size = np.bincount(self.core) if len(self.core) else np.empty(0, np.int64)
        self.first = np.concatenate([[0], np.cumsum(self.size)]).astype(np.int64)
        self.members = np.argsort(self.core, kind="stable")  # entries: piece * p + place

    def degrees(self) -> np.ndarray:
        return (self.size[self.core] - 1).reshape(-1, self.p).sum(axis=1)

    def pairs(self) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Neighbours ``x, y`` by ``x``, all of an ``x`` together."""
        per = self.size[self.core].reshape(-1, self.p).sum(axis=1)
        for lo, hi in slices(per, PAIRS):
            core = self.core[lo * self.p : hi * self.p]
            run, place = spread(self.size[core])
            x, y = lo + run // self.p, self.members[self.first[core[run]] + place] // self.p
            other = x != y
            yield x[other], y[other]

    def pairs_by_core(self) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Neighbours ``x, y``, both directions of a pair together."""
        for lo, hi in slices(self.size * self.size, PAIRS):
            size = self.size[lo:hi]
            entry = np.repeat(np.arange(lo, hi), size)  # the core of each member
            run, place = spread(self.size[entry])
            x = self.members[self.first[lo] : self.first[hi]][run] // self.p
            y = self.members[self.first[entry[run]] + place] // self.p
            other = x != y
            yield x[other], y[other]


def slices(weights: np.ndarray, most: int) -> Iterator[tuple[int, int]]:
    """Runs of consecutive items of about ``most`` weight each."""
    if not len(weights):
        return
    part = (np.cumsum(weights) - weights) // most
    at = np.flatnonzero(np.diff(part)) + 1
    yield from zip([0, *at.tolist()], [*at.tolist(), len(weights)])


def chunks(batch: pa.RecordBatch, p: int) -> Iterator[Chunk]:
    """The packed graphs of a batch in chunks of about ``PIECES`` pieces of size ``p``."""
    column = {name: batch.column(i) for i, name in enumerate(batch.schema.names)}
    sizes = lambda c: np.asarray(column[c].value_lengths().fill_null(0)).astype(np.int64)
    number = lambda c: column[c].flatten().to_numpy(zero_copy_only=False).astype(np.int64)

    def coded(c: str) -> tuple[np.ndarray, list[str]]:
        d = column[c].flatten().dictionary_encode()
        names = d.dictionary.to_pylist()
        order = sorted(range(len(names)), key=names.__getitem__)
        rank = np.empty(len(names), np.int64)
        rank[order] = np.arange(len(names))
        return rank[d.indices.to_numpy(zero_copy_only=False)], [names[i] for i in order]

    gids, n_v, n_e = column["gid"].to_numpy(zero_copy_only=False), sizes("vids"), sizes("ea")
    v0, e0 = np.concatenate([[0], np.cumsum(n_v)]), np.concatenate([[0], np.cumsum(n_e)])
    vids, ea, eb = number("vids"), number("ea"), number("eb")
    (label, names), (elabel, links) = coded("vlab"), coded("elab")
    base = np.repeat(v0[:-1], n_e)
    ea, eb = ea + base, eb + base
    ea, eb = np.minimum(ea, eb), np.maximum(ea, eb)
    degree = np.bincount(np.concatenate([ea, eb]), minlength=len(vids)).astype(np.float64)
    cost = np.bincount(np.repeat(np.arange(len(gids)), n_v), weights=degree ** max(1, p - 1), minlength=len(gids)) / max(1, p) + 1
    for lo, hi in slices(cost.astype(np.int64), PIECES):
        v, e = slice(v0[lo], v0[hi]), slice(e0[lo], e0[hi])
        yield Chunk(gids[lo:hi], np.repeat(np.arange(hi - lo), n_v[lo:hi]), vids[v], label[v], names, ea[e] - v0[lo], eb[e] - v0[lo], elabel[e], links)


def over_pieces(packed: DataFrame, p: int, make: Callable[[Chunk], Iterator[dict]], schema: str) -> DataFrame:
    """``make`` run over the packed graphs; it gives columns by name."""
    names = [c.split()[0] for c in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for chunk in chunks(batch, p):
                for out in make(chunk):
                    arrays = [c if isinstance(c, pa.Array) else pa.array(c) for c in (out[n] for n in names)]
                    if len(arrays[0]):
                        yield pa.RecordBatch.from_arrays(arrays, names=names)

    return packed.select("gid", "vids", "vlab", "ea", "eb", "elab").mapInArrow(run, schema)
