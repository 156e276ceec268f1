"""Canonical strings: one name for all isomorphic forms of a labelled piece.

A *raw* code lists a piece's labels and edges in vertex order; it differs between
forms but is cheap. The minimum depth-first code names the class. Codes are computed
once per distinct raw code.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import lru_cache
from itertools import combinations, permutations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StringType

#: Separators of raw codes; labels must not hold them.
_PART, _ITEM, _FIELD = "\x1d", "\x1e", "\x1f"
Edge = tuple[int, int, str]


def raw_code(labels: list[str], edges: list[Edge]) -> str:
    return _ITEM.join(labels) + _PART + _ITEM.join(f"{a}{_FIELD}{b}{_FIELD}{x}" for a, b, x in sorted(edges))


def parse_raw(raw: str) -> tuple[list[str], list[Edge]]:
    v, e = raw.split(_PART)
    return v.split(_ITEM), [(int(a), int(b), x) for a, b, x in (s.split(_FIELD) for s in e.split(_ITEM) if s)]


def min_dfs(labels: list[str], edges: list[Edge]) -> list[tuple[int, int, str, str, str]]:
    """The least depth-first edge sequence.

    The order of sequences is decided by their first difference, so the least one grows
    edge by edge: of all partial traversals that spell the least prefix, those whose
    next edge is least go on.
    """
    near: list[list[tuple[int, str]]] = [[] for _ in labels]
    for a, b, x in edges:
        near[a].append((b, x))
        near[b].append((a, x))
    if not edges:
        return []
    start = min((labels[a], x, labels[b]) for a in range(len(labels)) for b, x in near[a])
    code = [(0, 1, *start)]
    # a traversal: vertices in order of discovery, the places on the rightmost path, edges used
    live = [((a, b), (0, 1), frozenset([(min(a, b), max(a, b))])) for a in range(len(labels)) for b, x in near[a] if (labels[a], x, labels[b]) == start]
    while len(code) < len(edges):
        best, follow = None, []
        for seen, path, used in live:
            tip = seen[path[-1]]
            place = {v: i for i, v in enumerate(seen)}
            back = [(i, x) for i in path[:-1] for v, x in near[tip] if v == seen[i] and (min(tip, v), max(tip, v)) not in used]
            if back:
                i, x = min(back)
                options = [((0, i, x, ""), seen, path, used | {(min(tip, seen[i]), max(tip, seen[i]))})]
            else:
                options = []
                for depth in range(len(path) - 1, -1, -1):
                    v = seen[path[depth]]
                    grown = [((1, -path[depth], x, labels[w]), (*seen, w), (*path[: depth + 1], len(seen)), used | {(min(v, w), max(v, w))}) for w, x in near[v] if w not in place]
                    if grown:
                        options = grown
                        break
            for option in options:
                if best is None or option[0] < best:
                    best, follow = option[0], [option]
                elif option[0] == best:
                    follow.append(option)
        kind, at, x, label = best
        seen, path = follow[0][1], follow[0][2]
        if kind == 0:
            code.append((path[-1], at, labels[seen[path[-1]]], x, labels[seen[at]]))
        else:
            code.append((-at, len(seen) - 1, labels[seen[-at]], x, label))
        live = list({(s, p, u) for _, s, p, u in follow})
    return code


def code_text(labels: list[str], edges: list[Edge]) -> str:
    if len(labels) == 1:
        return labels[0]
    return ";".join(f"{i},{j},{a},{x},{b}" for i, j, a, x, b in min_dfs(labels, edges))


@lru_cache(maxsize=1 << 16)
def dfs_code(raw: str) -> str:
    """The canonical string of a raw code; remembered per worker."""
    return code_text(*parse_raw(raw))


def perm_code(labels: list[str], edges: list[Edge]) -> str:
    """The least spelling over all vertex orders: the check of :func:`min_dfs` for small pieces, also available in SQL."""
    at = {(a, b): x for a, b, x in edges} | {(b, a): x for a, b, x in edges}
    n = len(labels)
    return min("|".join([*(labels[i] for i in o), *(at.get((o[i], o[j]), "-") for i, j in combinations(range(n), 2))]) for o in permutations(range(n)))


@lru_cache(maxsize=1 << 16)
def perm_name(raw: str) -> str:
    """The least spelling of a raw code; remembered per worker."""
    return perm_code(*parse_raw(raw))


#: Names of patterns from raw codes. Any canonical string will do; the least spelling is for pieces of a few vertices.
NAMINGS: dict[str, Callable[[str], str]] = {"dfs": dfs_code, "permutation": perm_name}


def perm_code_sql(p: int, label: Callable[[int], str], edge: Callable[[int, int], str]) -> str:
    """The same as a SQL expression: ``label(i)`` and ``edge(i, j)`` give expressions, the latter ``'-'`` where there is none."""
    spellings = []
    for o in permutations(range(p)):
        parts = [label(i) for i in o] + [edge(*sorted((o[i], o[j]))) for i, j in combinations(range(p), 2)]
        spellings.append(f"concat_ws('|', {', '.join(parts)})")
    return f"least({', '.join(spellings)})"


def wl_key(labels: list[str], edges: list[Edge], rounds: int = 3) -> str:
    """Colour refinement: equal for isomorphic pieces, not always different for others."""
    colour = list(labels)
    for _ in range(rounds):
        colour = [f"{colour[v]}({','.join(sorted(f'{x}{colour[b if a == v else a]}' for a, b, x in edges if v in (a, b)))})" for v in range(len(labels))]
        names = {c: str(i) for i, c in enumerate(sorted(set(colour)))}
        if len(names) == len(labels):
            break
    return ";".join(sorted(colour))


def edge_list_code(labels: list[str], edges: list[Edge]) -> str:
    """Canonical already where all labels differ."""
    if len(set(labels)) != len(labels):
        raise ValueError("labels repeat")
    return ";".join(sorted(f"{min(labels[a], labels[b])},{x},{max(labels[a], labels[b])}" for a, b, x in edges))


def decode_code(code: str) -> tuple[list[str], list[Edge]]:
    """Labels and edges of a canonical string."""
    if ";" not in code and code.count(",") < 4:
        return [code], []
    labels: dict[int, str] = {}
    edges = []
    for part in code.split(";"):
        i, j, a, x, b = part.split(",")
        labels[int(i)], labels[int(j)] = a, b
        edges.append((min(int(i), int(j)), max(int(i), int(j)), x))
    return [labels[i] for i in range(len(labels))], edges


def to_dot(code: str) -> str:
    labels, edges = decode_code(code)
    return "graph {" + " ".join([*(f'{i} [label="{v}"];' for i, v in enumerate(labels)), *(f'{a} -- {b} [label="{x}"];' for a, b, x in edges)]) + "}"


def same_pattern(a: str, b: str) -> bool:
    return a == b


@F.pandas_udf(StringType())
def dfs_code_udf(raw: pd.Series) -> pd.Series:
    return raw.map(dfs_code)


@F.pandas_udf(StringType())
def perm_name_udf(raw: pd.Series) -> pd.Series:
    return raw.map(perm_name)


@F.pandas_udf(StringType())
def respelled(code: pd.Series) -> pd.Series:
    """The least spelling of a depth-first code."""
    return code.map(lambda c: perm_code(*decode_code(c)))


def with_code(df: DataFrame, raw_col: str = "raw", method: str = "join", naming: str = "dfs") -> DataFrame:
    """Add ``code``. ``join``: code each distinct raw string once and join back; ``inline``: per row with a worker's memory, no shuffle, so that a common piece's samples need not meet."""
    name = {"dfs": dfs_code_udf, "permutation": perm_name_udf}[naming]
    if method == "inline":
        return df.withColumn("code", name(raw_col))
    codes = df.select(F.col(raw_col).alias("_raw")).distinct().withColumn("code", name("_raw"))
    return df.join(codes, F.col(raw_col) == F.col("_raw")).drop("_raw")
