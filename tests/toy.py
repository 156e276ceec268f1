"""The hand-made graphs of FIXTURES.md."""

from patternwalk.model import EDGES, VERTICES, GraphDB
from patternwalk.operators.kernel import Graph

LABELS = {1: "ABACBABC", 2: "ABABC", 3: "CABA"}
LINKS = {
    1: [(0, 1, "x"), (0, 2, "y"), (1, 2, "x"), (2, 3, "x"), (3, 4, "y"), (4, 5, "x"), (2, 5, "y"), (5, 6, "x"), (6, 7, "y"), (0, 7, "x")],
    2: [(0, 1, "x"), (1, 2, "x"), (0, 2, "y"), (2, 3, "x"), (3, 4, "y")],
    3: [(0, 1, "x"), (1, 2, "x"), (1, 3, "y")],
}
TYPES = {("A", "x", "B"): 0, ("A", "x", "C"): 1, ("A", "y", "A"): 2, ("B", "y", "C"): 3}


def graph(gid: int) -> Graph:
    lab, es = LABELS[gid], LINKS[gid]
    return Graph(range(len(lab)), list(lab), [a for a, _, _ in es], [b for _, b, _ in es], [x for _, _, x in es], [TYPES[min(lab[a], lab[b]), x, max(lab[a], lab[b])] for a, b, x in es])


def database(spark) -> GraphDB:
    v = [(g, i, c) for g, lab in LABELS.items() for i, c in enumerate(lab)]
    e = [(g, min(a, b), max(a, b), x) for g, es in LINKS.items() for a, b, x in es]
    return GraphDB(spark.createDataFrame(v, VERTICES), spark.createDataFrame(e, EDGES))


def mask(vertices) -> int:
    return sum(1 << v for v in vertices)
