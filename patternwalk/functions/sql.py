"""Names for SQL: views of a database, scalar functions and table functions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import BooleanType, DoubleType, StringType

from patternwalk.functions.accuracy import tau_b
from patternwalk.model import GraphDB, pack
from patternwalk.operators.canon import decode_code, dfs_code, parse_raw, perm_code, same_pattern, to_dot
from patternwalk.operators.kernel import Graph, bits, connected


@pandas_udf(StringType())
def _dfs(raw: pd.Series) -> pd.Series:
    return raw.map(dfs_code)


@pandas_udf(StringType())
def _perm(raw: pd.Series) -> pd.Series:
    return raw.map(lambda r: perm_code(*parse_raw(r)))


@pandas_udf(StringType())
def _dot(code: pd.Series) -> pd.Series:
    return code.map(to_dot)


@pandas_udf(BooleanType())
def _same(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([same_pattern(x, y) for x, y in zip(a, b)])


@pandas_udf(BooleanType())
def _connected(raw: pd.Series) -> pd.Series:
    def check(r: str) -> bool:
        labels, edges = parse_raw(r)
        return connected((1 << len(labels)) - 1, [(a, b) for a, b, _ in edges])

    return raw.map(check)


@pandas_udf(DoubleType())
def _density(raw: pd.Series) -> pd.Series:
    def share(r: str) -> float:
        labels, edges = parse_raw(r)
        return 2 * len(edges) / (len(labels) * (len(labels) - 1)) if len(labels) > 1 else 0.0

    return raw.map(share)


@pandas_udf(DoubleType())
def _tau(x: pd.Series, y: pd.Series) -> float:
    return float(tau_b(x.to_numpy(float), y.to_numpy(float)))


def edge_type_key(a: Column, x: Column, b: Column) -> Column:
    """The name of an edge type, the same from both ends."""
    return F.concat_ws("|", F.least(a, b), x, F.greatest(a, b))


@udtf(returnType="src int, dst int, la string, elabel string, lb string")
class DecodeCode:
    def eval(self, code: str):
        labels, edges = decode_code(code)
        for a, b, x in edges:
            yield a, b, labels[a], x, labels[b]


@udtf(returnType="gid bigint, vs array<bigint>, raw string")
class EnumeratePieces:
    """``enumerate_pieces(TABLE(packed), p)``: the pieces of each packed row."""

    def eval(self, row, p: int):
        g = Graph(row["vids"], row["vlab"], row["ea"], row["eb"], row["elab"], row["etyp"])
        for s in g.enumerate(p):
            yield row["gid"], [g.vids[v] for v in bits(s)], g.raw(s)


@udtf(returnType="gid bigint, u bigint, w bigint")
class ExpandNeighbours:
    """``expand_neighbours(TABLE(packed with a column vs))``: the replacements of each vertex of a piece."""

    def eval(self, row):
        g = Graph(row["vids"], row["vlab"], row["ea"], row["eb"], row["elab"], row["etyp"])
        place = {v: i for i, v in enumerate(g.vids)}
        for u, mask in g.boxes(sum(1 << place[v] for v in row["vs"])):
            for w in bits(mask):
                yield row["gid"], g.vids[u], g.vids[w]


def register(spark: SparkSession, db: GraphDB | None = None, prefix: str = "gdb") -> None:
    """Register the functions, and the views ``{prefix}_vertices``, ``_edges`` and ``_packed`` of a database."""
    for name, f in (("dfs_code", _dfs), ("perm_code", _perm), ("code_to_dot", _dot), ("same_pattern", _same), ("is_connected", _connected), ("piece_density", _density), ("tau_b", _tau)):
        spark.udf.register(name, f)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION edge_type_key(a STRING, x STRING, b STRING) RETURNS STRING RETURN concat_ws('|', least(a, b), x, greatest(a, b))")
    spark.udtf.register("decode_code", DecodeCode)
    spark.udtf.register("enumerate_pieces", EnumeratePieces)
    spark.udtf.register("expand_neighbours", ExpandNeighbours)
    if db is not None:
        db.vertices.createOrReplaceTempView(f"{prefix}_vertices")
        db.edges.createOrReplaceTempView(f"{prefix}_edges")
        pack(db).createOrReplaceTempView(f"{prefix}_packed")
