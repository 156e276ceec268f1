"""SQL twins of the registered queries, for an engine of its own kind: each builds its graphs and measures from the tables."""

from __future__ import annotations

from itertools import combinations

from patternwalk.operators.canon import perm_code_sql

_LABELS = {
    "coarse": "event_type",
    "fine": "event_type || ':' || CASE WHEN value < 15 THEN '0' WHEN value < 35 THEN '1' WHEN value < 70 THEN '2' ELSE '3' END",
    "skewed": "CASE WHEN value < 70 THEN substr(event_type, 1, 1) ELSE event_type || least(floor(value / 35), 6)::INT::VARCHAR END",
}


def proximity(alphabet: str = "coarse", where: str = "true") -> str:
    """CTEs ``v`` and ``e`` of the proximity graphs."""
    return f"""
ev AS (SELECT user_id AS gid, event_id AS vid, epoch_us(ts) AS t, {_LABELS[alphabet]} AS vlabel,
         row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS n FROM events WHERE {where}),
v AS (SELECT gid, vid, vlabel FROM ev),
e AS (SELECT a.gid, least(a.vid, b.vid) AS src, greatest(a.vid, b.vid) AS dst,
        CASE WHEN b.t - a.t <= 77400000000 THEN '1' WHEN b.t - a.t <= 154800000000 THEN '2' ELSE '3' END AS elabel
      FROM ev a JOIN ev b ON a.gid = b.gid AND b.n > a.n AND (b.t - a.t <= 154800000000 OR b.n = a.n + 1))"""


STAR = """
li AS (SELECT l_orderkey AS gid, l_partkey, l_suppkey, 'L:' || l_returnflag || l_linestatus AS flags,
   row_number() OVER (PARTITION BY l_orderkey ORDER BY l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate) AS n FROM lineitem),
o AS (SELECT o_orderkey AS gid, o_custkey, o_orderpriority FROM orders WHERE o_orderkey IN (SELECT gid FROM li)),
w AS (SELECT * FROM li WHERE gid IN (SELECT gid FROM o)),
v AS (SELECT gid, 0::BIGINT AS vid, 'O:' || o_orderpriority AS vlabel FROM o
  UNION ALL SELECT gid, 1, 'C:' || c_mktsegment FROM o JOIN customer ON c_custkey = o_custkey
  UNION ALL SELECT gid, n + 1, flags FROM w
  UNION ALL SELECT DISTINCT gid, l_partkey + 1000000, 'P:' || p_type FROM w JOIN part ON p_partkey = l_partkey
  UNION ALL SELECT DISTINCT gid, l_suppkey + 1000000000000, 'S:' || n_regionkey::VARCHAR FROM w JOIN supplier ON s_suppkey = l_suppkey JOIN nation ON n_nationkey = s_nationkey),
e AS (SELECT gid, 0::BIGINT AS src, 1::BIGINT AS dst, 'oc' AS elabel FROM o UNION ALL SELECT gid, 0, n + 1, 'ol' FROM w
  UNION ALL SELECT gid, n + 1, l_partkey + 1000000, 'lp' FROM w UNION ALL SELECT gid, n + 1, l_suppkey + 1000000000000, 'ls' FROM w)"""

DIALOGUE = """
v AS (SELECT conv_id AS gid, turn AS vid, role AS vlabel FROM conversations),
e AS (SELECT * FROM (SELECT conv_id AS gid, turn AS src, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS dst, 'next' AS elabel FROM conversations) WHERE dst IS NOT NULL)"""


def tokens(source: str, key: str, where: str = "true") -> str:
    return rf"""
tk AS (SELECT gid, i, w FROM (SELECT gid, unnest(range(1, len(ws) + 1)) AS i, unnest(ws) AS w FROM (
   SELECT {key} AS gid, list_filter(string_split(lower(text), ' '), lambda x: regexp_full_match(x, '[a-z]{{2,}}')) AS ws FROM {source} WHERE {where}))),
nu AS (SELECT gid, i, w, dense_rank() OVER (PARTITION BY gid ORDER BY w) - 1 AS vid FROM tk),
v AS (SELECT DISTINCT gid, vid, w AS vlabel FROM nu),
e AS (SELECT gid, least(vid, nx) AS src, greatest(vid, nx) AS dst, min('n') AS elabel FROM (SELECT gid, vid, lead(vid) OVER (PARTITION BY gid ORDER BY i) AS nx FROM nu) WHERE nx IS NOT NULL AND nx <> vid GROUP BY ALL)"""


VECTOR = """
ve AS (SELECT vec_id % (SELECT greatest(1, count(*) // 50) FROM embeddings) AS gid, vec_id AS vid, label::VARCHAR AS vlabel, embedding::DOUBLE[] AS x FROM embeddings),
ee AS (SELECT a.gid, a.vid AS src, b.vid AS dst, round(list_dot_product(a.x, b.x) / (sqrt(list_dot_product(a.x, a.x)) * sqrt(list_dot_product(b.x, b.x))), 6) AS c FROM ve a JOIN ve b ON a.gid = b.gid AND a.vid < b.vid),
e0 AS (SELECT gid, src, dst, CASE WHEN c >= 0.25 THEN '1' ELSE '2' END AS elabel FROM ee WHERE c >= 0.15),
v0 AS (SELECT gid, vid, vlabel FROM ve)"""

COPURCHASE = """
seg AS (SELECT c_mktsegment, rank() OVER (ORDER BY c_mktsegment) - 1 AS k FROM (SELECT DISTINCT c_mktsegment FROM customer)),
oo AS (SELECT o_orderkey, o_orderpriority, c_nationkey * 100 + k AS gid FROM orders JOIN customer ON c_custkey = o_custkey JOIN seg USING (c_mktsegment)),
pp AS (SELECT DISTINCT l_orderkey AS o_orderkey, l_partkey AS part FROM lineitem),
e0 AS (SELECT gid, a.part AS src, b.part AS dst, min(o_orderpriority) AS elabel FROM pp a JOIN pp b ON a.o_orderkey = b.o_orderkey AND a.part < b.part JOIN oo ON oo.o_orderkey = a.o_orderkey GROUP BY ALL),
v0 AS (SELECT DISTINCT gid, part AS vid, p_brand AS vlabel FROM pp JOIN oo USING (o_orderkey) JOIN part ON p_partkey = part)"""

#: Largest components of ``v0`` and ``e0``: labels spread along edges until each vertex has its component's least.
LARGEST = """
sy AS (SELECT gid, src AS a, dst AS b FROM e0 UNION ALL SELECT gid, dst, src FROM e0),
reach AS (SELECT gid, vid, vid AS far FROM v0 UNION SELECT r.gid, r.vid, s.b FROM reach r JOIN sy s ON s.gid = r.gid AND s.a = r.far),
comp AS (SELECT gid, vid, min(far) AS comp FROM reach GROUP BY ALL),
sized AS (SELECT gid, comp, count(*) AS n FROM comp GROUP BY ALL),
best AS (SELECT gid, arg_max(comp, n * 1000000000 - comp) AS comp FROM sized GROUP BY gid),
keep AS (SELECT gid, vid FROM comp JOIN best USING (gid, comp)),
v AS (SELECT * FROM v0 SEMI JOIN keep USING (gid, vid)),
e AS (SELECT e0.* FROM e0 JOIN keep k1 ON k1.gid = e0.gid AND k1.vid = src JOIN keep k2 ON k2.gid = e0.gid AND k2.vid = dst)"""

STATS = """
SELECT (SELECT count(DISTINCT gid) FROM v) AS n_graphs, (SELECT count(*) FROM v) AS n_vertices, (SELECT count(*) FROM e)::BIGINT AS n_edges,
       (SELECT max(n) FROM (SELECT count(*) AS n FROM v GROUP BY gid)) AS max_vertices, (SELECT count(DISTINCT vlabel) FROM v) AS n_vlabels, (SELECT count(DISTINCT elabel) FROM e) AS n_elabels"""

TYPES = """
te AS (SELECT e.gid, src, dst, elabel AS el, least(a.vlabel, b.vlabel) AS la, greatest(a.vlabel, b.vlabel) AS lb FROM e JOIN v a ON a.gid = e.gid AND a.vid = src JOIN v b ON b.gid = e.gid AND b.vid = dst),
ty AS (SELECT row_number() OVER (ORDER BY la, el, lb) - 1 AS etype, la, el, lb, count(DISTINCT gid) AS support FROM te GROUP BY la, el, lb)"""


def pieces(p: int) -> str:
    """CTEs up to ``s{p}(gid, vs)``."""
    out = ["sym AS (SELECT gid, src AS a, dst AS b FROM e UNION ALL SELECT gid, dst, src FROM e)", "s2 AS (SELECT gid, [src, dst] AS vs FROM e)"]
    for k in range(3, p + 1):
        out.append(f"s{k} AS (SELECT DISTINCT x.gid, list_sort(list_append(vs, b)) AS vs FROM (SELECT gid, vs, unnest(vs) AS a FROM s{k - 1}) x JOIN sym ON sym.gid = x.gid AND sym.a = x.a WHERE NOT list_contains(vs, b))")
    return ",\n".join(out)


def codes(p: int) -> str:
    """CTE ``cd(gid, vs, code)``."""
    joins = " ".join(f"JOIN v v{i} ON v{i}.gid = s.gid AND v{i}.vid = s.vs[{i + 1}]" for i in range(p))
    joins += " " + " ".join(f"LEFT JOIN e e{i}{j} ON e{i}{j}.gid = s.gid AND e{i}{j}.src = s.vs[{i + 1}] AND e{i}{j}.dst = s.vs[{j + 1}]" for i, j in combinations(range(p), 2))
    code = perm_code_sql(p, lambda i: f"v{i}.vlabel", lambda i, j: f"coalesce(e{i}{j}.elabel, '-')")
    return f"cd AS (SELECT s.gid, s.vs, {code} AS code FROM s{p} s {joins})"


SUPPORT = "su AS (SELECT code, count(DISTINCT gid) AS support, count(*) AS embeddings FROM cd GROUP BY code)"


def scores(p: int) -> str:
    """CTEs ``s1s(gid, vs, s1_num, s1_den, s1)`` and ``s2s(gid, vs, s2)``."""
    return f"""
pe AS (SELECT s.gid, s.vs, t.etype, t.support FROM s{p} s JOIN te ON te.gid = s.gid AND list_contains(s.vs, te.src) AND list_contains(s.vs, te.dst) JOIN ty t USING (la, el, lb)),
s1s AS (SELECT gid, vs, sum(support)::BIGINT AS s1_num, count(*) AS s1_den, sum(support)::BIGINT / count(*) AS s1 FROM pe GROUP BY gid, vs),
tg AS (SELECT DISTINCT etype, gid AS g FROM te JOIN ty USING (la, el, lb)),
ks AS (SELECT gid, vs, list_sort(list(DISTINCT etype)) AS kinds FROM pe GROUP BY gid, vs),
kc AS (SELECT kinds, count(*) AS s2 FROM (SELECT kinds, g FROM (SELECT kinds, unnest(kinds) AS etype FROM (SELECT DISTINCT kinds FROM ks)) JOIN tg USING (etype) GROUP BY kinds, g HAVING count(*) = len(kinds)) GROUP BY kinds),
s2s AS (SELECT gid, vs, s2 FROM ks JOIN kc USING (kinds))"""


def law(p: int, score: str) -> str:
    """CTEs ``nb`` (neighbour pairs), ``dg`` (degrees) and ``tr`` (transitions)."""
    value = {"s2": "SELECT gid, vs, s2 AS num, 1 AS den FROM s2s", "s1": "SELECT gid, vs, s1_num AS num, s1_den AS den FROM s1s", "uniform": f"SELECT gid, vs, 1 AS num, 1 AS den FROM s{p}"}[score]
    return f"""
co AS (SELECT gid, vs, array_to_string(list_filter(vs, lambda y: y <> u), ',') AS core FROM (SELECT gid, vs, unnest(vs) AS u FROM s{p})),
nb AS (SELECT a.gid, a.vs, b.vs AS ws FROM co a JOIN co b ON a.gid = b.gid AND a.core = b.core AND a.vs <> b.vs),
dg AS (SELECT gid, vs, count(*) AS d FROM nb GROUP BY gid, vs),
sc AS ({value}),
tr AS (SELECT n.gid, n.vs, n.ws, x.d, sx.num, sx.den, y.d AS d_y, sy.num AS num_y, sy.den AS den_y,
   least(1.0::DOUBLE, (x.d * sy.num * sx.den)::DOUBLE / (y.d * sx.num * sy.den)::DOUBLE) AS alpha
 FROM nb n JOIN dg x ON x.gid = n.gid AND x.vs = n.vs JOIN dg y ON y.gid = n.gid AND y.vs = n.ws JOIN sc sx ON sx.gid = n.gid AND sx.vs = n.vs JOIN sc sy ON sy.gid = n.gid AND sy.vs = n.ws)"""


def uniform(*key: str) -> str:
    return f"(('0x' || substr(md5(concat_ws('|', {', '.join(key)})), 1, 13))::BIGINT / 4503599627370496.0)"


#: Random connected graphs over the users' events: see :func:`patternwalk.sources.builders.synthetic_on`.
SYNTHETIC = f"""
n AS (SELECT user_id AS gid, event_id, row_number() OVER (PARTITION BY user_id ORDER BY event_id) - 1 AS vid, count(*) OVER (PARTITION BY user_id) AS size FROM events),
v AS (SELECT gid, vid, 'v' || floor({uniform("'7'", "'v'", "event_id::VARCHAR")} * 20)::BIGINT AS vlabel FROM n),
r AS (SELECT gid, floor({uniform("'7'", "'t'", "event_id::VARCHAR")} * vid)::BIGINT AS src, vid AS dst FROM n WHERE vid > 0
  UNION ALL SELECT gid, vid, floor({uniform("'7'", "'x'", "event_id::VARCHAR")} * size)::BIGINT FROM n),
e AS (SELECT DISTINCT gid, least(src, dst) AS src, greatest(src, dst) AS dst, 'e' || floor({uniform("'7'", "'e'", "gid::VARCHAR", "least(src, dst)::VARCHAR", "greatest(src, dst)::VARCHAR")} * 5)::BIGINT AS elabel FROM r WHERE src <> dst)"""


def schedule(m: int, seed: int, chains: int, graphs: str = "el") -> str:
    """CTEs ``el(gid, place)`` must exist; gives ``sd(chain, iter, gid)``."""
    return f"""
dr AS (SELECT c.chain, i.iter, floor({uniform(f"'{seed}'", "c.chain::VARCHAR", "i.iter::VARCHAR")} * (SELECT count(*) FROM {graphs}))::BIGINT AS place FROM (SELECT unnest(range(1, {m + 1})) AS iter) i, (SELECT unnest(range(0, {chains})) AS chain) c),
sd AS (SELECT chain::INT AS chain, iter, gid FROM dr JOIN {graphs} USING (place))"""


def _draw(step: str, which: int, seed: int = 0) -> str:
    return uniform(f"'{seed}'", "w.chain::VARCHAR", "w.gid::VARCHAR", step, f"'{which}'")


def walk(m: int, chains: int = 1, emit: str = "accepted", graphs: str = "el") -> str:
    """The walk itself over the transitions of pieces of three vertices: first states and moves by the same counters. Gives ``smp(chain, iter, gid, vs)``."""
    moves = f"CASE WHEN {_draw('(w.attempt + 1)::VARCHAR', 1)} <= m.alpha THEN 1 ELSE 0 END"
    return f"""
{schedule(m, 0, chains, graphs)},
visits AS (SELECT chain, gid, iter, row_number() OVER (PARTITION BY chain, gid ORDER BY iter) - 1 AS k FROM sd),
le AS (SELECT gid, src, dst, row_number() OVER (PARTITION BY gid ORDER BY src, dst) - 1 AS i, count(*) OVER (PARTITION BY gid) AS m FROM e),
ch AS (SELECT DISTINCT chain, gid FROM visits),
s0 AS (SELECT w.chain, le.gid, src, dst FROM ch w JOIN le ON le.gid = w.gid WHERE i = floor({_draw("'0'", 0)} * m)),
fz AS (SELECT DISTINCT s0.chain, s0.gid, src, dst, b FROM s0 JOIN sym ON sym.gid = s0.gid AND sym.a IN (src, dst) WHERE b NOT IN (src, dst)),
fr AS (SELECT *, row_number() OVER (PARTITION BY chain, gid ORDER BY b) - 1 AS i, count(*) OVER (PARTITION BY chain, gid) AS m FROM fz),
st AS (SELECT w.chain, w.gid, list_sort([src, dst, b]) AS vs FROM fr w WHERE i = floor({_draw("'0'", 1)} * m)),
ix AS MATERIALIZED (SELECT gid, vs, row_number() OVER (ORDER BY gid, vs) AS sid FROM s3),
cx AS (SELECT sid, gid, u, array_to_string(list_filter(vs, lambda y: y <> u), ',') AS core FROM (SELECT sid, gid, vs, unnest(vs) AS u FROM ix)),
nx AS MATERIALIZED (SELECT a.sid, b.sid AS tid, a.u, b.u AS w FROM cx a JOIN cx b ON a.gid = b.gid AND a.core = b.core AND a.sid <> b.sid),
dx AS MATERIALIZED (SELECT n.sid, n.d, sc.num, sc.den FROM (SELECT sid, count(*) AS d FROM nx GROUP BY sid) n JOIN ix ON ix.sid = n.sid JOIN sc ON sc.gid = ix.gid AND sc.vs = ix.vs),
id AS (SELECT ix.*, d FROM ix JOIN dx USING (sid)),
mo AS (SELECT n.sid, n.tid, y.d AS td, least(1.0::DOUBLE, (x.d * y.num * x.den)::DOUBLE / (y.d * x.num * y.den)::DOUBLE) AS alpha, row_number() OVER (PARTITION BY n.sid ORDER BY n.u, n.w) - 1 AS i
  FROM nx n JOIN dx x ON x.sid = n.sid JOIN dx y ON y.sid = n.tid),
mv AS MATERIALIZED (SELECT sid * 65536 + i AS move, tid, td, alpha FROM mo),
ls AS (SELECT chain, gid, max(k) AS last FROM visits GROUP BY chain, gid),
walk AS (SELECT st.chain, st.gid, id.sid, id.d, 0 AS attempt, 0 AS k, last FROM st JOIN id ON id.gid = st.gid AND id.vs = st.vs JOIN ls ON ls.chain = st.chain AND ls.gid = st.gid
  UNION ALL
  SELECT chain, gid, CASE WHEN moves = 1 THEN tid ELSE sid END, CASE WHEN moves = 1 THEN td ELSE d END, attempt + 1, k + {"1" if emit == "lazy" else "moves"}, last
  FROM (SELECT w.*, m.tid, m.td, {moves} AS moves FROM mv m JOIN (SELECT *, (w.sid * 65536 + floor({_draw('(w.attempt + 1)::VARCHAR', 0)} * w.d))::BIGINT AS move FROM walk w WHERE w.k < w.last) w ON m.move = w.move)),
seen AS (SELECT w.chain, w.gid, w.k, id.vs FROM (SELECT chain, gid, k, arg_min(sid, attempt) AS sid FROM walk GROUP BY chain, gid, k) w JOIN id USING (sid)),
smp AS (SELECT chain, iter, visits.gid, seen.vs FROM visits JOIN seen USING (chain, gid, k))"""


#: After :func:`walk` and :func:`codes`: each sample's pattern and score, and the patterns of each chain, ranked as a queue without a bound ranks them.
MINED = """
nm AS MATERIALIZED (SELECT smp.chain, smp.iter, smp.gid, code, num / den AS score FROM smp JOIN cd ON cd.gid = smp.gid AND cd.vs = smp.vs JOIN sc ON sc.gid = smp.gid AND sc.vs = smp.vs),
fs AS (SELECT chain, code, gid, min(iter) AS t, min(score) AS score FROM nm GROUP BY chain, code, gid),
mq AS (SELECT chain, code, count(*)::INT AS exp_support, min(score) AS score, max(t) AS last_time FROM fs GROUP BY chain, code),
mined AS (SELECT chain, row_number() OVER (PARTITION BY chain ORDER BY exp_support DESC, score DESC, last_time DESC, code)::INT AS rank, code, exp_support, score, last_time FROM mq)"""


def replay(capacity: int) -> str:
    """After :data:`MINED`: the bounded queue, one sample a step, as a list sorted by support, score, time and code. Gives ``kept(x)`` of the last state."""
    entry = "STRUCT(a BIGINT, b DOUBLE, c BIGINT, code VARCHAR, ids BIGINT[])"
    new = f"{{'a': -1::BIGINT, 'b': -score, 'c': -iter, 'code': code, 'ids': [gid]}}::{entry}"
    grown = f"{{'a': hit[1].a - 1, 'b': hit[1].b, 'c': -iter, 'code': code, 'ids': list_append(hit[1].ids, gid)}}::{entry}"
    return f"""
qq AS (SELECT 0::BIGINT AS iter, []::{entry}[] AS q
  UNION ALL
  SELECT iter, CASE WHEN shut THEN q
      WHEN len(hit) > 0 THEN (CASE WHEN list_contains(hit[1].ids, gid) THEN q ELSE list_sort(list_append(list_filter(q, lambda x: x.code <> code), {grown})) END)
      ELSE list_sort(list_append(q[1:{capacity - 1}], {new})) END
  FROM (SELECT s.iter, s.gid, s.code, s.score, w.q, len(w.q) >= {capacity} AND s.score < list_avg(list_transform(w.q[len(w.q) - greatest(1, len(w.q) // 2) + 1:], lambda x: -x.b)) AS shut,
          list_filter(w.q, lambda x: x.code = s.code) AS hit FROM qq w JOIN (SELECT * FROM nm WHERE chain = 0) s ON s.iter = w.iter + 1)),
kept AS (SELECT unnest(q) AS x, unnest(range(1, len(q) + 1)) AS place, len(q) AS n FROM qq WHERE iter = (SELECT max(iter) FROM qq))"""


def plain_codes() -> str:
    """Non-induced pieces of two and three vertices: ``o1``, ``o2``, ``o3(gid, code, ...)`` of one to three edges with their parts' codes, and ``ps(code, n_vertices, n_edges, support)``."""
    one = perm_code_sql(2, lambda i: f"v{i}", lambda i, j: "x01")
    path = lambda a, b, c, x, y: perm_code_sql(3, lambda i: (a, b, c)[i], lambda i, j: {(0, 1): x, (1, 2): y, (0, 2): "'-'"}[i, j])
    ring = perm_code_sql(3, lambda i: f"v{i}", lambda i, j: f"x{i}{j}")
    part = lambda a, b, x: one.replace("v0", a).replace("v1", b).replace("x01", x)
    return f"""
le AS (SELECT e.gid, src, dst, a.vlabel AS la, b.vlabel AS lb, elabel AS el FROM e JOIN v a ON a.gid = e.gid AND a.vid = src JOIN v b ON b.gid = e.gid AND b.vid = dst),
se AS (SELECT gid, src AS a, dst AS b, la, lb, el FROM le UNION ALL SELECT gid, dst, src, lb, la, el FROM le),
o1 AS (SELECT gid, {part('la', 'lb', 'el')} AS code FROM le),
o2 AS (SELECT gid, {path('v0', 'v1', 'v2', 'x01', 'x12')} AS code, {part('v0', 'v1', 'x01')} AS p1, {part('v1', 'v2', 'x12')} AS p2 FROM (
   SELECT x.gid, x.lb AS v0, x.la AS v1, y.lb AS v2, x.el AS x01, y.el AS x12 FROM se x JOIN se y ON x.gid = y.gid AND x.a = y.a AND x.b < y.b)),
o3 AS (SELECT gid, {ring} AS code, {path('v0', 'v1', 'v2', 'x01', 'x12')} AS p1, {path('v1', 'v2', 'v0', 'x12', 'x02')} AS p2, {path('v2', 'v0', 'v1', 'x02', 'x01')} AS p3 FROM (
   SELECT x.gid, x.la AS v0, x.lb AS v1, y.lb AS v2, x.el AS x01, y.el AS x12, z.el AS x02 FROM le x JOIN le y ON x.gid = y.gid AND y.src = x.dst JOIN le z ON z.gid = x.gid AND z.src = x.src AND z.dst = y.dst)),
ps AS (SELECT code, 2 AS n_vertices, 1 AS n_edges, count(DISTINCT gid) AS support FROM o1 GROUP BY code UNION ALL SELECT code, 3, 2, count(DISTINCT gid) FROM o2 GROUP BY code UNION ALL SELECT code, 3, 3, count(DISTINCT gid) FROM o3 GROUP BY code),
parts AS (SELECT DISTINCT code, p1 AS part FROM o2 UNION SELECT DISTINCT code, p2 FROM o2 UNION SELECT DISTINCT code, unnest([p1, p2, p3]) FROM o3)"""
