"""The graphs and the sequential rules as DuckDB SQL, written from their definitions, to check the engine against."""

from __future__ import annotations

_SHINGLES = "list_distinct(list_transform(range(1, len(w) - {n} + 2), lambda i: array_to_string(w[i:i + {n} - 1], ' ')))"
_WORDS = r"list_filter(regexp_split_to_array(lower(coalesce(text, '')), '\s+'), lambda x: x <> '')"


def _grams(table: str, key: str, n: int = 5) -> str:
    return f"SELECT {key}, unnest({_SHINGLES.format(n=n)}) AS g FROM (SELECT {key}, {_WORDS} AS w FROM {table}) WHERE len(w) >= {n}"


#: raw edges (a, b, w) of each builder
PAIRS = {
    "G1": "SELECT x.l_partkey AS a, y.l_partkey AS b, count(*) AS w FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) x JOIN (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) y ON x.l_orderkey = y.l_orderkey AND x.l_partkey < y.l_partkey GROUP BY 1, 2",
    "G1w": "SELECT x.l_partkey AS a, y.l_partkey AS b, count(*) AS w FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) x JOIN (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) y ON x.l_orderkey = y.l_orderkey AND x.l_partkey < y.l_partkey GROUP BY 1, 2 HAVING count(*) >= 2",
    "G2": "SELECT 'c' || o_custkey AS a, 's' || l_suppkey AS b, count(*) AS w FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1, 2",
    "G3": "SELECT 'b' || n_nationkey AS a, 'a' || n_regionkey AS b, 1 AS w FROM nation UNION ALL SELECT 'b' || c_nationkey, 'c' || c_custkey, 1 FROM customer UNION ALL SELECT 'b' || s_nationkey, 'd' || s_suppkey, 1 FROM supplier",
    "G4": "SELECT x.u AS a, y.u AS b, count(*) AS w FROM (SELECT DISTINCT user_id AS u, floor(epoch(ts) / 300) AS t FROM events) x JOIN (SELECT DISTINCT user_id AS u, floor(epoch(ts) / 300) AS t FROM events) y ON x.t = y.t AND x.u < y.u GROUP BY 1, 2",
    "G5": f"SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS w FROM (SELECT *, count(*) OVER (PARTITION BY g) AS df FROM ({_grams('documents', 'doc_id')})) x JOIN ({_grams('documents', 'doc_id')}) y ON x.g = y.g AND x.doc_id < y.doc_id WHERE x.df <= 100 GROUP BY 1, 2",
    "G6": "SELECT DISTINCT 'p' || page_id AS a, 't' || unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS b, 1 AS w FROM pages",
    "G7": "SELECT DISTINCT least(a, b) AS a, greatest(a, b) AS b, 1 AS w FROM (SELECT a, b, row_number() OVER (PARTITION BY a ORDER BY s DESC, b) AS r FROM (SELECT x.vec_id AS a, y.vec_id AS b, list_inner_product(x.v, y.v) AS s FROM (SELECT vec_id, list_transform(embedding, lambda z: CAST(round(CAST(z AS DOUBLE) * 10000) AS DOUBLE)) AS v FROM embeddings) x JOIN (SELECT vec_id, list_transform(embedding, lambda z: CAST(round(CAST(z AS DOUBLE) * 10000) AS DOUBLE)) AS v FROM embeddings) y ON x.vec_id <> y.vec_id)) WHERE r <= 10",
    "G8": "SELECT conv_id * 1000 + turn AS a, conv_id * 1000 + n AS b, 1 AS w FROM (SELECT conv_id, turn, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS n FROM (SELECT DISTINCT conv_id, turn FROM conversations)) WHERE n IS NOT NULL",
    "G9": "SELECT DISTINCT 'o' || l_orderkey AS a, 'p' || l_partkey AS b, 1 AS w FROM lineitem",
    "G10": f"SELECT 'd' || x.doc_id AS a, 'b' || y.item_id AS b, count(*) AS w FROM ({_grams('documents', 'doc_id')}) x JOIN ({_grams('benchmark', 'item_id')}) y ON x.g = y.g GROUP BY 1, 2",
}

#: T, the worked example: two triangles and a bridge; names of fixed graphs can be used as those of built ones
PAIRS["T"] = "SELECT * FROM (VALUES (0, 1, 1), (0, 2, 1), (1, 2, 1), (2, 3, 1), (3, 4, 1), (3, 5, 1), (4, 5, 1)) t(a, b, w)"


def graph_ctes(name: str, unit: bool = True) -> str:
    """CTEs arcs (src, dst, w), nodes (id, okey, deg, wdeg, cw), tot (two_m, n), materialised once."""
    weight = "CAST(1 AS BIGINT)" if unit else "CAST(sum(w) AS BIGINT)"
    return f"""raw AS ({PAIRS[name]}),
e AS MATERIALIZED (SELECT least(a, b) AS a, greatest(a, b) AS b, {weight} AS w FROM raw WHERE a <> b GROUP BY 1, 2),
ids AS MATERIALIZED (SELECT k, row_number() OVER (ORDER BY k) - 1 AS id FROM (SELECT a AS k FROM e UNION SELECT b FROM e)),
half AS MATERIALIZED (SELECT x.id AS u, y.id AS v, w FROM e JOIN ids x ON e.a = x.k JOIN ids y ON e.b = y.k),
arcs AS MATERIALIZED (SELECT u AS src, v AS dst, w FROM half UNION ALL SELECT v, u, w FROM half),
nodes AS MATERIALIZED (SELECT id, CAST(k AS VARCHAR) AS okey, d.deg, d.wdeg, 1 AS cw FROM ids JOIN (SELECT src, count(*) AS deg, CAST(sum(w) AS BIGINT) AS wdeg FROM arcs GROUP BY 1) d ON d.src = ids.id),
tot AS MATERIALIZED (SELECT CAST(sum(wdeg) AS BIGINT) AS two_m, count(*) AS n FROM nodes)"""


def with_graph(name: str, body: str, more: str = "", unit: bool = True) -> str:
    """A query over a graph; more: further CTEs."""
    return f"WITH RECURSIVE {graph_ctes(name, unit)}{', ' + more if more else ''} {body}"


def one_pass(candidates: str = "assigned", order: str = "id") -> str:
    """CTEs ordered (id, rank, wdeg) and st (node, cid, d, pos): the node stream, one node per iteration."""
    ordered = f"ordered AS MATERIALIZED (SELECT id, wdeg, row_number() OVER (ORDER BY {order}) - 1 AS rank FROM nodes)"
    if candidates == "assigned":
        return f"""{ordered},
st(node, cid, d, pos) USING KEY (node) AS (
  SELECT id, id, wdeg, rank FROM ordered WHERE rank = 0
  UNION
  SELECT nx.id, coalesce(b.c, nx.id), nx.wdeg, nx.rank
  FROM (SELECT o.* FROM ordered o, (SELECT max(pos) AS p FROM st) l WHERE o.rank = l.p + 1) nx
  LEFT JOIN (
    SELECT k.src, arg_max(k.cid, (k.g, -k.cid)) AS c FROM (
      SELECT l.src, l.cid, (SELECT two_m FROM tot) * l.k - n.wdeg * v.vol AS g
      FROM (SELECT a.src, s.cid, sum(a.w) AS k FROM arcs a JOIN recurring.st s ON a.dst = s.node
            WHERE a.src = (SELECT o.id FROM ordered o WHERE o.rank = (SELECT max(pos) FROM st) + 1) GROUP BY 1, 2) l
      JOIN (SELECT cid, sum(d) AS vol FROM recurring.st GROUP BY 1) v ON v.cid = l.cid
      JOIN nodes n ON n.id = l.src) k
    WHERE k.g > 0 GROUP BY k.src) b ON b.src = nx.id)"""
    return f"""{ordered},
st(node, cid, d, pos) USING KEY (node) AS (
  SELECT id, id, wdeg, CAST(-1 AS BIGINT) FROM ordered
  UNION ALL
  SELECT nx.id, coalesce(b.c, nx.cur), nx.wdeg, nx.rank
  FROM (SELECT o.*, s.cid AS cur FROM ordered o JOIN (SELECT max(pos) AS p FROM st) l ON o.rank = l.p + 1 JOIN recurring.st s ON s.node = o.id) nx
  LEFT JOIN (
    SELECT k.src, arg_max(k.cid, (k.g, -k.cid)) AS c FROM (
      SELECT l.src, l.cid, (SELECT two_m FROM tot) * (l.k - l.own) - n.wdeg * (n.wdeg + v.vol - vc.vol) AS g
      FROM (SELECT x.src, x.cid, x.k, coalesce(sum(x.k) FILTER (WHERE x.cid = me.cid) OVER (), 0) AS own, me.cid AS cur FROM (
              SELECT a.src, s.cid, sum(a.w) AS k FROM arcs a JOIN recurring.st s ON a.dst = s.node
              WHERE a.src = (SELECT o.id FROM ordered o WHERE o.rank = (SELECT max(pos) FROM st) + 1) GROUP BY 1, 2) x
            JOIN recurring.st me ON me.node = x.src) l
      JOIN (SELECT cid, sum(d) AS vol FROM recurring.st GROUP BY 1) v ON v.cid = l.cid
      JOIN (SELECT cid, sum(d) AS vol FROM recurring.st GROUP BY 1) vc ON vc.cid = l.cur
      JOIN nodes n ON n.id = l.src WHERE l.cid <> l.cur) k
    WHERE k.g > 0 GROUP BY k.src) b ON b.src = nx.id)"""


def edge_stream(limit: str, order: str = "u, v") -> str:
    """CTEs es (seq, u, v) and st (k, com, deg): k = -1 is the cursor, whose com is the next seq. limit: the cap as SQL."""
    return f"""es AS MATERIALIZED (SELECT row_number() OVER (ORDER BY {order}) - 1 AS seq, u, v FROM half),
cap AS MATERIALIZED (SELECT {limit} AS lim),
st(k, com, deg) USING KEY (k) AS (
  SELECT id, id, CAST(0 AS BIGINT) FROM nodes UNION ALL SELECT -1, 0, 0
  UNION ALL
  SELECT unnest([CAST(-1 AS BIGINT), z.u, z.v]), unnest([z.seq + 1, z.nu, z.nv]), unnest([CAST(0 AS BIGINT), z.du, z.dv]) FROM (
    SELECT y.seq, y.u, y.v, y.du, y.dv,
      CASE WHEN y.cu <> y.cv AND greatest(y.vu, y.vv) <= (SELECT lim FROM cap) AND y.vu <= y.vv THEN y.cv ELSE y.cu END AS nu,
      CASE WHEN y.cu <> y.cv AND greatest(y.vu, y.vv) <= (SELECT lim FROM cap) AND y.vu > y.vv THEN y.cu ELSE y.cv END AS nv
    FROM (SELECT e.seq, e.u, e.v, a.com AS cu, b.com AS cv, a.deg + 1 AS du, b.deg + 1 AS dv,
        CAST((SELECT sum(s.deg) FROM recurring.st s WHERE s.k >= 0 AND s.com = a.com) + 1 + CASE WHEN a.com = b.com THEN 1 ELSE 0 END AS BIGINT) AS vu,
        CAST((SELECT sum(s.deg) FROM recurring.st s WHERE s.k >= 0 AND s.com = b.com) + 1 + CASE WHEN a.com = b.com THEN 1 ELSE 0 END AS BIGINT) AS vv
      FROM es e JOIN (SELECT com AS c FROM st WHERE k = -1) cur ON e.seq = cur.c JOIN recurring.st a ON a.k = e.u JOIN recurring.st b ON b.k = e.v) y) z)"""


def restream(start: str, rounds: int = 1 << 30) -> str:
    """CTEs begin (id, cid) from the SQL start, and st (k, com, d, due0, due1): flags of even and odd rounds; row -1 holds (round, last id).
    rounds: how many are made at most."""
    return f"""begin_ AS MATERIALIZED ({start}),
st(k, com, d, due0, due1) USING KEY (k) AS (
  SELECT n.id, b.cid, n.wdeg, true, false FROM nodes n JOIN begin_ b ON b.id = n.id UNION ALL SELECT -1, 0, -1, false, false
  UNION ALL
  SELECT o.k, o.com, o.d, o.due0, o.due1 FROM (
    WITH cur AS (SELECT com AS r, d AS last FROM recurring.st WHERE k = -1),
    nxt AS (SELECT min(s.k) AS v FROM recurring.st s, cur WHERE cur.r < {rounds} AND s.k > cur.last AND s.k >= 0 AND CASE WHEN cur.r % 2 = 0 THEN s.due0 ELSE s.due1 END),
    lk AS (SELECT s.com AS c, sum(a.w) AS k FROM arcs a JOIN nxt ON a.src = nxt.v JOIN recurring.st s ON s.k = a.dst GROUP BY 1),
    me AS (SELECT s.k AS v, s.com AS cur, s.d, s.due0, s.due1, coalesce((SELECT lk.k FROM lk WHERE lk.c = s.com), 0) AS own FROM recurring.st s JOIN nxt ON s.k = nxt.v),
    vol AS (SELECT com AS c, sum(d) AS x FROM recurring.st WHERE k >= 0 GROUP BY 1),
    gain AS (SELECT lk.c, (SELECT two_m FROM tot) * (lk.k - me.own) - me.d * (me.d + vol.x - vc.x) AS g
      FROM lk JOIN vol ON vol.c = lk.c, me JOIN vol vc ON vc.c = me.cur WHERE lk.c <> me.cur),
    best AS (SELECT arg_max(c, (g, -c)) AS c FROM gain WHERE g > 0)
    SELECT me.v AS k, coalesce(best.c, me.cur) AS com, me.d, CASE WHEN cur.r % 2 = 0 THEN false ELSE me.due0 END AS due0, CASE WHEN cur.r % 2 = 1 THEN false ELSE me.due1 END AS due1
      FROM me, cur, best
    UNION ALL
    SELECT s.k, s.com, s.d, s.due0 OR cur.r % 2 = 1, s.due1 OR cur.r % 2 = 0
      FROM (SELECT DISTINCT a.dst FROM arcs a JOIN nxt ON a.src = nxt.v) t JOIN recurring.st s ON s.k = t.dst, cur, best WHERE best.c IS NOT NULL
    UNION ALL
    SELECT -1, cur.r, nxt.v, false, false FROM cur, nxt WHERE nxt.v IS NOT NULL
    UNION ALL
    SELECT -1, cur.r + 1, -1, false, false FROM cur, nxt WHERE nxt.v IS NULL AND cur.r + 1 < {rounds}
      AND EXISTS (SELECT 1 FROM recurring.st s, cur c2 WHERE s.k >= 0 AND CASE WHEN c2.r % 2 = 0 THEN s.due1 ELSE s.due0 END)) o)"""


def wave_pass(n_waves: int, ready: int = 900) -> str:
    """CTEs w0 .. w<n_waves> (id, cid): the first waves of the pass over the whole stream in id order; cid is null while a node waits."""
    out = ["w0 AS MATERIALIZED (SELECT id, CAST(NULL AS BIGINT) AS cid FROM nodes)"]
    for i in range(n_waves):
        out.append(f"""r{i} AS MATERIALIZED (SELECT n.id, n.wdeg AS d FROM nodes n JOIN w{i} s ON s.id = n.id AND s.cid IS NULL
  LEFT JOIN (SELECT a.src, sum(a.w) AS b, coalesce(sum(a.w) FILTER (WHERE t.cid IS NOT NULL), 0) AS have FROM arcs a JOIN w{i} t ON t.id = a.dst WHERE a.dst < a.src GROUP BY 1) x ON x.src = n.id
  WHERE x.b IS NULL OR x.have * 1000 // x.b >= {ready}),
v{i} AS MATERIALIZED (SELECT s.cid, sum(n.wdeg) AS vol FROM w{i} s JOIN nodes n USING (id) WHERE s.cid IS NOT NULL GROUP BY 1),
g{i} AS MATERIALIZED (SELECT k.id, k.d, k.cid, k.k, v.vol, (SELECT two_m FROM tot) * k.k - k.d * v.vol AS gain FROM
  (SELECT r.id, r.d, s.cid, sum(a.w) AS k FROM r{i} r JOIN arcs a ON a.src = r.id JOIN w{i} s ON s.id = a.dst AND s.cid IS NOT NULL GROUP BY 1, 2, 3) k JOIN v{i} v USING (cid)),
b{i} AS MATERIALIZED (SELECT id, any_value(d) AS d, arg_max((cid, k, vol, gain), (gain, -cid)) AS b FROM g{i} WHERE gain > 0 GROUP BY id),
j{i} AS MATERIALIZED (SELECT id, d, b[1] AS cid, b[2] AS k, b[3] AS vol, coalesce(sum(d) OVER (PARTITION BY b[1] ORDER BY floor(log2(CAST(b[4] AS DOUBLE)) * 8) DESC, id >> 16, b[4] DESC, id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS joined FROM b{i}),
w{i + 1} AS MATERIALIZED (SELECT s.id, CASE WHEN s.cid IS NOT NULL THEN s.cid WHEN r.id IS NULL THEN NULL WHEN j.id IS NULL THEN s.id
  WHEN (SELECT two_m FROM tot) * j.k - j.d * (j.vol + j.joined) > 0 THEN j.cid END AS cid FROM w{i} s LEFT JOIN r{i} r USING (id) LEFT JOIN j{i} j USING (id))""")
    return ",\n".join(out)
