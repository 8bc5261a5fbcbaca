"""DuckDB SQL twins of the queries, from common table expressions."""

from __future__ import annotations

KEY60 = "('0x' || substr(md5({}), 1, 15))::BIGINT"

GRAPHS = {
    "copurchase_part": """
l AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS p FROM lineitem),
pairs AS (SELECT x.p AS x, y.p AS y FROM l x JOIN l y ON x.o = y.o AND x.p < y.p GROUP BY 1, 2 HAVING count(*) >= 2),
occ AS (SELECT p_partkey AS node, p_type AS event FROM part UNION SELECT p_partkey, p_brand FROM part),
more AS (SELECT p_partkey AS id FROM part)""",
    "cobuyer_customer": """
l AS (SELECT DISTINCT l_partkey AS p, l_suppkey AS s, o_custkey AS c FROM lineitem JOIN orders ON l_orderkey = o_orderkey),
pairs AS (SELECT x.c AS x, y.c AS y FROM l x JOIN l y ON x.p = y.p AND x.s = y.s AND x.c < y.c),
occ AS (SELECT c_custkey AS node, c_mktsegment AS event FROM customer),
more AS (SELECT c_custkey AS id FROM customer)""",
    "order_part": """
pairs AS (SELECT l_orderkey * 2 AS x, l_partkey * 2 + 1 AS y FROM lineitem),
occ AS (SELECT o_orderkey * 2 AS node, o_orderstatus AS event FROM orders UNION SELECT o_orderkey * 2, o_orderpriority FROM orders UNION SELECT p_partkey * 2 + 1, p_brand FROM part),
more AS (SELECT node AS id FROM occ)""",
    "star_tree": """
pairs AS (SELECT n_regionkey * 5 AS x, n_nationkey * 5 + 1 AS y FROM nation UNION ALL SELECT c_nationkey * 5 + 1, c_custkey * 5 + 2 FROM customer
  UNION ALL SELECT o_custkey * 5 + 2, o_orderkey * 5 + 3 FROM orders UNION ALL SELECT s_nationkey * 5 + 1, s_suppkey * 5 + 4 FROM supplier),
occ AS (SELECT c_custkey * 5 + 2 AS node, c_mktsegment AS event FROM customer UNION SELECT o_orderkey * 5 + 3, o_orderstatus FROM orders),
more AS (SELECT node AS id FROM occ)""",
    "page_path": """
pairs AS (SELECT page_id * 2 AS x, (('0x' || substr(md5(href), 1, 15))::BIGINT % 1152921504606846976) * 2 + 1 AS y FROM (
  SELECT page_id, unnest(list_distinct(regexp_extract_all(html, 'href="([^"]*)"', 1))) AS href FROM pages)),
occ AS (SELECT DISTINCT page_id * 2 AS node, regexp_extract(html, '<html[^>]*lang="([^"]*)"', 1) AS event FROM pages WHERE regexp_extract(html, '<html[^>]*lang="([^"]*)"', 1) <> ''),
more AS (SELECT node AS id FROM occ)""",
    "doc_shingle": """
w AS (SELECT doc_id, list_filter(regexp_split_to_array(lower(text), '[^a-z]+'), lambda x: x <> '') AS w FROM documents),
gr AS (SELECT DISTINCT doc_id, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] || ' ' || w[i + 3] AS g FROM w, range(1, len(w) - 2) r(i) WHERE len(w) >= 4),
kept AS (SELECT g FROM gr GROUP BY g HAVING count(*) BETWEEN 2 AND 20),
s AS (SELECT gr.* FROM gr JOIN kept USING (g)),
pairs AS (SELECT DISTINCT x.doc_id AS x, y.doc_id AS y FROM s x JOIN s y ON x.g = y.g AND x.doc_id < y.doc_id),
occ AS (SELECT doc_id AS node, lang AS event FROM documents WHERE lang IS NOT NULL UNION SELECT doc_id, 'q' || quality FROM labels UNION SELECT doc_id, 't' || toxic FROM labels),
more AS (SELECT doc_id AS id FROM documents)""",
    "user_handoff": """
e AS (SELECT user_id AS x, lead(user_id) OVER (ORDER BY ts, event_id) AS y, ts, lead(ts) OVER (ORDER BY ts, event_id) AS ts2 FROM events),
pairs AS (SELECT x, y FROM e WHERE ts2 <= ts + INTERVAL 5 SECOND),
occ AS (SELECT DISTINCT user_id AS node, event_type AS event FROM events WHERE ts < TIMESTAMP '2024-01-02'),
more AS (SELECT user_id AS id FROM events)""",
    "embed_knn": """
v AS (SELECT vec_id, embedding::DOUBLE[] AS a, label FROM embeddings),
u AS (SELECT vec_id, label, unnest(a) AS x, generate_subscripts(a, 1) AS i FROM v),
nrm AS (SELECT vec_id, sqrt(sum(x * x)) AS n FROM u GROUP BY 1),
c AS (SELECT p.vec_id AS x, q.vec_id AS y, round(list_dot_product(p.a, q.a) / (m.n * k.n), 10) AS c FROM v p JOIN v q ON p.vec_id <> q.vec_id JOIN nrm m ON m.vec_id = p.vec_id JOIN nrm k ON k.vec_id = q.vec_id),
pairs AS (SELECT x, y FROM (SELECT *, row_number() OVER (PARTITION BY x ORDER BY c DESC, y) AS r FROM c) WHERE r <= 5),
occ AS (SELECT DISTINCT vec_id AS node, label::VARCHAR AS event FROM embeddings),
more AS (SELECT vec_id AS id FROM embeddings)""",
}


def graph(name: str) -> str:
    return f"""{GRAPHS[name]},
edges AS MATERIALIZED (SELECT DISTINCT least(x, y) AS src, greatest(x, y) AS dst FROM pairs WHERE x <> y),
adj AS (SELECT src AS u, dst AS v FROM edges UNION ALL SELECT dst, src FROM edges),
nodes AS MATERIALIZED (SELECT src AS id FROM edges UNION SELECT dst FROM edges UNION SELECT node FROM occ UNION SELECT id FROM more)"""


def events(a: str, b: str) -> str:
    return f"ev AS MATERIALIZED (SELECT node, bool_or(event = '{a}') AS has_a, bool_or(event = '{b}') AS has_b FROM occ WHERE event IN ('{a}', '{b}') GROUP BY node)"


def seeds(h: int, source: str = "ev", name: str = "s") -> str:
    """{name}0..{name}h: nodes within so many hops of the source's nodes."""
    out = [f"{name}0 AS (SELECT DISTINCT node FROM {source})"]
    out += [f"{name}{d} AS MATERIALIZED (SELECT node FROM {name}{d - 1} UNION SELECT v FROM {name}{d - 1} JOIN adj ON u = node)" for d in range(1, h + 1)]
    return ", ".join(out)


def roots(h: int, source: str, name: str = "b") -> str:
    out = [f"{name}0 AS (SELECT DISTINCT node AS root, node FROM {source})"]
    out += [f"{name}{d} AS MATERIALIZED (SELECT root, node FROM {name}{d - 1} UNION SELECT root, v FROM {name}{d - 1} JOIN adj ON u = node)" for d in range(1, h + 1)]
    return ", ".join(out)


DENS = "dens AS MATERIALIZED (SELECT root AS node, count(*) AS size, count(*) FILTER (WHERE has_a) AS cnt_a, count(*) FILTER (WHERE has_b) AS cnt_b, count(has_a) AS c FROM {b} LEFT JOIN ev ON ev.node = {b}.node GROUP BY root)"
PAIRS = """
d AS (SELECT row_number() OVER (ORDER BY node) AS i, * FROM dens),
pc AS (SELECT count(*) FILTER (WHERE v > 0) AS concordant, count(*) FILTER (WHERE v < 0) AS discordant, count(*) FILTER (WHERE p = 0 AND q <> 0) AS tied_a, count(*) FILTER (WHERE p <> 0 AND q = 0) AS tied_b, count(*) FILTER (WHERE p = 0 AND q = 0) AS tied_both
  FROM (SELECT p, q, p * q AS v FROM (SELECT sign(x.cnt_a * y.size - y.cnt_a * x.size) AS p, sign(x.cnt_b * y.size - y.cnt_b * x.size) AS q FROM d x JOIN d y ON x.i < y.i)))"""


def ties(side: str) -> str:
    return f"t{side} AS (SELECT sum(u * (u - 1))::DOUBLE AS t2, sum(u * (u - 1) * (u - 2))::DOUBLE AS t3, sum(u * (u - 1) * (2 * u + 5))::DOUBLE AS t5 FROM (SELECT count(*)::HUGEINT AS u FROM dens GROUP BY cnt_{side} / size))"


ERFC = "((((1.061405429 * t - 1.453152027) * t + 1.421413741) * t - 0.284496736) * t + 0.254829592) * t * exp(-z * z / 2) / 2"
TEST = f"""{PAIRS}, {ties('a')}, {ties('b')},
m AS (SELECT (SELECT count(*) FROM dens) AS n, (concordant - discordant)::BIGINT AS s FROM pc),
vs AS (SELECT n, s, (n::DOUBLE * (n - 1) * (2 * n + 5) - ta.t5 - tb.t5) / 18 + ta.t3 * tb.t3 / (9 * n::DOUBLE * (n - 1) * (n - 2)) + ta.t2 * tb.t2 / (2 * n::DOUBLE * (n - 1)) AS var_s FROM m, ta, tb),
zz AS (SELECT *, s / sqrt(var_s) AS z, 1 / (1 + 0.3275911 * abs(s / sqrt(var_s)) / sqrt(2)) AS t FROM vs),
res AS (SELECT n, s, round(s / (n * (n - 1) / 2.0), 6) AS t, round(var_s, 3) AS var_s, round(z, 6) AS z, round(CASE WHEN z >= 0 THEN {ERFC} ELSE 1 - {ERFC} END, 6) AS p_upper,
  CASE WHEN (CASE WHEN z >= 0 THEN {ERFC} ELSE 1 - {ERFC} END) < 0.05 THEN 'attraction' WHEN (CASE WHEN z <= 0 THEN {ERFC} ELSE 1 - {ERFC} END) < 0.05 THEN 'repulsion' ELSE 'none' END AS verdict FROM zz)"""


def exact(name: str, a: str, b: str, h: int) -> str:
    return f"WITH {graph(name)}, {events(a, b)}, {seeds(h)}, {roots(h, f's{h}')}, {DENS.format(b=f'b{h}')}, {TEST} SELECT * FROM res"


def dens(name: str, a: str, b: str, h: int) -> str:
    return f"WITH {graph(name)}, {events(a, b)}, {seeds(h)}, {roots(h, f's{h}')}, {DENS.format(b=f'b{h}')}"


def draws(h: int, total_draws: int, seed: int = 42) -> str:
    """picks(j, root, size, at) and member(j, node), as the weighted draw makes them."""
    return f"""{roots(h, 'ev', 'e')},
sz AS (SELECT root AS node, count(*) AS size FROM e{h} GROUP BY root),
iv AS MATERIALIZED (SELECT node, size, (sum(size) OVER (ORDER BY node) - size)::BIGINT AS lo FROM sz),
x AS (SELECT j, ('0x' || substr(md5(j || ':{seed}'), 1, 15))::BIGINT % (SELECT sum(size)::BIGINT FROM iv) AS x FROM range(1, {total_draws + 1}) r(j)),
picks AS MATERIALIZED (SELECT j, node AS root, size, x - lo AS at_ FROM x JOIN iv ON x >= lo AND x < lo + size),
ordered AS MATERIALIZED (SELECT root, node, row_number() OVER (PARTITION BY root ORDER BY md5(node || ':{seed}'), node) - 1 AS pos FROM e{h}),
member AS MATERIALIZED (SELECT j, 1 AS i, node FROM picks JOIN ordered ON picks.root = ordered.root AND picks.at_ = ordered.pos)"""


def first_distinct(n: int, source: str = "member") -> str:
    return f"""f AS (SELECT node, min(j * 100 + i) AS k FROM {source} GROUP BY node),
lastk AS (SELECT max(k) AS k FROM (SELECT k FROM f ORDER BY k LIMIT {n})),
smp AS MATERIALIZED (SELECT node, count(*) AS w FROM {source}, lastk WHERE j * 100 + i <= lastk.k GROUP BY node)"""
