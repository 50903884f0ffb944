"""SQL fragments for oracles: fixtures, refinement rounds, k-means layers, as common table expressions."""

from __future__ import annotations

import math


def with_(*ctes: str) -> str:
    return "WITH " + ",\n".join(c for c in ctes if c)


def norm(x: str) -> str:
    return f"sqrt(list_dot_product({x}, {x}))"


def unit(x: str) -> str:
    return f"CASE WHEN list_dot_product({x}, {x}) > 0 THEN list_transform({x}, lambda e: e / {norm(x)}) ELSE {x} END"


def r6(x: str, digits: int = 6) -> str:
    return f"round({x}, {digits}) + 0.0"


def emb_nodes(scale: float = 1.0) -> str:
    return f"x0 AS MATERIALIZED (SELECT vec_id AS id, list_transform(embedding, lambda e: e::DOUBLE * {scale}) AS x, label AS verdict, label FROM embeddings)"


def emb_edges(tau: float) -> str:
    return f"""u0 AS MATERIALIZED (SELECT id, {unit('x')} AS u FROM x0),
ed AS MATERIALIZED (SELECT a.id AS src, b.id AS dst FROM u0 a JOIN u0 b ON a.id <> b.id WHERE round(list_dot_product(a.u, b.u), 9) > {tau})"""


PART_PAIRS = """pp AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS p FROM lineitem),
pe AS (SELECT a.p AS src, b.p AS dst, count(*) AS support FROM pp a JOIN pp b ON a.o = b.o AND a.p < b.p GROUP BY ALL)"""


def part_fixture(min_support: int) -> str:
    return f"""br AS (SELECT list(b ORDER BY b) AS bs FROM (SELECT DISTINCT p_brand AS b FROM part)),
ty AS (SELECT list(t ORDER BY t) AS ts FROM (SELECT DISTINCT p_type AS t FROM part)),
x0 AS MATERIALIZED (SELECT p_partkey AS id, list_concat(list_transform(bs, lambda b: CASE WHEN b = p_brand THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END),
  [p_size / 50.0::DOUBLE, (p_retailprice - 900.0::DOUBLE) / 100.0::DOUBLE]) AS x, (list_position(ts, p_type) - 1)::INT AS verdict, (list_position(ts, p_type) - 1)::INT AS label FROM part, br, ty),
{PART_PAIRS},
ed AS MATERIALIZED (SELECT src, dst FROM pe WHERE support >= {min_support} UNION ALL SELECT dst, src FROM pe WHERE support >= {min_support})"""


CUST_BASE = """pk AS (SELECT list(p ORDER BY p) AS ps FROM (SELECT DISTINCT o_orderpriority AS p FROM orders)),
sg AS (SELECT list(s ORDER BY s) AS ss FROM (SELECT DISTINCT c_mktsegment AS s FROM customer)),
rg AS (SELECT list(r ORDER BY r) AS rs FROM (SELECT DISTINCT r_name AS r FROM region)),
per AS (SELECT o_custkey, count(*) AS orders, avg(o_totalprice) AS mean_price FROM orders GROUP BY 1),
mx AS (SELECT o_custkey, list(share ORDER BY p) AS mix FROM (SELECT o_custkey, p, avg(CASE WHEN o_orderpriority = p THEN 1.0 ELSE 0.0 END)::DOUBLE AS share FROM orders, (SELECT unnest(ps) AS p FROM pk) GROUP BY ALL) GROUP BY 1),
cb AS MATERIALIZED (SELECT c_custkey, c_nationkey, c_mktsegment, r_name, c_acctbal, coalesce(orders, 0) AS orders, coalesce(mean_price, 0.0) AS mean_price,
  coalesce(mix, list_transform(ps, lambda p: 0.0::DOUBLE)) AS mix
  FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey, pk LEFT JOIN per ON per.o_custkey = c_custkey LEFT JOIN mx ON mx.o_custkey = c_custkey)"""

CUST_FIXTURE = f"""{CUST_BASE},
x0 AS MATERIALIZED (SELECT c_custkey AS id, list_concat(list_concat(list_transform(ss, lambda s: CASE WHEN s = c_mktsegment THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END),
  list_transform(rs, lambda r: CASE WHEN r = r_name THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END)), list_concat([orders / 20.0::DOUBLE, mean_price / 100000.0::DOUBLE], mix)) AS x,
  CASE WHEN c_acctbal < 0 THEN 1 ELSE 0 END AS label FROM cb, sg, rg),
ed AS MATERIALIZED (SELECT a.c_custkey AS src, b.c_custkey AS dst FROM customer a JOIN customer b ON a.c_nationkey = b.c_nationkey AND a.c_mktsegment = b.c_mktsegment AND a.c_custkey <> b.c_custkey)"""

CUST_VALUES = """fv AS MATERIALIZED (SELECT c_custkey AS id, unnest(['region', 'segment', 'orders', 'price']) AS feature, unnest([r_name, c_mktsegment,
  CASE WHEN orders < 8 THEN '0-7' WHEN orders < 13 THEN '8-12' ELSE '13+' END, CASE WHEN mean_price < 150000 THEN 'low' WHEN mean_price < 250000 THEN 'mid' ELSE 'high' END]) AS value FROM cb)"""


def refine(i: int, dim: int, alpha: float = 0.5) -> str:
    """``x{i}`` to ``x{i+1}``."""
    j = i + 1
    return f"""w{i} AS MATERIALIZED (SELECT src, dst, CASE WHEN {norm('a.x')} * {norm('b.x')} > 0 THEN list_dot_product(a.x, b.x) / ({norm('a.x')} * {norm('b.x')}) ELSE 0 END AS c
  FROM ed JOIN x{i} a ON a.id = src JOIN x{i} b ON b.id = dst),
m{i} AS (SELECT src AS id, i, avg(c * b.x[i]) AS m FROM w{i} JOIN x{i} b ON b.id = dst, range(1, {dim + 1}) t(i) GROUP BY src, i),
l{i} AS MATERIALIZED (SELECT id, list(m ORDER BY i) AS m FROM m{i} GROUP BY id),
x{j} AS MATERIALIZED (SELECT v.id, CASE WHEN m IS NULL THEN list_transform(x, lambda e: e * {alpha}) ELSE list_transform(list_zip(x, m), lambda z: z[1] * {alpha} + z[2] * {1 - alpha}) END AS x
  FROM x{i} v LEFT JOIN l{i} ON l{i}.id = v.id)"""


def signatures(dim: int, hops: int = 2, verdict: str = "x0") -> str:
    """``sig(id, verdict, s)`` from ``x0`` and ``ed``; ``verdict`` names the relation (id, verdict) to take verdicts from."""
    rounds = ",\n".join(refine(i, dim) for i in range(hops))
    total = "x0.x"
    joins = ""
    for i in range(1, hops + 1):
        total = f"list_transform(list_zip({total}, x{i}.x), lambda z: z[1] + z[2])"
        joins += f" JOIN x{i} USING (id)"
    return f"""{rounds},
tot AS MATERIALIZED (SELECT id, {total} AS t FROM x0{joins}),
sig AS MATERIALIZED (SELECT id, v.verdict, {unit('t')} AS s FROM tot JOIN (SELECT id, verdict FROM {verdict}) v USING (id))"""


def emb_sig(tau: float = 0.2, hops: int = 2, scale: float = 1.0) -> str:
    return ",\n".join((emb_nodes(scale), emb_edges(tau), signatures(64, hops)))


def centroid_rule(dim: int) -> str:
    """``vd(id, verdict)`` from ``x0(id, x, label)`` and ``ed``, fitted on ids below 6 modulo 10."""
    return f"""hm AS (SELECT id, i, avg(v) AS h FROM (SELECT src AS id, i, b.x[i] AS v FROM ed JOIN x0 b ON b.id = dst, range(1, {dim + 1}) t(i) UNION ALL SELECT id, i, x[i] FROM x0, range(1, {dim + 1}) t(i)) GROUP BY id, i),
hl AS MATERIALIZED (SELECT id, list(h ORDER BY i) AS h FROM hm GROUP BY id),
cm AS (SELECT label, list(m ORDER BY i) AS m FROM (SELECT label, i, avg(h) AS m FROM hm JOIN x0 USING (id) WHERE label IS NOT NULL AND id % 10 < 6 GROUP BY label, i) GROUP BY label),
vd AS MATERIALIZED (SELECT id, label::INT AS verdict FROM (SELECT hl.id, cm.label, row_number() OVER (PARTITION BY hl.id ORDER BY round(list_dot_product(m, m) - 2 * list_dot_product(h, m), 9), cm.label) AS r FROM hl, cm) WHERE r = 1)"""


def local(k: int, name: str = "lt", only: str = "") -> str:
    """``lt(v, u, rank, sim)``: exact local twins; ``only`` is a condition on ``a.id``."""
    return f"""{name} AS MATERIALIZED (SELECT * FROM (SELECT a.id AS v, b.id AS u, row_number() OVER (PARTITION BY a.id ORDER BY round(list_dot_product(a.s, b.s), 9) DESC, b.id)::INT AS rank,
  round(list_dot_product(a.s, b.s), 9) AS sim FROM sig a JOIN sig b ON a.verdict <> b.verdict{only}) WHERE rank <= {k})"""


def lloyd(layer: int, m: int, rounds: int, weight: str | None = None) -> str:
    """``at{layer}(id, c, cos)`` and ``mu{layer}_{rounds}``; ``weight`` names a relation (id, w)."""
    n = f"{layer}"
    out = [f"mu{n}_0 AS MATERIALIZED (SELECT (row_number() OVER (ORDER BY md5(id || ':{layer}')) - 1)::INT AS c, s AS mu FROM sig ORDER BY md5(id || ':{layer}') LIMIT {m})"]

    def at(r: int) -> str:
        cos = f"CASE WHEN {norm('mu')} > 0 THEN list_dot_product(s, mu) / {norm('mu')} ELSE 0 END"
        return f"""at{n}_{r} AS MATERIALIZED (SELECT id, c, cos FROM (SELECT id, c, {cos} AS cos, row_number() OVER (PARTITION BY id ORDER BY round({cos}, 12) DESC, c) AS rn FROM sig, mu{n}_{r}) WHERE rn = 1)"""

    for r in range(rounds):
        w, join = ("greatest(w, 1e-9)", f" JOIN {weight} USING (id)") if weight else ("1.0", "")
        out.append(at(r))
        out.append(f"""mu{n}_{r + 1} AS MATERIALIZED (SELECT o.c, coalesce(n.mu, o.mu) AS mu FROM mu{n}_{r} o LEFT JOIN (SELECT c, list(v ORDER BY i) AS mu FROM (SELECT c, i, sum({w} * s[i]) / count(*) AS v
  FROM at{n}_{r} JOIN sig USING (id){join}, (SELECT unnest(range(1, len(s) + 1)) AS i FROM (SELECT s FROM sig LIMIT 1)) GROUP BY c, i) GROUP BY c) n USING (c))""")
    out.append(at(rounds))
    out.append(f"at{n} AS (SELECT * FROM at{n}_{rounds})")
    return ",\n".join(out)


def cap_table(dim: int, theta: float = math.pi / 3, points: int = 2001, intervals: int = 400) -> str:
    """``tab(t)``: the weight table as one list."""
    return f"""gi AS (SELECT j, (top / {intervals} / 3) * sum((CASE WHEN q IN (0, {intervals}) THEN 1.0 WHEN q % 2 = 1 THEN 4.0 ELSE 2.0 END)
  * 2 * (top * q / {intervals}) * pow(greatest(0.0, 1.0 - pow(cos({theta!r}) / cos({theta!r} - pow(top * q / {intervals}, 2)), 2)), ({dim} - 2) / 2.0)) AS g
  FROM (SELECT j, sqrt({theta!r} - least({theta!r}, {theta!r} * j / {points - 1})) AS top FROM range(0, {points}) t(j)), range(0, {intervals + 1}) s(q) GROUP BY j, top),
tab AS MATERIALIZED (SELECT list(CASE WHEN j < {points - 1} AND g > 0 THEN 1.0 - g / g0 ELSE 1.0 END ORDER BY j) AS t FROM gi, (SELECT g AS g0 FROM gi WHERE j = 0))"""


def weight_of(cos: str, theta: float = math.pi / 3, points: int = 2001) -> str:
    at = f"(acos(greatest(-1.0, least(1.0, {cos}))) / {2 * theta!r} * {points - 1})"
    lo = f"least(floor({at})::INT, {points - 2})"
    return f"CASE WHEN {at} >= {points - 1} THEN 1.0 ELSE t[{lo} + 1] + ({at} - {lo}) * (t[{lo} + 2] - t[{lo} + 1]) END"


def layers(p: int, m: int, rounds: int, dim: int, carry: str = "last", rule: str = "cap") -> str:
    """Layers 0 to ``p``; ``wt{l}(id, w)`` are weights, ``asg(layer, c, id, cos, w)`` layers 1 to p, ``home(id, layer, c)``."""
    w = "1.0 - cos" if rule == "distance" else weight_of("cos")
    out = ["" if rule == "distance" else cap_table(dim), lloyd(0, m, rounds)]
    src = "" if rule == "distance" else ", tab"
    out.append(f"wt0 AS MATERIALIZED (SELECT id, {w} AS w FROM at0{src})")
    out.append("cw0 AS (SELECT id, 1.0 AS w FROM wt0)" if rule == "unit" else "cw0 AS (SELECT * FROM wt0)")
    for i in range(1, p + 1):
        out.append(lloyd(i, m, rounds, f"cw{i - 1}"))
        out.append(f"wt{i} AS MATERIALIZED (SELECT id, {w} AS w FROM at{i}{src})")
        mix = "1.0" if rule == "unit" else {"last": "n.w", "min": "least(o.w, n.w)", "product": "o.w * n.w"}[carry]
        out.append(f"cw{i} AS MATERIALIZED (SELECT n.id, {mix} AS w FROM cw{i - 1} o JOIN wt{i} n USING (id))")
    union = " UNION ALL ".join(f"SELECT {i} AS layer, c, id, cos, w FROM at{i} JOIN wt{i} USING (id)" for i in range(1, p + 1))
    out.append(f"asg AS MATERIALIZED ({union})")
    out.append("home AS MATERIALIZED (SELECT id, layer, c FROM (SELECT id, layer, c, row_number() OVER (PARTITION BY id ORDER BY round(w, 12), round(cos, 12) DESC, layer) AS rn FROM asg) WHERE rn = 1)")
    return ",\n".join(x for x in out if x)


def indexed(k: int, name: str = "ix") -> str:
    """``ix(v, u, rank, sim)``: twins inside each node's home."""
    return f"""{name} AS MATERIALIZED (SELECT * FROM (SELECT a.id AS v, b.id AS u, row_number() OVER (PARTITION BY a.id ORDER BY round(list_dot_product(a.s, b.s), 9) DESC, b.id)::INT AS rank,
  round(list_dot_product(a.s, b.s), 9) AS sim FROM sig a JOIN home h ON h.id = a.id JOIN asg g ON g.layer = h.layer AND g.c = h.c JOIN sig b ON b.id = g.id WHERE a.verdict <> b.verdict) WHERE rank <= {k})"""


def pairs(source: str, k: int) -> str:
    """``pr(a, b, rank, sim)`` from a relation (v, u, sim)."""
    return f"""pr AS MATERIALIZED (SELECT a, b, row_number() OVER (ORDER BY sim DESC, a, b)::INT AS rank, sim FROM (SELECT DISTINCT least(v, u) AS a, greatest(v, u) AS b, sim FROM {source}) ORDER BY rank LIMIT {k})"""
