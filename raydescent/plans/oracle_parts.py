"""Pieces of DuckDB SQL that several oracles share."""

from __future__ import annotations


def h(key: str, factor: int = 48271) -> str:
    return f"((({key}) % 2147483647) * {factor} % 2147483647)"


def shard(key: str, k: int) -> str:
    return f"({h(h(key), 69621)} % {k})"


def split(key: str) -> str:
    x = f"({h(h(h(key), 69621))} % 5)"
    return f"(CASE WHEN {x} = 0 THEN 'test' WHEN {x} = 1 THEN 'valid' ELSE 'train' END)"


def uniform(key: str) -> str:
    return f"(({h(key)} + 0.5) / 2147483647.0)"


def sign(a: str, b: str) -> str:
    return f"(1 - 2 * (bit_count((({a}) & ({b}))::BIGINT)::INT % 2))"


def sign_table(t: int) -> str:
    return f"SELECT a.i::INT AS alpha, b.i::INT AS beta, {sign('a.i', 'b.i')}::INT AS sign FROM range({t}) a(i), range({t}) b(i)"


def code(k: int, t: int, n: int | None = None) -> str:
    """lane, theta, sign of the power-of-two code in block form: systematic blocks first, then halves on neighbouring blocks."""
    n = 2 * k if n is None else n
    s, half = k // t, t // 2
    return f"""
SELECT lane::INT AS lane, theta::INT AS theta, sign::INT AS sign FROM (
  SELECT b.i * {t} + x.alpha AS lane, b.i * {t} + x.beta AS theta, x.sign FROM range({s}) b(i), ({sign_table(t)}) x
  UNION ALL
  SELECT {k} + b.i * {t} + x.alpha, b.i * {t} + {half} + x.beta, x.sign FROM range({s}) b(i), ({sign_table(t)}) x WHERE x.beta < {half}
  UNION ALL
  SELECT {k} + b.i * {t} + x.alpha, ((b.i + 1) % {s}) * {t} + x.beta - {half}, x.sign FROM range({s}) b(i), ({sign_table(t)}) x WHERE x.beta >= {half})
WHERE lane < {n}"""


def softmax_gradient(examples: str, v: int, weights: str, mse: bool = False) -> str:
    """part_id, out_unit, in_unit, g, n from examples (row_key, part_id, x with bias, y) and weights (out_unit, in_unit, w).

    The long form: scores by row and class, probabilities, then products of errors and inputs.
    """
    error = "p - hot" if not mse else "p * ((p - hot) - s)"
    extra = "" if not mse else ", sum(p * (p - hot)) OVER (PARTITION BY rid) AS s"
    return f"""
ex AS MATERIALIZED (SELECT row_number() OVER () AS rid, * FROM ({examples})),
cell AS (SELECT rid, part_id, y, unnest(range(len(x))) AS in_unit, unnest(x) AS xv FROM ex),
score AS (SELECT c.rid, c.part_id, c.y, w.out_unit, sum(c.xv * w.w) AS z FROM cell c JOIN ({weights}) w USING (in_unit) GROUP BY ALL),
soft AS (SELECT rid, part_id, out_unit, (y = out_unit)::INT AS hot, exp(z - max(z) OVER (PARTITION BY rid)) AS e FROM score),
prob AS (SELECT rid, part_id, out_unit, hot, e / sum(e) OVER (PARTITION BY rid) AS p FROM soft),
err AS (SELECT rid, part_id, out_unit, {error} AS d FROM (SELECT *{extra} FROM prob)),
grad AS (SELECT e.part_id, e.out_unit, c.in_unit, sum(e.d * c.xv) AS g FROM err e JOIN cell c USING (rid) GROUP BY ALL)"""


def test_weights(v: int, inputs: int) -> str:
    """Fixed small weights for one-step oracles: out_unit, in_unit, w (the last in_unit is the bias)."""
    return f"SELECT o.i AS out_unit, c.i AS in_unit, ((o.i * 31 + c.i * 17 + 7) * 48271 % 1000 - 500) / 5000.0 AS w FROM range({v}) o(i), range({inputs + 1}) c(i)"


def embedding_examples(k: int, delta: float = 0.0) -> str:
    x = "embedding[j + 1]::DOUBLE" + (f" + {delta} * {sign('label + 1', 'j')} / 8.0" if delta else "")
    return f"""SELECT vec_id AS row_key, {shard('vec_id', k)} AS part_id, {split('vec_id')} AS split, list_append(list_transform(range(64), lambda j: {x}), 1.0) AS x, label AS y FROM embeddings"""


LINE_X = """[(l_quantity - 25.0) / 15.0, (l_extendedprice - 53000.0) / 30000.0, (l_discount - 0.05) / 0.03, (l_tax - 0.04) / 0.03,
 sin(month(l_shipdate) * (2 * pi() / 12)), cos(month(l_shipdate) * (2 * pi() / 12))]"""


def lineitem_examples(k: int, real: bool = False) -> str:
    key = "(l_orderkey * 8 + l_linenumber)"
    if real:
        y = "(CASE l_returnflag WHEN 'A' THEN 0 WHEN 'N' THEN 1 ELSE 2 END) * 2 + (CASE l_linestatus WHEN 'F' THEN 0 ELSE 1 END)"
    else:
        score = f"(f[1] + f[2] - f[3] + 0.5 * f[4] + 0.5 * (({h(h(key + ' + 31'))} % 1000) / 1000.0 - 0.5))"
        y = f"CASE WHEN {score} < -1 THEN 0 WHEN {score} < 0 THEN 1 WHEN {score} < 1 THEN 2 ELSE 3 END"
    return f"SELECT {key} AS row_key, {shard(key, k)} AS part_id, {split(key)} AS split, list_append(f, 1.0) AS x, {y} AS y FROM (SELECT *, {LINE_X} AS f FROM lineitem)"


def priority_examples(k: int) -> str:
    region = ", ".join(f"(n_regionkey = {r})::INT::DOUBLE" for r in range(5))
    return f"""SELECT o_orderkey AS row_key, {shard('o_orderkey', k)} AS part_id, {split('o_orderkey')} AS split,
 [(o_totalprice - 250000) / 144000, (c_acctbal - 4500) / 3000, (month(o_orderdate) - 6.5) / 3.5, {region}, 1.0] AS x, o_orderpriority[1]::INT - 1 AS y
FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey"""


def regression_examples(k: int) -> str:
    key = "(l_orderkey * 8 + l_linenumber)"
    return f"""SELECT row_key, {shard('row_key', k)} AS part_id, {split('row_key')} AS split, list_append(f, 1.0) AS x, 2 * f[1] - f[2] + 0.5 * f[3] + ({h('row_key + 31')} % 1000) / 1000.0 - 0.5 AS y
FROM (SELECT {key} AS row_key, [(l_quantity - 25) / 15, (p_retailprice - 950) / 50, (l_discount - 0.05) / 0.03] AS f FROM lineitem JOIN part ON l_partkey = p_partkey)"""


def event_examples(k: int) -> str:
    return f"""SELECT event_id AS row_key, {shard('event_id', k)} AS part_id, {split('event_id')} AS split,
 [value / 50 - 1, sin(hour(ts) * (2 * pi() / 24)), cos(hour(ts) * (2 * pi() / 24)), n / 50.0 - 1, 1.0] AS x, CASE WHEN q < 0.75 THEN 0 WHEN q < 1.5 THEN 1 WHEN q < 2.5 THEN 2 ELSE 3 END AS y
FROM (SELECT *, value / 50 + n / 50.0 AS q FROM (SELECT *, (props->>'$.k')::INT AS n FROM events))"""


def conversation_examples(k: int) -> str:
    key = "(conv_id * 64 + turn)"
    return f"""SELECT {key} AS row_key, {shard(key, k)} AS part_id, {split(key)} AS split,
 [ln(1 + length(t)) - 5, least(length(t) - length(replace(t, '?', '')), 5) / 5.0, length(t) / greatest(len(string_split(t, ' ')), 1) / 10.0 - 0.5, 1.0] AS x,
 CASE role WHEN 'system' THEN 0 WHEN 'user' THEN 1 ELSE 2 END AS y
FROM (SELECT *, coalesce(text, '') AS t FROM conversations WHERE role IN ('system', 'user', 'assistant'))"""


def page_examples(k: int) -> str:
    return f"""SELECT page_id AS row_key, {shard('page_id', k)} AS part_id, {split('page_id')} AS split,
 [ln(1 + len(regexp_extract_all(h, '<[a-z]'))) - 3, ln(1 + len(regexp_extract_all(h, '<a '))) - 1.5, ln(size) - 7, 1.0] AS x,
 CASE WHEN bare / size < 0.4 THEN 0 WHEN bare / size < 0.6 THEN 1 WHEN bare / size < 0.8 THEN 2 ELSE 3 END AS y
FROM (SELECT *, greatest(length(h), 1) AS size, length(regexp_replace(h, '<[^>]*>', '', 'g')) AS bare FROM (SELECT page_id, coalesce(html, '') AS h FROM pages))"""
