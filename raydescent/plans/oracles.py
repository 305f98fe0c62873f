"""DuckDB SQL for the queries of catalog.py, by the same names. Written from the definitions, not from the operators:
codes in block form, gradients in long form, descent as chained tables."""

from __future__ import annotations

import math
from itertools import permutations

from raydescent.operators.arrivals import Delays, arrival_schedule
from raydescent.plans import oracle_parts as part

ORACLES: dict[str, str] = {}
SEED = 5


def tidy(c: str, digits: int = 6) -> str:
    return f"round({c}, {digits}) + 0.0"


def lineitem_shards(k: int) -> str:
    return f"SELECT {part.shard('l_orderkey * 8 + l_linenumber', k)} AS theta, count(*) AS rows FROM lineitem GROUP BY 1"


def row_signs(t: int) -> str:
    """The signs of t lanes for the rows of each shard of lineitem."""
    return f"SELECT a.i::INT AS alpha, theta::INT AS beta, {part.sign('a.i', 'theta')}::INT AS sign, ({part.sign('a.i', 'theta')} * rows)::BIGINT AS signed_rows FROM range({t}) a(i), ({lineitem_shards(t)}) WHERE theta IS NOT NULL"


ORACLES["char_table_t8"] = part.sign_table(8)
for _t in (2, 4, 16):
    ORACLES[f"char_table_t{_t}"] = row_signs(_t)
ORACLES["char_kron_equals_direct"] = row_signs(8)
ORACLES["char_gram_is_identity"] = f"SELECT a.i::INT AS alpha_a, theta::INT AS alpha_b, CASE WHEN a.i = theta THEN 8 * rows ELSE 0 END::BIGINT AS product FROM range(8) a(i), ({lineitem_shards(8)}) WHERE a.i <= theta"
ORACLES["code_base_4x2"] = "SELECT lane::INT AS lane, theta::INT AS theta, sign::INT AS sign, round(scale, 6) AS scale FROM (VALUES (0, 0, 1, 1.0::DOUBLE), (1, 1, 1, 1.0), (2, 0, 1, sqrt(0.5)), (2, 1, 1, sqrt(0.5)), (3, 0, 1, sqrt(0.5)), (3, 1, -1, sqrt(0.5))) v(lane, theta, sign, scale)"
#: The non-zeros of the code of eight lanes, four shards and weight two.
ORACLES["code_8_4_2"] = """SELECT lane::INT AS lane, theta::INT AS theta, sign::INT AS sign FROM (VALUES
(0, 0, 1), (0, 1, 1), (1, 0, 1), (1, 1, -1), (2, 2, 1), (2, 3, 1), (3, 2, 1), (3, 3, -1),
(4, 1, 1), (4, 2, 1), (5, 1, 1), (5, 2, -1), (6, 3, 1), (6, 0, 1), (7, 3, 1), (7, 0, -1)) v(lane, theta, sign)"""
ORACLES["code_16_8_4"] = part.code(8, 4)
ORACLES["code_32_16_8"] = part.code(16, 8)
ORACLES["code_12_8_2"] = part.code(8, 2, 12)
ORACLES["code_parity_parts"] = f"SELECT CASE WHEN beta < 4 THEN 'L' ELSE 'R' END AS side, alpha AS \"row\", (beta % 4)::INT AS col, sign FROM ({part.sign_table(8)})"
ORACLES["code_tight_frame"] = "SELECT i::INT AS theta_a, i::INT AS theta_b, 16::BIGINT AS product FROM range(16) r(i)"
ORACLES["code_row_weights"] = "SELECT i::INT AS lane, 4::BIGINT AS weight FROM range(32) r(i)"
ORACLES["code_col_weights"] = "SELECT i::INT AS theta, 8::BIGINT AS weight FROM range(16) r(i)"
ORACLES["weight_distribution_base"] = "SELECT * FROM (VALUES (1::BIGINT, 2::BIGINT), (2, 2)) v(weight, how_many)"
ORACLES["mds_code_8_4"] = f"SELECT a.i::INT AS lane, b.i::INT AS theta, {tidy('pow(cos((2 * a.i + 1) * pi() / 16), b.i)')} AS coef FROM range(8) a(i), range(4) b(i)"
ORACLES["replication_code"] = "SELECT i::INT AS lane, (i % 4)::INT AS theta, 1::INT AS sign FROM range(12) r(i)"
_cell = f"SELECT a.i AS lane, b.i AS theta, {part.h(part.h('a.i * 8 + b.i + 1 + 3 * 1000003'), 69621)} AS h FROM range(16) a(i), range(8) b(i)"
ORACLES["random_sign_code"] = f"SELECT lane::INT AS lane, theta::INT AS theta, (1 - 2 * (h // 7 % 2))::INT AS sign FROM (SELECT *, row_number() OVER (PARTITION BY lane ORDER BY h, theta) AS r FROM ({_cell})) WHERE r <= 4"


def profile(k: int, t: int) -> str:
    """absolute product and pairs over all pairs of lanes, with the pairs that share nothing."""
    return f"""SELECT abs(product)::BIGINT AS product, count(*)::BIGINT AS pairs FROM (
  SELECT a.lane, b.lane, sum(CASE WHEN x.theta = y.theta THEN x.sign * y.sign ELSE 0 END) AS product
  FROM range({2 * k}) a(lane) JOIN range({2 * k}) b(lane) ON a.lane < b.lane JOIN c x ON x.lane = a.lane JOIN c y ON y.lane = b.lane GROUP BY ALL) GROUP BY 1"""


def row_profile(n: int, k: int, t: int) -> str:
    """The angles of all pairs of lanes as vectors over the rows of lineitem: a lane's sign on the rows of its shards, 0 elsewhere."""
    return f"""WITH v AS (SELECT lane, theta, sign, rows FROM ({part.code(k, t, n)}) JOIN ({lineitem_shards(k)}) USING (theta)),
 l AS (SELECT i AS lane, coalesce(sum(rows), 0) AS length FROM range({n}) r(i) LEFT JOIN v ON lane = i GROUP BY i),
 p AS (SELECT a.lane, b.lane, a.length AS la, b.length AS lb, abs(coalesce(sum(x.sign * y.sign * x.rows), 0))::BIGINT AS product
  FROM l a JOIN l b ON a.lane < b.lane LEFT JOIN v x ON x.lane = a.lane LEFT JOIN v y ON y.lane = b.lane AND y.theta = x.theta GROUP BY ALL)
SELECT product, {tidy('CASE WHEN product = 0 THEN pi() / 2 ELSE acos(least(1.0::DOUBLE, product / (sqrt(la) * sqrt(lb)))) END')} AS angle, count(*)::BIGINT AS pairs FROM p GROUP BY 1, 2"""


for _n, _k, _t in ((8, 4, 2), (16, 8, 4), (64, 32, 8)):
    ORACLES[f"angle_profile_{_n}_{_k}_{_t}"] = row_profile(_n, _k, _t)
ORACLES["neighbour_counts"] = "SELECT i::INT AS lane, 4::BIGINT AS neighbours FROM range(32) r(i)"
ORACLES["optimality_gap"] = f"SELECT {tidy('pi() / 3')} AS least_angle, {tidy('pi() / 6')} AS abs_gap, {tidy('1.0::DOUBLE / 3')} AS rel_gap, {tidy('2.0::DOUBLE / 3')} AS fraction_of_ideal"
ORACLES["pair_information"] = f"WITH c AS ({part.code(8, 4)}), p AS ({profile(8, 4)}) SELECT product, pairs, {tidy('-0.5 * ln(1 - (product / 4.0) * (product / 4.0))')} AS nats FROM p"
ORACLES["replication_factor"] = "SELECT 128::BIGINT AS copies, 16::BIGINT AS shards, 8.0::DOUBLE AS factor"
#: Lane subsets of the code of eight lanes by size, those of full rank, and those that give the sum.
ORACLES["subset_rank_8_4_2"] = """SELECT size::INT AS size, subsets::BIGINT AS subsets, full_rank::BIGINT AS full_rank, sum_recoverable::BIGINT AS sum_recoverable FROM (VALUES
(1, 8, 0, 0), (2, 28, 0, 2), (3, 56, 0, 16), (4, 70, 58, 61), (5, 56, 56, 56), (6, 28, 28, 28), (7, 8, 8, 8), (8, 1, 1, 1)) v(size, subsets, full_rank, sum_recoverable)"""
_sizes = [(8, 4, 2), (16, 8, 2), (16, 8, 4), (32, 16, 2), (32, 16, 4), (32, 16, 8), (64, 32, 8), (128, 64, 16)]


def determinant(size: int) -> str:
    """Of the matrix g_ij (i < j; symmetric, ones on the diagonal), by permutations."""
    terms = []
    for order in permutations(range(size)):
        turns = sum(order[i] > order[j] for i in range(size) for j in range(i + 1, size))
        factors = [f"g{min(i, j)}{max(i, j)}" for i, j in enumerate(order) if i != j]
        terms.append(f"{'-' if turns % 2 else '+'} {' * '.join(factors) or '1.0'}")
    return " ".join(terms)


def entropies(size: int) -> str:
    """Mean half logarithm of the Gram determinant over all lane subsets of a size of the code of eight lanes, singular ones left out."""
    pairs = [(i, j) for i in range(size) for j in range(i + 1, size)]
    lanes = f"range(8) a0(i0) {' '.join(f'JOIN range(8) a{j}(i{j}) ON i{j - 1} < i{j}' for j in range(1, size))}"
    grams = " ".join(f"JOIN gram g_{i}{j} ON g_{i}{j}.a = i{i} AND g_{i}{j}.b = i{j}" for i, j in pairs)
    named = ", ".join(["1 AS one", *(f"g_{i}{j}.v AS g{i}{j}" for i, j in pairs)])
    return f"SELECT {size}::INT AS size, {tidy('avg(0.5 * ln(d))')} AS mean_entropy FROM (SELECT {determinant(size)} AS d FROM (SELECT {named} FROM {lanes} {grams})) WHERE d > 1e-9"


ORACLES["subset_entropy_8_4_2"] = f"""WITH c AS ({part.code(4, 2)}), gram AS (SELECT x.i AS a, y.i AS b, coalesce(sum(p.sign * q.sign) / 2.0, 0.0)::DOUBLE AS v
 FROM range(8) x(i) JOIN range(8) y(i) ON x.i < y.i LEFT JOIN c p ON p.lane = x.i LEFT JOIN c q ON q.lane = y.i AND q.theta = p.theta GROUP BY ALL)
{' UNION ALL '.join(entropies(m) for m in (1, 2, 3, 4))}"""
ORACLES["code_sweep"] = " UNION ALL ".join(f"SELECT {n}::INT AS n, {k}::INT AS k, {t}::INT AS t, {tidy('pi() / 3')} AS least_angle, 0.5::DOUBLE AS largest_cosine, {tidy(f'sqrt({n - k}.0::DOUBLE / ({k} * {n - 1}))')} AS welch, {2 * n}::BIGINT AS closest_pairs" for n, k, t in _sizes)
ORACLES["degenerate_pair_sweep"] = f"SELECT {tidy('(i + 1) * pi() / 32')} AS eps, 0.0::DOUBLE AS first, {tidy('-sqrt(2.0) * sin((i + 1) * pi() / 32)')} AS second FROM range(16) r(i)"
ORACLES["code_rows_in_sql"] = part.code(8, 4)
ORACLES["ray_angles_in_sql"] = f"""WITH c AS ({part.code(4, 2)}), p AS (SELECT a.lane AS lane_a, b.lane AS lane_b, sum(CASE WHEN x.theta = y.theta THEN x.sign * y.sign ELSE 0 END) AS product
 FROM range(8) a(lane) JOIN range(8) b(lane) ON a.lane < b.lane JOIN c x ON x.lane = a.lane JOIN c y ON y.lane = b.lane GROUP BY ALL)
SELECT lane_a::INT AS lane_a, lane_b::INT AS lane_b, round(acos(abs(product) / 2.0), 6) AS angle FROM p"""
ORACLES["coprime_step_small_k"] = "SELECT k::INT AS k, min(p)::INT AS step FROM (VALUES (2), (3), (4), (5), (6), (7), (8), (30), (210), (2310)) a(k), (VALUES (3), (5), (7), (11), (13), (17), (19), (23), (29), (31)) b(p) WHERE k % p <> 0 GROUP BY k"


def up(x: int) -> int:
    return 1 << (x - 1).bit_length()


def waves(n: int, k: int, t: int, many: int, d: int) -> str:
    rows, cols = up(n), up(k)
    return f"""SELECT w.i::INT AS wave, l.i::INT AS lane, ((l.i + w.i * {d}) % {rows})::INT AS code_row, s.i::INT AS slot, ((s.i + w.i) % {cols})::INT AS code_col, ((s.i + w.i) % {k})::INT AS task, c.sign
FROM range({many}) w(i), range({n}) l(i), range({k}) s(i), ({part.code(cols, t, min(rows, 2 * cols))}) c
WHERE c.lane = (l.i + w.i * {d}) % {rows} % {min(rows, 2 * cols)} AND c.theta = (s.i + w.i) % {cols}"""


for _n, _k, _t, _d in ((5, 3, 2, 5), (12, 6, 2, 5), (13, 7, 2, 3)):
    ORACLES[f"wave_schedule_{_n}_{_k}_{_t}"] = waves(_n, _k, _t, 6, _d)
ORACLES["wave_rows_in_sql"] = waves(5, 3, 2, 6, 5)
for _n, _k, _t, _d in ((5, 3, 2, 5), (6, 3, 2, 5), (12, 6, 2, 5), (12, 5, 2, 3), (13, 7, 2, 3)):
    _rows = up(_n)
    _period = math.lcm(_rows // math.gcd(_rows, _d), up(_k), _k)
    ORACLES[f"wave_coverage_{_n}_{_k}_{_t}"] = f"SELECT {_period}::BIGINT AS period, count(DISTINCT ((i * {_d}) % {_rows}) * 1000 + i % {_k})::BIGINT AS pairs_hit, {_rows * _k}::BIGINT AS pairs_total FROM range({_period}) r(i)"
ORACLES["idle_lanes_12_5_2"] = f"WITH b AS ({waves(12, 5, 2, 80, 3)}) SELECT w.i::INT AS wave, l.i::INT AS lane FROM range(80) w(i), range(12) l(i) WHERE NOT EXISTS (SELECT 1 FROM b WHERE b.wave = w.i AND b.lane = l.i)"
for _k, _t in ((4, 2), (8, 4)):
    ORACLES[f"data_allocation_{2 * _k}_{_k}_{_t}"] = f"SELECT DISTINCT lane, theta AS part_id FROM ({part.code(_k, _t)})"
ORACLES["gradient_allocation_8_4_2"] = f"SELECT lane, theta, (theta % 2)::INT AS \"group\", (theta // 2)::INT AS block, sign FROM ({part.code(4, 2)})"
ORACLES["gradient_allocation_mlp"] = f"""SELECT lane, layer::INT AS layer, (theta % 4)::INT AS "group", (theta // 4)::INT AS block, (theta % 4 * 3)::INT AS first_unit, greatest(0, least(3, v - theta % 4 * 3))::INT AS units, sign
FROM ({part.code(8, 4)}), (VALUES (0, 12), (1, 10)) x(layer, v)"""
ORACLES["gradient_allocation_nested"] = f"""WITH c AS ({part.code(4, 2)}), g AS (SELECT lane, theta % 2 AS g, theta // 2 AS block, sign FROM c)
SELECT a.lane, 0::INT AS layer, (a.g * 2 + b.g)::INT AS "group", a.block::INT AS block, ((a.g * 2 + b.g) * 3)::INT AS first_unit, 3::INT AS units, (a.sign * b.sign)::INT AS sign FROM g a JOIN g b USING (lane)
UNION ALL SELECT lane, 1::INT, g::INT, block::INT, (g * 5)::INT, 5::INT, sign::INT FROM g"""
for _name, _key in (("lineitem", "l_orderkey * 8 + l_linenumber"), ("orders", "o_orderkey"), ("events", "event_id")):
    ORACLES[f"shard_histogram_{_name}"] = f"SELECT {part.shard(_key, 16)}::INT AS part_id, {part.split(_key)} AS split, count(*)::BIGINT AS n FROM {_name} GROUP BY ALL"


def long_gradient(examples: str, v: int, inputs: int, scale: float, mse: bool = False) -> str:
    return f"""WITH {part.softmax_gradient(examples, v, part.test_weights(v, inputs), mse)}
SELECT part_id::INT AS part_id, out_unit::INT AS out_unit, in_unit::INT AS in_unit, {tidy(f'g / {scale}')} AS g FROM grad"""


def single_output_gradient(examples: str, inputs: int, scale: float, error: str) -> str:
    """part_id, out_unit 0, in_unit, g for one output whose error is an expression of z (score) and y."""
    return f"""WITH ex AS MATERIALIZED (SELECT row_number() OVER () AS rid, * FROM ({examples})),
cell AS (SELECT rid, part_id, y, unnest(range(len(x))) AS in_unit, unnest(x) AS xv FROM ex),
score AS (SELECT rid, any_value(y) AS y, sum(xv * w) AS z FROM cell JOIN ({part.test_weights(1, inputs)}) USING (in_unit) GROUP BY rid)
SELECT part_id::INT AS part_id, 0::INT AS out_unit, in_unit::INT AS in_unit, {tidy(f'sum(({error}) * xv) / {scale}')} AS g FROM cell JOIN (SELECT rid, z, y AS yy FROM score) USING (rid) GROUP BY part_id, in_unit"""


ORACLES["shard_gradient_embeddings"] = long_gradient(part.embedding_examples(4), 10, 64, 100.0)
ORACLES["shard_gradient_lineitem"] = long_gradient(part.lineitem_examples(4, real=True), 6, 6, 10000.0)
ORACLES["shard_gradient_orders"] = long_gradient(part.priority_examples(4), 5, 8, 1000.0)
ORACLES["mse_softmax_gradient"] = long_gradient(part.embedding_examples(4), 10, 64, 100.0, mse=True)
ORACLES["softmax_gradient_events"] = long_gradient(part.event_examples(4), 4, 4, 1000.0)
ORACLES["softmax_gradient_conversations"] = long_gradient(part.conversation_examples(4), 3, 3, 100.0)
ORACLES["softmax_gradient_pages"] = long_gradient(part.page_examples(4), 4, 3, 100.0)
ORACLES["mse_gradient_lineitem"] = single_output_gradient(part.regression_examples(4), 3, 10000.0, "z - yy")
ORACLES["logistic_gradient_orders"] = single_output_gradient(f"SELECT * REPLACE ((y = 0)::INT AS y) FROM ({part.priority_examples(4)})", 8, 1000.0, "1 / (1 + exp(-z)) - yy")

# Messages: the gradient cells of the embeddings by group and place, then signed sums

_cells = f"""{part.softmax_gradient(part.embedding_examples(4), 10, part.test_weights(10, 64))},
c AS ({part.code(4, 2)}),
s AS (SELECT lane, theta % 2 AS grp, sign FROM c),
cells AS (SELECT part_id, out_unit // 5 AS grp, out_unit % 5 * 65 + in_unit AS pos, g FROM grad)"""
_support = "SELECT c.lane, cells.pos, sum(s.sign * g) AS value FROM c JOIN cells ON part_id = theta JOIN s ON s.lane = c.lane AND s.grp = cells.grp GROUP BY ALL"
_pure = "SELECT c.lane, cells.pos, sum(c.sign * g) AS value FROM c JOIN cells ON cells.grp = theta % 2 AND part_id // 2 = theta // 2 GROUP BY ALL"
for _mode, _sql in (("support", _support), ("pure", _pure)):
    ORACLES[f"lane_messages_{_mode}_8_4_2"] = f"WITH {_cells}, m AS ({_sql}) SELECT lane, pos::INT AS pos, {tidy('value / 100')} AS value FROM m"
_twice = f"WITH {_cells} SELECT grp::INT AS grp, pos::INT AS pos, {tidy('2 * sum(g) / 100')} AS delta FROM cells GROUP BY grp, pos"
ORACLES["decode_all_lanes_is_twice_gradient"] = _twice
ORACLES["decode_all_lanes_pure"] = _twice
ORACLES["decode_first_k_lanes"] = f"WITH {_cells}, m AS ({_support}) SELECT s.grp::INT AS grp, pos::INT AS pos, {tidy('sum(s.sign * value) / 100')} AS delta FROM m JOIN s USING (lane) WHERE lane < 4 GROUP BY s.grp, pos"
ORACLES["gradient_error_by_subset"] = f"""WITH {_cells}, m AS ({_support}), whole AS (SELECT grp, pos, sum(g) AS b FROM cells GROUP BY ALL),
d AS (SELECT f.i AS lanes, s.grp, pos, sum(s.sign * value / (0.5 * f.i)) AS a FROM range(1, 9) f(i) JOIN m ON m.lane < f.i JOIN s USING (lane) GROUP BY ALL)
SELECT lanes::INT AS lanes, {tidy('sqrt(sum((a - b) * (a - b)) / sum(b * b))')} AS relative_error, {tidy('sum(a * b) / sqrt(sum(a * a) * sum(b * b))')} AS cosine FROM d JOIN whole USING (grp, pos) GROUP BY lanes"""
for _name, _digits in (("xgc_cyclic_recovers_sum", 5), ("xgc_repetition_decode", 6)):
    ORACLES[_name] = f"WITH {part.softmax_gradient(part.embedding_examples(8), 10, part.test_weights(10, 64))} SELECT out_unit::INT AS out_unit, in_unit::INT AS in_unit, {tidy('sum(g) / 100', _digits)} AS g FROM grad GROUP BY out_unit, in_unit"

# Arrivals


def delay(lane: str, job: str) -> str:
    return f"(1 - ln({part.uniform(f'{SEED} * 1000003 + 17 + {lane} * 10007 + {job} * 101')}))"


def sync(n: int, K: int, updates: int) -> str:
    return f"SELECT *, place <= {K} AS taken FROM (SELECT *, row_number() OVER (PARTITION BY update_no ORDER BY arrive_at, lane) AS place FROM (SELECT u.i::BIGINT AS update_no, l.i::INT AS lane, {delay('l.i', 'u.i')} AS arrive_at FROM range({updates}) u(i), range({n}) l(i)))"


def batch(n: int, K: int, updates: int) -> str:
    jobs = f"SELECT l.i::INT AS lane, j.i AS job, {delay('l.i', 'j.i')} AS d FROM range({n}) l(i), range({updates * K + 1}) j(i)"
    clock = f"SELECT lane, job, sum(d) OVER (PARTITION BY lane ORDER BY job) AS arrive_at FROM ({jobs})"
    placed = f"SELECT *, row_number() OVER (ORDER BY arrive_at, lane) - 1 AS seq FROM ({clock})"
    read = f"SELECT *, seq // {K} AS update_no, coalesce((lag(seq) OVER (PARTITION BY lane ORDER BY job) + 1) // {K}, 0) AS read_version FROM ({placed})"
    return f"SELECT * FROM ({read}) WHERE update_no < {updates}"


ORACLES["staleness_hist"] = f"SELECT update_no - read_version AS staleness, count(*)::BIGINT AS messages FROM ({batch(8, 4, 40)}) GROUP BY 1"
ORACLES["wait_profile"] = f"SELECT update_no, {tidy('min(arrive_at)')} AS first_at, {tidy('max(arrive_at)')} AS last_at, {tidy('max(arrive_at) - min(arrive_at)')} AS waited FROM ({sync(8, 4, 20)}) WHERE taken GROUP BY update_no"


def event_jobs(base: int) -> str:
    """Every event as a job that takes so many millionths of a second and a second for 50 of its value."""
    return f"SELECT event_id, {base} + floor(value * 20000)::BIGINT AS took FROM events WHERE event_id IS NOT NULL AND value BETWEEN 0 AND 1e9"


def event_waiting(n: int, K: int, updates: int, base: int = 1000000, solve: int = 0) -> str:
    """Lanes as a sorted list (arrival, lane, version) and the jobs that wait; the first K make an update and start anew on its weights."""
    made = f"least({K}, len(s))"
    return f"""WITH RECURSIVE q AS (SELECT event_id // {K * updates} AS run, list(took ORDER BY event_id, took) AS w FROM ({event_jobs(base)}) GROUP BY 1),
 st(run, u, s, w) AS (
 SELECT run, 0::BIGINT, list_sort(list_transform(range(least({n}, len(w))), lambda l: {{'at': w[l + 1], 'lane': l, 'version': 0::BIGINT}})), w[{n + 1}:] FROM q
 UNION ALL SELECT run, u + 1, list_sort(s[{K + 1}:] || list_transform(range(least({K}, len(w))), lambda i: {{'at': s[{made}].at + {solve} + w[i + 1], 'lane': s[i + 1].lane, 'version': u + 1}})), w[{K + 1}:] FROM st WHERE len(s) > {K} OR len(w) > 0),
 m AS (SELECT run, u, unnest(s[:{K}]) AS x, s[{made}].at + {solve} AS made FROM st)
SELECT run, u AS update_no, x.lane::INT AS lane, x.version AS read_version, x.at / 1e6 AS arrive_at, made / 1e6 AS updated_at FROM m"""


ORACLES["arrival_ksync"] = f"""SELECT *, place <= 4 AS taken FROM (
 SELECT event_id // 8 AS update_no, (event_id % 8)::INT AS lane, took / 1e6 AS arrive_at, row_number() OVER (PARTITION BY event_id // 8 ORDER BY took, event_id % 8) AS place FROM ({event_jobs(1000000)}))"""
ORACLES["arrival_kbatch"] = f"""WITH clock AS (SELECT event_id // 48 AS run, (event_id % 48 % 8)::INT AS lane, event_id % 48 // 8 AS job, took,
  sum(took) OVER (PARTITION BY event_id // 48, event_id % 48 % 8 ORDER BY event_id % 48 // 8, took ROWS UNBOUNDED PRECEDING)::BIGINT AS due FROM ({event_jobs(1000000)})),
 placed AS (SELECT *, row_number() OVER (PARTITION BY run ORDER BY due, lane) - 1 AS seq FROM clock)
SELECT run, seq // 4 AS update_no, lane, coalesce((lag(seq) OVER (PARTITION BY run, lane ORDER BY job, took) + 1) // 4, 0) AS read_version, due / 1e6 AS arrive_at FROM placed"""
ORACLES["arrival_kasync_wait"] = event_waiting(8, 4, 40)
ORACLES["arrival_charged"] = event_waiting(8, 4, 40, 4650000, 500000)
ORACLES["failure_report"] = """SELECT scheme, lost::INT AS lost, (CASE WHEN 8 - lost >= need THEN 8 ELSE 0 END)::INT AS updates, 8 - lost < need AS refused
FROM (VALUES ('coded', 4), ('uncoded', 4), ('exact_6_of_8', 6), ('synchronous', 8)) v(scheme, need), range(5) r(lost)"""
ORACLES["repetition_picks"] = f"SELECT lane, {tidy('arrive_at')} AS arrive_at FROM (SELECT *, row_number() OVER (PARTITION BY lane // 4 ORDER BY arrive_at, lane) AS r FROM ({sync(8, 5, 1)})) WHERE r = 1"
ORACLES["asof_version"] = """WITH p AS (SELECT i AS version, 1704067200.0 + i * 200000.0 AS published_at FROM range(12) r(i)), e AS (SELECT event_id, epoch_us(ts) / 1e6 AS started_at FROM events)
SELECT e.event_id, p.version AS read_version FROM e ASOF LEFT JOIN p ON e.started_at >= p.published_at"""

# Descent in three chained updates on planted embeddings


def coded_message(k: int) -> tuple[str, str]:
    """Tables named once, and the sum over an update's messages of what they add to each weight (given r: lane, version)."""
    return f"c AS ({part.code(k, 2)}), s AS (SELECT lane, theta % 2 AS grp, sign FROM c)", """
 m AS (SELECT r.lane, r.version, g.out_unit % 5 AS u, g.in_unit, sum(s.sign * g.g) AS value FROM r JOIN c USING (lane) JOIN gall g ON g.part_id = c.theta AND g.version = r.version JOIN s ON s.lane = r.lane AND s.grp = g.out_unit // 5 GROUP BY ALL)
 SELECT s.grp * 5 + m.u AS out_unit, in_unit, sum(s.sign * value) AS d FROM m JOIN s USING (lane) GROUP BY ALL"""


def descent(k: int, lr: float, updates: list[list[tuple[int, int]]], setup: str, message: str, share: float) -> str:
    """updates: the (lane, version) of the messages of each update. share: the part of the rows that a message stands for."""
    out = [f"train AS MATERIALIZED (SELECT * FROM ({part.embedding_examples(k, 0.5)}) WHERE split = 'train')", "size AS (SELECT count(*) AS n FROM train)", setup] if setup else [f"train AS MATERIALIZED (SELECT * FROM ({part.embedding_examples(k, 0.5)}) WHERE split = 'train')", "size AS (SELECT count(*) AS n FROM train)"]
    out += ["ex AS MATERIALIZED (SELECT row_number() OVER () AS rid, * FROM train)", "cell AS MATERIALIZED (SELECT rid, part_id, y, unnest(range(len(x))) AS in_unit, unnest(x) AS xv FROM ex)"]
    out.append("w0 AS (SELECT o.i AS out_unit, c.i AS in_unit, 0.0::DOUBLE AS w FROM range(10) o(i), range(65) c(i))")
    for u, messages in enumerate(updates):
        out.append(f"""g{u} AS MATERIALIZED (WITH score AS (SELECT c.rid, c.part_id, c.y, w.out_unit, sum(c.xv * w.w) AS z FROM cell c JOIN w{u} w USING (in_unit) GROUP BY ALL),
 soft AS (SELECT rid, part_id, out_unit, (y = out_unit)::INT AS hot, exp(z - max(z) OVER (PARTITION BY rid)) AS e FROM score),
 err AS (SELECT rid, part_id, out_unit, e / sum(e) OVER (PARTITION BY rid) - hot AS d FROM soft)
 SELECT e.part_id, e.out_unit, c.in_unit, sum(e.d * c.xv) AS g FROM err e JOIN cell c USING (rid) GROUP BY ALL)""")
        rows = ", ".join(f"({lane}, {v})" for lane, v in messages)
        every = " UNION ALL ".join(f"SELECT {v} AS version, * FROM g{v}" for v in range(u + 1))
        out.append(f"""d{u} AS MATERIALIZED (WITH r AS (SELECT * FROM (VALUES {rows}) v(lane, version)), gall AS ({every}),{message})""")
        out.append(f"w{u + 1} AS MATERIALIZED (SELECT out_unit, in_unit, w - {lr} * coalesce(d, 0) / (n * {share} * {len(messages)}) AS w FROM w{u} LEFT JOIN d{u} USING (out_unit, in_unit), size)")
    return f"WITH {', '.join(out)} SELECT out_unit::INT AS out_unit, in_unit::INT AS in_unit, {tidy('w')} AS w FROM w{len(updates)}"


_plan = [[m[:2] for m in u.messages] for u in arrival_schedule(8, 4, 3, "k_batch_async", Delays(seed=SEED))]
ORACLES["coded_descent_3_updates_embeddings"] = descent(4, 4.0, _plan, *coded_message(4), 0.5)
ORACLES["kasync_3_updates"] = descent(4, 4.0, _plan, f"c AS ({part.code(4, 2)})", " x AS (SELECT 1) SELECT g.out_unit, g.in_unit, sum(g.g) AS d FROM r JOIN c USING (lane) JOIN gall g ON g.part_id = c.theta AND g.version = r.version GROUP BY ALL", 0.5)
_wait = [[m[:2] for m in u.messages] for u in arrival_schedule(8, 4, 3, "k_async_wait", Delays(seed=SEED))]
ORACLES["coded_wait_3_updates"] = descent(4, 4.0, _wait, *coded_message(4), 0.5)
_all = " x AS (SELECT 1) SELECT g.out_unit, g.in_unit, sum(g.g) AS d FROM r JOIN gall g ON g.version = r.version GROUP BY ALL"
ORACLES["sync_3_updates"] = descent(4, 4.0, [[(0, u)] for u in range(3)], "", _all, 1.0)
ORACLES["exact_3_updates"] = descent(8, 4.0, [[(0, u)] for u in range(3)], "", _all, 1.0)
ORACLES["repetition_3_updates"] = ORACLES["exact_3_updates"]
_lanes = ", ".join(f"({m[0]})" for m in arrival_schedule(8, 4, 1, "k_async_wait", Delays(seed=SEED))[0].messages)
ORACLES["regression_step_by_inputs"] = f"""WITH ex AS MATERIALIZED (SELECT row_number() OVER () AS rid, * FROM ({part.regression_examples(4)}) WHERE split = 'train'),
g AS (SELECT part_id, in_unit, sum(-y * xv) AS g FROM (SELECT part_id, y, unnest(range(len(x))) AS in_unit, unnest(x) AS xv FROM ex) GROUP BY ALL),
c AS ({part.code(4, 2)}), s AS (SELECT lane, theta % 2 AS grp, sign FROM c), r AS (SELECT * FROM (VALUES {_lanes}) v(lane)),
m AS (SELECT r.lane, in_unit % 2 AS pos, sum(s.sign * g) AS value FROM r JOIN c USING (lane) JOIN g ON part_id = theta JOIN s ON s.lane = r.lane AND s.grp = in_unit // 2 GROUP BY ALL),
d AS (SELECT s.grp * 2 + pos AS in_unit, sum(s.sign * value) AS d FROM m JOIN s USING (lane) GROUP BY ALL)
SELECT 0::INT AS out_unit, in_unit::INT AS in_unit, {tidy('-0.3 * d / ((SELECT count(*) FROM ex) * 0.5 * 4)')} AS w FROM d"""
ORACLES["decode_padded_groups"] = f"""WITH {part.softmax_gradient(part.priority_examples(4), 5, part.test_weights(5, 8))},
c AS ({part.code(4, 2)}), s AS (SELECT lane, theta % 2 AS grp, sign FROM c),
m AS (SELECT c.lane, out_unit % 3 * 9 + in_unit AS pos, sum(s.sign * g) AS value FROM c JOIN grad ON part_id = theta JOIN s ON s.lane = c.lane AND s.grp = out_unit // 3 WHERE c.lane < 5 GROUP BY ALL)
SELECT s.grp::INT AS grp, pos::INT AS pos, {tidy('sum(s.sign * value) / 1000')} AS delta FROM m JOIN s USING (lane) GROUP BY s.grp, pos"""
ORACLES["relu_gradient_lineitem"] = f"""WITH ex AS MATERIALIZED (SELECT row_number() OVER () AS rid, * FROM ({part.lineitem_examples(4)})),
cell AS MATERIALIZED (SELECT rid, part_id, y, unnest(range(len(x))) AS in_unit, unnest(x) AS xv FROM ex),
w1 AS ({part.test_weights(4, 6)}), w2 AS ({part.test_weights(4, 4)}),
hid AS MATERIALIZED (SELECT rid, out_unit AS unit, sum(xv * w) AS z FROM cell JOIN w1 USING (in_unit) GROUP BY ALL),
act AS (SELECT rid, unit, greatest(z, 0) AS a FROM hid UNION ALL SELECT rid, 4, 1.0 FROM ex),
score AS (SELECT rid, out_unit, sum(a * w) AS z FROM act JOIN w2 ON in_unit = unit GROUP BY ALL),
soft AS (SELECT rid, out_unit, exp(z - max(z) OVER (PARTITION BY rid)) AS e FROM score),
err AS MATERIALIZED (SELECT rid, part_id, out_unit, e / sum(e) OVER (PARTITION BY rid) - (y = out_unit)::INT AS d FROM soft JOIN ex USING (rid)),
back AS (SELECT rid, part_id, unit, sum(d * w) * any_value((z > 0)::INT) AS d FROM err JOIN w2 USING (out_unit) JOIN hid USING (rid) WHERE in_unit = unit GROUP BY rid, part_id, unit)
SELECT part_id::INT AS part_id, 1::INT AS layer, out_unit::INT AS out_unit, unit::INT AS in_unit, {tidy('sum(d * a) / 10000')} AS g FROM err JOIN act USING (rid) GROUP BY part_id, out_unit, unit
UNION ALL SELECT back.part_id::INT, 0::INT, unit::INT, in_unit::INT, {tidy('sum(d * xv) / 10000')} FROM back JOIN cell USING (rid) GROUP BY back.part_id, unit, in_unit"""
ORACLES["own_kernel_gradient"] = single_output_gradient(part.regression_examples(4), 3, 10000.0, "greatest(-1, least(1, z - yy))")
_events = f"SELECT * REPLACE (epoch_us(ts) // {6 * 3600 * 10**6} AS part_id) FROM (SELECT e.*, ts FROM ({part.event_examples(4)}) e JOIN events ON row_key = event_id)"
ORACLES["events_tumbling_gradient"] = f"WITH {part.softmax_gradient(_events, 4, part.test_weights(4, 4))} SELECT part_id::INT AS \"window\", out_unit::INT AS out_unit, in_unit::INT AS in_unit, {tidy('g / 100.0')} AS g FROM grad"
_words = "list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^a-zà-ÿ0-9]+'), lambda w: w <> '')"
_seven = [f"lead(w, {i}) OVER o" for i in range(1, 8)]
_run = f"SELECT id, concat_ws(' ', w, {', '.join(_seven)}) AS run, {_seven[-1]} AS last"


def runs(key: str, table: str) -> str:
    """id and every eight words in a row of the texts of a table."""
    spread = f"SELECT {key} AS id, unnest(w) AS w, generate_subscripts(w, 1) AS i FROM (SELECT {key}, {_words} AS w FROM {table})"
    return f"SELECT id, run FROM ({_run} FROM ({spread}) WINDOW o AS (PARTITION BY id ORDER BY i)) WHERE last IS NOT NULL"


ORACLES["benchmark_overlap_anti"] = f"""SELECT doc_id FROM documents JOIN labels USING (doc_id) WHERE quality IS NOT NULL AND doc_id NOT IN (
 SELECT id FROM ({runs('doc_id', 'documents')}) WHERE run IN (SELECT run FROM ({runs('item_id', 'benchmark')})))"""
ORACLES["doc_dedup_split"] = "SELECT sha256(coalesce(text, '')) AS text_sha256, count(*)::BIGINT AS copies, 1::BIGINT AS splits, 1::BIGINT AS shards FROM documents JOIN labels USING (doc_id) GROUP BY 1 HAVING count(*) > 1"
_documents = f"""SELECT row_key, {part.shard('row_key', 4)} AS part_id, list_append(list_transform(range(32), lambda j: sqrt(len(list_filter(slots, lambda s: s = j)) / n)), 1.0) AS x, quality AS y
FROM (SELECT quality, ('0x' || substr(md5(coalesce(text, '')), 1, 8))::BIGINT AS row_key, list_transform(w, lambda v: ('0x' || substr(md5(v), 1, 8))::BIGINT % 32) AS slots, greatest(len(w), 1) AS n
 FROM (SELECT doc_id, quality, text, {_words} AS w FROM documents JOIN labels USING (doc_id)) WHERE doc_id IN ({ORACLES['benchmark_overlap_anti']}))"""
ORACLES["logistic_gradient_documents"] = single_output_gradient(_documents, 32, 10.0, "1 / (1 + exp(-z)) - yy")
ORACLES["stateful_master_steps"] = f"SELECT lane, (update_no + (seq % 4 = 3)::INT)::BIGINT AS version, (update_no - read_version)::BIGINT AS staleness, CASE WHEN seq % 4 = 3 THEN 'step' ELSE 'held' END AS outcome FROM ({batch(8, 4, 10)})"
ORACLES["stream_notice_join"] = "SELECT l::INT AS lane, v AS version FROM range(6) a(l), range(3) b(v) WHERE 5 * l - 10 * v BETWEEN 0 AND 10"
ORACLES["formats_round_trip"] = "SELECT format, count(*)::BIGINT AS n, sum(n_nationkey)::BIGINT AS keys, max(n_name) AS last_name FROM nation, (VALUES ('json'), ('csv'), ('orc'), ('parquet')) v(format) GROUP BY format"
_curve = "SELECT 'run_' || r AS run_id, 'coded' AS scheme, u AS update_no, 1.5 * u + r AS virtual_time, 2.0 / (u + 1) AS train_loss, CASE WHEN r < 2 THEN round(2.0 - 0.3 * u + (0.02 + 0.01 * r) * u * u + 0.1 * (r * u % 3), 6) END AS test_loss, 100 * u * (r + 1) AS floats_sent FROM range(3) a(r), range(12) b(u)"
ORACLES["curve_measures"] = f"""WITH k AS MATERIALIZED ({_curve}), o AS (SELECT *, test_loss > min(test_loss) OVER w AND coalesce(train_loss < lag(train_loss) OVER (PARTITION BY run_id ORDER BY update_no), false) AS over_, avg(test_loss) OVER (PARTITION BY run_id ORDER BY update_no ROWS 2 PRECEDING) AS smooth FROM k WINDOW w AS (PARTITION BY run_id ORDER BY update_no ROWS UNBOUNDED PRECEDING))
SELECT run_id, scheme, min(update_no) FILTER (test_loss <= 1.05)::BIGINT AS update_no, {tidy('min(virtual_time) FILTER (test_loss <= 1.05)::DOUBLE')} AS virtual_time, min(floats_sent) FILTER (test_loss <= 1.05)::BIGINT AS floats_sent, sum(over_::BIGINT)::BIGINT AS overfit_points, {tidy('arg_max(smooth, update_no)::DOUBLE')} AS last_smooth FROM o GROUP BY run_id, scheme"""

# Measures

_given = "(VALUES " + ", ".join(map(str, _sizes[:6])) + ") v(n, k, t)"
_costs = f"""SELECT 'coded' AS scheme, n, k, t, t AS weight, 0 AS encode_mults, -(-650 // t) AS floats_per_message, t AS decode_adds, 0.0 AS decode_mults, n * t / k AS copies, true AS asynchronous, true AS compresses FROM {_given}
UNION ALL SELECT 'exact', n, k, t, n - k + 1, n * k, 650, 0, pow(k, 2.38), n - k + 1, false, false FROM {_given}
UNION ALL SELECT 'uncoded', n, k, t, t, 0, 650, 1, 0.0, n * t / k, true, false FROM {_given}"""
_costs = _costs.replace("-(-650 // t)", "ceil(650.0 / t)::BIGINT")
ORACLES["cost_table_8_16_32"] = f"SELECT scheme, n::INT AS n, k::INT AS k, t::INT AS t, weight::BIGINT AS weight, encode_mults::BIGINT AS encode_mults, floats_per_message::BIGINT AS floats_per_message, decode_adds::BIGINT AS decode_adds, {tidy('decode_mults::DOUBLE', 3)} AS decode_mults, copies::DOUBLE AS copies, asynchronous, compresses FROM ({_costs})"
ORACLES["communication_rollup"] = f"SELECT scheme, n::INT AS n, sum(floats_per_message * n)::BIGINT AS floats FROM ({_costs}) GROUP BY ROLLUP (scheme, n)"
_scores = f"""ex AS MATERIALIZED (SELECT row_number() OVER () AS rid, * FROM ({part.embedding_examples(4, 0.5)})),
cell AS (SELECT rid, unnest(range(len(x))) AS in_unit, unnest(x) AS xv FROM ex),
score AS (SELECT rid, out_unit, sum(xv * w) AS z FROM cell JOIN ({part.test_weights(10, 64)}) USING (in_unit) GROUP BY ALL),
judged AS (SELECT rid, arg_max(out_unit, z) AS guess, max(z) + ln(sum(exp(z))) - max(z) AS lse FROM score GROUP BY rid),
lossy AS (SELECT ex.split, ex.part_id, lse - z AS loss, (guess <> y)::INT AS wrong FROM ex JOIN judged USING (rid) JOIN score ON score.rid = ex.rid AND score.out_unit = ex.y)"""
ORACLES["test_loss_at_w0"] = f"WITH {_scores} SELECT split, count(*)::BIGINT AS n_rows, {tidy('avg(loss)')} AS loss, {tidy('avg(wrong)')} AS error FROM lossy GROUP BY split"
ORACLES["lane_loss"] = f"WITH {_scores}, c AS ({part.code(4, 2)}) SELECT lane, count(*)::BIGINT AS n_rows, {tidy('avg(loss)')} AS loss FROM lossy JOIN c ON part_id = theta WHERE split = 'train' GROUP BY lane"
ORACLES["confusion_matrix"] = f"""WITH ex AS MATERIALIZED (SELECT row_number() OVER () AS rid, * FROM ({part.lineitem_examples(4)})),
score AS (SELECT rid, y, out_unit, list_sum(list_transform(range(7), lambda j: x[j + 1] * ((out_unit * 31 + j * 17 + 7) * 48271 % 1000 - 500) / 5000.0)) AS z FROM ex, range(4) o(out_unit))
SELECT y::INT AS y, guess::INT AS predicted, count(*)::BIGINT AS n FROM (SELECT rid, any_value(y) AS y, arg_max(out_unit, z) AS guess FROM score GROUP BY rid) GROUP BY ALL"""
_u1, _u2 = part.uniform("b + 1"), part.uniform(part.h("b + 2", 69621))
ORACLES["mixture_moments"] = f"""WITH r AS (SELECT i AS key, {part.h(part.h('i + 7919'), 16807)} % 8 AS comp FROM range(3200) r(i)),
x AS (SELECT comp % 4 AS y, j, {part.sign('comp + 1', 'j')} * 2.0 / 4.0 AS centre, (key * 6 + j) * 2 + 1000003 AS b FROM r, range(6) c(j)),
v AS (SELECT y, j, centre + sqrt(-2 * ln({_u1})) * cos(2 * pi() * {_u2}) AS v FROM x)
SELECT y::INT AS y, j::INT AS j, count(*)::BIGINT AS n, {tidy('avg(v)')} AS mean, {tidy('stddev_pop(v)')} AS spread FROM v GROUP BY y, j"""
ORACLES["mixture_source"] = ORACLES["mixture_moments"]
ORACLES["planted_label_counts_lineitem"] = f"SELECT part_id::INT AS part_id, split, y::INT AS y, count(*)::BIGINT AS n FROM ({part.lineitem_examples(16)}) GROUP BY ALL"
ORACLES["planted_label_counts_events"] = f"""SELECT {part.shard('event_id', 4)}::INT AS part_id, (CASE WHEN q < 0.75 THEN 0 WHEN q < 1.5 THEN 1 WHEN q < 2.5 THEN 2 ELSE 3 END)::INT AS y, count(*)::BIGINT AS n
FROM (SELECT event_id, value / 50 + (props->>'$.k')::INT / 50.0 AS q FROM events) GROUP BY ALL"""
ORACLES["events_tumbling"] = f"SELECT epoch_us(time_bucket(INTERVAL 6 HOURS, ts, TIMESTAMP '1970-01-01')) AS start, event_type, count(*)::BIGINT AS n, {tidy('sum(value)', 3)} AS total FROM events GROUP BY ALL"
ORACLES["events_session"] = """SELECT user_id, epoch_us(min(ts)) AS start, count(*)::BIGINT AS n FROM (
 SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (
  SELECT *, (coalesce(ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) >= INTERVAL 12 HOURS, true))::INT AS fresh FROM events)) GROUP BY user_id, s"""
ORACLES["events_rolling"] = f"SELECT event_id, {tidy('sum(value) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW)', 3)} AS day_value FROM events"

# Relations around the methods

ORACLES["code_matrix_pivot"] = f"SELECT lane, {', '.join(f'coalesce(sum(sign) FILTER (theta = {j}), 0)::INT AS theta_{j}' for j in range(4))} FROM ({part.code(4, 2)}) GROUP BY lane"
ORACLES["common_shards"] = f"WITH c AS ({part.code(8, 4)}) SELECT theta AS part_id FROM c WHERE lane = 0 INTERSECT SELECT theta FROM c WHERE lane = 9"
ORACLES["shards_out_of_reach"] = f"SELECT i::INT AS part_id FROM range(8) r(i) WHERE i NOT IN (SELECT theta FROM ({part.code(8, 4)}) WHERE lane < 5)"
ORACLES["updates_by_arrival"] = f"SELECT seq, lane, seq // 4 AS update_no FROM ({batch(8, 4, 10)})"
ORACLES["cost_grouping_sets"] = f"SELECT scheme, n::INT AS n, sum(floats_per_message)::BIGINT AS floats, max(copies)::DOUBLE AS most_copies FROM ({_costs}) GROUP BY GROUPING SETS ((scheme, n), (scheme), (n), ())"
ORACLES["cost_cube"] = f"SELECT scheme, t::INT AS t, sum(decode_adds)::BIGINT AS adds, count(*)::BIGINT AS rows FROM ({_costs}) GROUP BY CUBE (scheme, t)"
ORACLES["hardest_examples"] = f"""SELECT row_key, part_id, score, dense_rank() OVER (PARTITION BY part_id ORDER BY score DESC) AS place
FROM (SELECT row_key, part_id::INT AS part_id, {tidy('x[2] - x[1]')} AS score FROM ({part.lineitem_examples(4)}) ORDER BY score DESC, row_key LIMIT 10)"""
ORACLES["fastest_lanes"] = f"SELECT update_no, lane, place, {tidy('behind')} AS behind FROM (SELECT *, arrive_at - min(arrive_at) OVER (PARTITION BY update_no) AS behind FROM ({sync(8, 4, 12)})) WHERE place <= 3"
ORACLES["value_quarters"] = "SELECT event_type, quarter, count(*)::BIGINT AS n, min(value) AS low, max(value) AS high FROM (SELECT *, ntile(4) OVER (PARTITION BY event_type ORDER BY value, event_id) AS quarter FROM events) GROUP BY ALL"
ORACLES["schemes_side_by_side"] = f"SELECT update_no, lane, place <= 4 AS four, place <= 6 AS six FROM ({sync(8, 6, 6)}) WHERE place <= 6"
