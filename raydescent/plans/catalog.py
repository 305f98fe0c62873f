"""The registered queries of methods, rivals, measures and workloads. Their SQL is in oracles.py under the same names."""

from __future__ import annotations

import re
import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from raydescent.functions import sql_functions
from raydescent.operators import arrivals, codes, exact_coding, geometry, gradients, lanes, layout, measures, torus, training
from raydescent.plans.models import GroupLayout, NetSpec
from raydescent.plans.params import CodeParams, embed_parameters
from raydescent.session import shared_folder
from raydescent.sources import mixture, workloads
from raydescent.sources.tables import load_table, read_any
from raydescent.streaming import master

QUERIES: dict = {}

P842 = CodeParams(8, 4, 2)
DELAYS = arrivals.Delays(seed=5)
SIZES = [(8, 4, 2), (16, 8, 2), (16, 8, 4), (32, 16, 2), (32, 16, 4), (32, 16, 8)]


def query(f):
    QUERIES[f.__name__] = f
    return f


def add(name: str, f) -> None:
    QUERIES[name] = f


def tidy(c, digits: int = 6):
    """Rounded, and never minus zero."""
    return F.round(c, digits) + 0.0


def micros(name: str):
    """Microseconds of a wall-clock timestamp since 1970, whatever the session's time zone."""
    return F.expr(f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', CAST({name} AS TIMESTAMP_NTZ))")


def fixed_weights(v: int, inputs: int) -> list[np.ndarray]:
    """Small weights for one-step queries."""
    o, i = np.arange(v)[:, None], np.arange(inputs + 1)[None, :]
    return [((o * 31 + i * 17 + 7) * 48271 % 1000 - 500) / 5000.0]


def lineitem_shards(spark: SparkSession, sf_dir: str, k: int) -> DataFrame:
    """part_id, rows: the rows of lineitem in k shards."""
    return layout.rows_by_shard(load_table(spark, sf_dir, "lineitem"), F.expr("l_orderkey * 8 + l_linenumber"), k)


# Codes and their geometry

add("char_table_t8", lambda spark, sf: codes.sign_table(spark, 8))
for _t in (2, 4, 16):
    add(f"char_table_t{_t}", lambda spark, sf, t=_t: codes.row_sign_table(lineitem_shards(spark, sf, t), t))
add("char_kron_equals_direct", lambda spark, sf: codes.row_sign_table_kron(lineitem_shards(spark, sf, 8), 8))
add("char_gram_is_identity", lambda spark, sf: codes.hadamard_report(codes.sign_table(spark, 8), codes.row_sign_table(lineitem_shards(spark, sf, 8), 8).select("beta", "alpha", "signed_rows")))
add("code_base_4x2", lambda spark, sf: codes.identity_parity_code(spark).select("lane", "theta", "sign", tidy("scale").alias("scale")))
for _k, _t, _n in ((4, 2, None), (8, 4, None), (16, 8, None), (8, 2, 12)):
    add(f"code_{_n or 2 * _k}_{_k}_{_t}", lambda spark, sf, k=_k, t=_t, n=_n: codes.projective_code(spark, k, t, n).select("lane", "theta", "sign"))
add("code_parity_parts", lambda spark, sf: codes.parity_parts(spark, 8))
add("code_tight_frame", lambda spark, sf: geometry.frame_operator(codes.projective_code(spark, 16, 8)).select("theta_a", "theta_b", F.col("product").cast("long").alias("product")))
add("code_row_weights", lambda spark, sf: geometry.weights_of(codes.projective_code(spark, 16, 4)))
add("code_col_weights", lambda spark, sf: geometry.weights_of(codes.projective_code(spark, 16, 4), "theta"))
add("weight_distribution_base", lambda spark, sf: geometry.weight_distribution(codes.identity_parity_code(spark)))
add("mds_code_8_4", lambda spark, sf: codes.mds_code(spark, 8, 4).select("lane", "theta", tidy("coef").alias("coef")))
add("replication_code", lambda spark, sf: codes.replication_code(spark, 4, 3).select("lane", "theta", "sign"))
add("random_sign_code", lambda spark, sf: codes.random_sign_code(spark, 16, 8, 4, seed=3).select("lane", "theta", "sign"))
for _n, _k, _t in ((8, 4, 2), (16, 8, 4), (64, 32, 8)):
    add(f"angle_profile_{_n}_{_k}_{_t}", lambda spark, sf, n=_n, k=_k, t=_t: geometry.row_angle_profile(codes.projective_code(spark, k, t), lineitem_shards(spark, sf, k), n))
add("neighbour_counts", lambda spark, sf: geometry.neighbour_counts(codes.projective_code(spark, 16, 4), 4))
add("optimality_gap", lambda spark, sf: geometry.optimality_gap(codes.projective_code(spark, 16, 8), 32, 8).select(*[tidy(c).alias(c) for c in ("least_angle", "abs_gap", "rel_gap", "fraction_of_ideal")]))
add("pair_information", lambda spark, sf: geometry.pair_information(codes.projective_code(spark, 8, 4), 16, 4).select("product", "pairs", tidy("nats").alias("nats")))
add("replication_factor", lambda spark, sf: geometry.replication_factor(codes.projective_code(spark, 16, 4)))
add("subset_rank_8_4_2", lambda spark, sf: geometry.subset_report(spark, P842).select("size", "subsets", "full_rank", "sum_recoverable"))
add("subset_entropy_8_4_2", lambda spark, sf: geometry.subset_report(spark, P842, [1, 2, 3, 4]).select("size", tidy("mean_entropy").alias("mean_entropy")))
add("code_sweep", lambda spark, sf: geometry.code_sweep(spark, [*SIZES, (64, 32, 8), (128, 64, 16)]).select("n", "k", "t", *[tidy(c).alias(c) for c in ("least_angle", "largest_cosine", "welch")], "closest_pairs"))
add("degenerate_pair_sweep", lambda spark, sf: geometry.degenerate_pair(spark).select(*[tidy(c).alias(c) for c in ("eps", "first", "second")]))


@query
def code_rows_in_sql(spark: SparkSession, sf_dir: str) -> DataFrame:
    sql_functions.register(spark)
    return spark.sql("SELECT lane, theta, sign FROM code_rows(8, 4)")


@query
def ray_angles_in_sql(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Angles between the lanes of a code written as vectors, by the SQL function."""
    sql_functions.register(spark)
    codes.projective_code(spark, 4, 2).createOrReplaceTempView("sparse_code")
    dense = "SELECT lane, transform(sequence(0, 3), j -> coalesce(map_from_entries(collect_list(struct(theta, sign * scale)))[j], 0D)) AS v FROM sparse_code GROUP BY lane"
    return spark.sql(f"WITH d AS ({dense}) SELECT a.lane AS lane_a, b.lane AS lane_b, round(ray_angle(a.v, b.v), 6) AS angle FROM d a JOIN d b ON a.lane < b.lane")


# Torus

add("coprime_step_small_k", lambda spark, sf: torus.coprime_steps(spark, [2, 3, 4, 5, 6, 7, 8, 30, 210, 2310]))
for _n, _k, _t, _d in ((5, 3, 2, 5), (12, 6, 2, 5), (13, 7, 2, 3)):
    add(f"wave_schedule_{_n}_{_k}_{_t}", lambda spark, sf, a=(_n, _k, _t), d=_d: torus.wave_schedule(spark, *a, 6, d))
for _n, _k, _t, _d in ((5, 3, 2, 5), (6, 3, 2, 5), (12, 6, 2, 5), (12, 5, 2, 3), (13, 7, 2, 3)):
    add(f"wave_coverage_{_n}_{_k}_{_t}", lambda spark, sf, a=(_n, _k, _t), d=_d: torus.wave_coverage(spark, *a, d))
add("idle_lanes_12_5_2", lambda spark, sf: torus.idle_lanes(spark, 12, 5, 2, 3))


@query
def wave_rows_in_sql(spark: SparkSession, sf_dir: str) -> DataFrame:
    sql_functions.register(spark)
    return spark.sql("SELECT * FROM wave_rows(5, 3, 2, 6)")


# Allocation

add("data_allocation_8_4_2", lambda spark, sf: layout.allocate_shards(codes.projective_code(spark, 4, 2)))
add("data_allocation_16_8_4", lambda spark, sf: layout.allocate_shards(codes.projective_code(spark, 8, 4)))
add("gradient_allocation_8_4_2", lambda spark, sf: layout.allocate_gradient(codes.projective_code(spark, 4, 2), 2))
add("gradient_allocation_mlp", lambda spark, sf: layout.allocate_network(codes.projective_code(spark, 8, 4), [12, 10], 4))
add("gradient_allocation_nested", lambda spark, sf: layout.allocate_network(codes.projective_code(spark, 4, 2), [12, 10], 2, "nested"))
for _name, _key in (("lineitem", "l_orderkey * 8 + l_linenumber"), ("orders", "o_orderkey"), ("events", "event_id")):
    add(f"shard_histogram_{_name}", lambda spark, sf, t=_name, key=_key: load_table(spark, sf, t).select(layout.shard_of(F.expr(key), 16).alias("part_id"), layout.split_of(F.expr(key)).alias("split")).groupBy("part_id", "split").agg(F.count("*").alias("n")))


# Gradients


def long_gradient(examples: DataFrame, spec: NetSpec, scale: float, k: int) -> DataFrame:
    cells = gradients.shard_gradients(examples, {0: fixed_weights(spec.outputs[0], spec.inputs)}, {s: [0] for s in range(k)}, GroupLayout(spec, 1))
    width = spec.inputs + 1
    return cells.select("part_id", F.expr(f"pos div {width}").cast("int").alias("out_unit"), (F.col("pos") % width).cast("int").alias("in_unit"), tidy(F.col("value") / scale).alias("g"))


add("shard_gradient_embeddings", lambda spark, sf: long_gradient(workloads.embedding_examples(spark, sf, 4), NetSpec(64, (10,)), 100, 4))
add("shard_gradient_lineitem", lambda spark, sf: long_gradient(workloads.lineitem_examples(spark, sf, 4, real=True), NetSpec(6, (6,)), 10000, 4))
add("shard_gradient_orders", lambda spark, sf: long_gradient(workloads.priority_examples(spark, sf, 4), NetSpec(8, (5,)), 1000, 4))
add("mse_softmax_gradient", lambda spark, sf: long_gradient(workloads.embedding_examples(spark, sf, 4), NetSpec(64, (10,), "mse_softmax"), 100, 4))
add("mse_gradient_lineitem", lambda spark, sf: long_gradient(workloads.regression_examples(spark, sf, 4), NetSpec(3, (1,), "mse_linear"), 10000, 4))
add("logistic_gradient_orders", lambda spark, sf: long_gradient(workloads.priority_examples(spark, sf, 4).withColumn("y", (F.col("y") == 0).cast("double")), NetSpec(8, (1,), "xent_logistic"), 1000, 4))
add("logistic_gradient_documents", lambda spark, sf: long_gradient(workloads.document_examples(spark, sf, 4), NetSpec(32, (1,), "xent_logistic"), 10, 4))
add("softmax_gradient_conversations", lambda spark, sf: long_gradient(workloads.conversation_examples(spark, sf, 4), NetSpec(3, (3,)), 100, 4))
add("softmax_gradient_pages", lambda spark, sf: long_gradient(workloads.page_examples(spark, sf, 4), NetSpec(3, (4,)), 100, 4))
add("softmax_gradient_events", lambda spark, sf: long_gradient(workloads.event_examples(load_table(spark, sf, "events"), 4), NetSpec(4, (4,)), 1000, 4))


# Messages and decoding

EMB = NetSpec(64, (10,))


def embedding_cells(spark: SparkSession, sf_dir: str, k: int, t: int) -> DataFrame:
    return gradients.shard_gradients(workloads.embedding_examples(spark, sf_dir, k), {0: fixed_weights(10, 64)}, {s: [0] for s in range(k)}, GroupLayout(EMB, t))


def messages_of(spark, sf_dir, params: CodeParams, mode: str, scaling: str = "sign") -> tuple[lanes.Scheme, DataFrame]:
    scheme = lanes.coded_scheme(params, mode, scaling)
    return scheme, lanes.lane_messages(embedding_cells(spark, sf_dir, params.k, params.t), scheme.encode_table(spark))


for _mode in ("support", "pure"):
    add(f"lane_messages_{_mode}_8_4_2", lambda spark, sf, m=_mode: messages_of(spark, sf, P842, m)[1].select("lane", F.col("pos").cast("int").alias("pos"), tidy(F.col("value") / 100).alias("value")))


def decoded(spark, sf_dir, mode: str, scaling: str, first: int | None = None) -> DataFrame:
    scheme, sent = messages_of(spark, sf_dir, P842, mode, scaling)
    some = sent if first is None else sent.where(F.col("lane") < first)
    out = lanes.decode_messages(some, scheme.decode_table(spark))
    return out.select(F.col("group").cast("int").alias("grp"), F.col("pos").cast("int").alias("pos"), tidy(F.col("delta") / 100).alias("delta"))


add("decode_all_lanes_is_twice_gradient", lambda spark, sf: decoded(spark, sf, "support", "unit"))
add("decode_all_lanes_pure", lambda spark, sf: decoded(spark, sf, "pure", "unit"))
add("decode_first_k_lanes", lambda spark, sf: decoded(spark, sf, "support", "sign", 4))


@query
def gradient_error_by_subset(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How near the decoded sum of the first m lanes comes to the gradient, by m. The sum is divided by what m messages are expected to hold."""
    scheme, sent = messages_of(spark, sf_dir, P842, "support")
    whole = embedding_cells(spark, sf_dir, 4, 2).groupBy("group", "pos").agg(F.sum("value").alias("value"))
    out = None
    for m in range(1, 9):
        delta = lanes.decode_messages(sent.where(F.col("lane") < m), scheme.decode_table(spark))
        row = measures.gradient_error(delta, whole, 1 / (scheme.rows_share * m)).select(F.lit(m).alias("lanes"), tidy("relative_error").alias("relative_error"), tidy("cosine").alias("cosine"))
        out = row if out is None else out.union(row)
    return out


@query
def xgc_cyclic_recovers_sum(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The whole gradient from any k of n exactly coded lanes (here the last k)."""
    code = exact_coding.exact_cyclic(8, 5, seed=2)
    scheme, arrived = code.scheme(), [3, 4, 5, 6, 7]
    sent = lanes.lane_messages(embedding_cells(spark, sf_dir, 8, 1), scheme.encode_table(spark))
    solved = spark.createDataFrame([(i, 0, 0, float(c)) for i, c in zip(arrived, code.solve(arrived))], "lane int, slot int, group int, coef double")
    out = lanes.decode_messages(sent, solved)
    return out.select(F.expr("pos div 65").cast("int").alias("out_unit"), (F.col("pos") % 65).cast("int").alias("in_unit"), tidy(F.col("delta") / 100, 5).alias("g"))


@query
def xgc_repetition_decode(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The sum from the first lane of every repetition group."""
    scheme = exact_coding.repetition_scheme(8, 5)
    arrived = arrivals.sync_arrivals(spark, 8, 5, 1, DELAYS).select("lane", "arrive_at")
    picks = exact_coding.repetition_picks(arrived, 8, 5).select("lane")
    sent = lanes.lane_messages(embedding_cells(spark, sf_dir, 8, 1), scheme.encode_table(spark)).join(F.broadcast(picks), "lane")
    out = lanes.decode_messages(sent, scheme.decode_table(spark))
    return out.select(F.expr("pos div 65").cast("int").alias("out_unit"), (F.col("pos") % 65).cast("int").alias("in_unit"), tidy(F.col("delta") / 100).alias("g"))


# Arrivals


def event_jobs(spark: SparkSession, sf_dir: str, delays: arrivals.Delays = arrivals.Delays()) -> DataFrame:
    """Every event as a job."""
    return arrivals.event_jobs(load_table(spark, sf_dir, "events", "event_id", "value"), delays)


add("arrival_ksync", lambda spark, sf: arrivals.event_sync_arrivals(event_jobs(spark, sf), 8, 4).withColumn("place", F.col("place").cast("long")))
add("arrival_kbatch", lambda spark, sf: arrivals.event_batch_arrivals(event_jobs(spark, sf), 8, 4, 12))
add("staleness_hist", lambda spark, sf: arrivals.staleness(arrivals.batch_arrivals(spark, 8, 4, 40, DELAYS)))
add("wait_profile", lambda spark, sf: arrivals.wait_profile(arrivals.sync_arrivals(spark, 8, 4, 20, DELAYS).where("taken")).select("update_no", *[tidy(c).alias(c) for c in ("first_at", "last_at", "waited")]))
add("arrival_kasync_wait", lambda spark, sf: arrivals.event_wait_arrivals(event_jobs(spark, sf), 8, 4, 40))
add("arrival_charged", lambda spark, sf: arrivals.event_wait_arrivals(event_jobs(spark, sf, training.Costs(True, 0.002, 0.0).on(arrivals.Delays(), 4.0, 325)), 8, 4, 40, 0.5))
add("repetition_picks", lambda spark, sf: exact_coding.repetition_picks(arrivals.sync_arrivals(spark, 8, 5, 1, DELAYS).select("lane", "arrive_at"), 8, 5).select("lane", tidy("arrive_at").alias("arrive_at")))


@query
def asof_version(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as messages, orders of magnitude as publications: the newest hourly version at each message's start."""
    events = load_table(spark, sf_dir, "events", "event_id", "ts")
    started = events.select("event_id", (micros("ts") / 1e6).alias("started_at"))
    published = spark.range(12).select(F.col("id").alias("version"), (F.lit(1704067200.0) + F.col("id") * 200000.0).alias("published_at"))
    return measures.read_as_of(started, published).select("event_id", "read_version")


# Descent against chained SQL

STEPS = 3
LR = 4.0


def after_steps(result: training.FitResult, spark: SparkSession) -> DataFrame:
    w = result.weights[0]
    rows = [(o, i, float(round(w[o, i], 6)) + 0.0) for o in range(w.shape[0]) for i in range(w.shape[1])]
    return spark.createDataFrame(rows, "out_unit int, in_unit int, w double")


@query
def coded_descent_3_updates_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    ex = workloads.embedding_examples(spark, sf_dir, 4, 0.5)
    return after_steps(training.fit_coded(ex, EMB, P842, STEPS, LR, policy="k_batch_async", delays=DELAYS, every=100), spark)


@query
def coded_wait_3_updates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The default policy: lanes that have not delivered go on with the weights that they have."""
    ex = workloads.embedding_examples(spark, sf_dir, 4, 0.5)
    return after_steps(training.fit_coded(ex, EMB, P842, STEPS, LR, delays=DELAYS, every=100), spark)


@query
def repetition_3_updates(spark: SparkSession, sf_dir: str) -> DataFrame:
    code = exact_coding.RepetitionCode(8, 5)
    return after_steps(training.fit_exact(workloads.embedding_examples(spark, sf_dir, 8, 0.5), EMB, code, STEPS, LR, DELAYS, every=100), spark)


@query
def regression_step_by_inputs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One update of least squares whose groups are blocks of one output's weights."""
    ex = workloads.regression_examples(spark, sf_dir, 4)
    return after_steps(training.fit_coded(ex, NetSpec(3, (1,), "mse_linear"), P842, 1, 0.3, axis="input", delays=DELAYS, every=100), spark)


@query
def decode_padded_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Five classes in two groups of three: the sixth is padding, which every message carries as zeros."""
    ex = workloads.priority_examples(spark, sf_dir, 4)
    cells = gradients.shard_gradients(ex, {0: fixed_weights(5, 8)}, {s: [0] for s in range(4)}, GroupLayout(NetSpec(8, (5,)), 2))
    scheme = lanes.coded_scheme(P842, "support", "sign")
    out = lanes.decode_messages(lanes.lane_messages(cells, scheme.encode_table(spark)).where("lane < 5"), scheme.decode_table(spark))
    return out.select(F.col("group").cast("int").alias("grp"), F.col("pos").cast("int").alias("pos"), tidy(F.col("delta") / 1000).alias("delta"))


@query
def relu_gradient_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Gradients of both layers of a network with four hidden units, by shard."""
    spec = NetSpec(6, (4, 4), "xent_relu_mlp")
    ex = workloads.lineitem_examples(spark, sf_dir, 4)
    weights = [fixed_weights(4, 6)[0], fixed_weights(4, 4)[0]]
    cells = gradients.shard_gradients(ex, {0: weights}, {s: [0] for s in range(4)}, GroupLayout(spec, 1))
    late = F.col("pos") >= 28
    at, width = F.when(late, F.col("pos") - 28).otherwise(F.col("pos")), F.when(late, 5).otherwise(7)
    return cells.select("part_id", F.when(late, 1).otherwise(0).alias("layer"), F.floor(at / width).cast("int").alias("out_unit"), (at % width).cast("int").alias("in_unit"), tidy(F.col("value") / 10000).alias("g"))


def clipped_residuals(spec, weights, x, y):
    """Least squares whose residuals count as one at most: a kernel of one's own."""
    e = np.clip(x @ weights[0][:, :-1].T[:, 0] + weights[0][0, -1] - y, -1, 1)
    return [np.r_[e @ x, e.sum()][None, :]]


@query
def own_kernel_gradient(spark: SparkSession, sf_dir: str) -> DataFrame:
    spec = NetSpec(3, (1,), "mse_linear")
    cells = gradients.shard_gradients(workloads.regression_examples(spark, sf_dir, 4), {0: fixed_weights(1, 3)}, {s: [0] for s in range(4)}, GroupLayout(spec, 1), clipped_residuals)
    return cells.select("part_id", F.lit(0).alias("out_unit"), F.col("pos").cast("int").alias("in_unit"), tidy(F.col("value") / 10000).alias("g"))


@query
def events_tumbling_gradient(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Gradients by window of six hours, as a stream's batches would give them."""
    events = load_table(spark, sf_dir, "events").withColumn("_window", F.expr(f"CAST(timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', CAST(ts AS TIMESTAMP_NTZ)) div {6 * 3600 * 10**6} AS int)"))
    ex = workloads.event_examples(events, 4, "_window").withColumn("part_id", F.col("_window"))
    low, high = ex.agg(F.min("part_id"), F.max("part_id")).first()
    cells = gradients.shard_gradients(ex, {0: fixed_weights(4, 4)}, {w: [0] for w in range(low, high + 1)}, GroupLayout(NetSpec(4, (4,)), 1))
    return cells.select(F.col("part_id").alias("window"), F.expr("pos div 5").cast("int").alias("out_unit"), (F.col("pos") % 5).cast("int").alias("in_unit"), tidy(F.col("value") / 100).alias("g"))


@query
def benchmark_overlap_anti(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Labelled documents that share no eight words in a row with the benchmark."""
    return workloads.labelled_documents(spark, sf_dir, "quality").select("doc_id")


@query
def doc_dedup_split(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Texts of labelled documents that occur more than once, and in how many splits and shards they are: one."""
    docs = load_table(spark, sf_dir, "documents", "doc_id", "text").join(load_table(spark, sf_dir, "labels", "doc_id"), "doc_id")
    body = F.coalesce("text", F.lit(""))
    key = workloads.text_number(body)
    by = docs.groupBy(F.sha2(body, 256).alias("text_sha256")).agg(F.count("*").alias("copies"), F.count_distinct(layout.split_of(key)).alias("splits"), F.count_distinct(layout.shard_of(key, 4)).alias("shards"))
    return by.where("copies > 1")


@query
def failure_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Which scheme makes eight updates with so many of its eight lanes lost, and which refuses (updates 0)."""
    rows = []
    for lost in range(5):
        hurt = arrivals.Delays(seed=5, dead=tuple(range(lost)))
        for scheme, K, policy in (("coded", 4, "k_async_wait"), ("uncoded", 4, "k_async_wait"), ("exact_6_of_8", 6, "k_sync"), ("synchronous", 8, "k_sync")):
            try:
                made = len(arrivals.arrival_schedule(8, K, 8, policy, hurt))
            except arrivals.LanesLost:
                made = 0
            rows.append((scheme, lost, made, made == 0))
    return spark.createDataFrame(rows, "scheme string, lost int, updates int, refused boolean")


@query
def kasync_3_updates(spark: SparkSession, sf_dir: str) -> DataFrame:
    ex = workloads.embedding_examples(spark, sf_dir, 4, 0.5)
    return after_steps(training.fit_uncoded(ex, EMB, P842, STEPS, LR, policy="k_batch_async", delays=DELAYS, every=100), spark)


@query
def sync_3_updates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return after_steps(training.fit_sync(workloads.embedding_examples(spark, sf_dir, 4, 0.5), EMB, 4, STEPS, LR, DELAYS, every=100), spark)


@query
def exact_3_updates(spark: SparkSession, sf_dir: str) -> DataFrame:
    code = exact_coding.exact_cyclic(8, 5, seed=2)
    return after_steps(training.fit_exact(workloads.embedding_examples(spark, sf_dir, 8, 0.5), EMB, code, STEPS, LR, DELAYS, every=100), spark)


# Measures

add("cost_table_8_16_32", lambda spark, sf: measures.cost_table(spark, SIZES, 650).select("scheme", "n", "k", "t", "weight", "encode_mults", "floats_per_message", "decode_adds", tidy("decode_mults", 3).alias("decode_mults"), "copies", "asynchronous", "compresses"))
add("communication_rollup", lambda spark, sf: measures.communication_rollup(measures.cost_table(spark, SIZES, 650)))
add("test_loss_at_w0", lambda spark, sf: gradients.evaluate(workloads.embedding_examples(spark, sf, 4, 0.5), {0: fixed_weights(10, 64)}, EMB, by="split").select("split", "n_rows", tidy("loss").alias("loss"), tidy("error").alias("error")))


@query
def lane_loss(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Training loss as each lane sees it on its own shards."""
    ex = workloads.embedding_examples(spark, sf_dir, 4, 0.5).withColumn("part", F.col("part_id").cast("string"))
    by = gradients.evaluate(ex.where("split = 'train'"), {0: fixed_weights(10, 64)}, EMB, by="part").withColumn("part_id", F.col("part").cast("int"))
    held = layout.allocate_shards(codes.projective_code(spark, 4, 2)).join(by, "part_id")
    return held.groupBy("lane").agg(F.sum("n_rows").alias("n_rows"), tidy(F.sum(F.col("loss") * F.col("n_rows")) / F.sum("n_rows")).alias("loss"))


@query
def confusion_matrix(spark: SparkSession, sf_dir: str) -> DataFrame:
    ex = workloads.lineitem_examples(spark, sf_dir, 4)
    guess = sql_functions.predict(ex, NetSpec(6, (4,)), fixed_weights(4, 6))
    return ex.select(F.col("y").cast("int").alias("y"), guess.cast("int").alias("predicted")).groupBy("y", "predicted").agg(F.count("*").alias("n"))


@query
def mixture_moments(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = mixture.gaussian_mixture(spark, 3200, 6, 4, 8, sep=2.0, seed=1, k=4)
    cells = df.select("y", F.posexplode("x").alias("j", "v"))
    return cells.groupBy(F.col("y").cast("int").alias("y"), "j").agg(F.count("*").alias("n"), tidy(F.avg("v")).alias("mean"), tidy(F.stddev_pop("v")).alias("spread"))


@query
def mixture_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same mixture read through the data source."""
    mixture.register_mixture(spark)
    df = spark.read.format("mixture").option("rows", 3200).option("u", 6).option("v", 4).option("components", 8).load()
    cells = df.select("y", F.posexplode("x").alias("j", "v"))
    return cells.groupBy(F.col("y").cast("int").alias("y"), "j").agg(F.count("*").alias("n"), tidy(F.avg("v")).alias("mean"), tidy(F.stddev_pop("v")).alias("spread"))


add("planted_label_counts_lineitem", lambda spark, sf: workloads.lineitem_examples(spark, sf, 16).groupBy("part_id", "split", F.col("y").cast("int").alias("y")).agg(F.count("*").alias("n")))
add("planted_label_counts_events", lambda spark, sf: workloads.event_examples(load_table(spark, sf, "events"), 4).groupBy("part_id", F.col("y").cast("int").alias("y")).agg(F.count("*").alias("n")))


@query
def events_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = master.window_sums(load_table(spark, sf_dir, "events", "ts", "event_type", "value"), "6 hours")
    return out.select(micros("start").alias("start"), "event_type", "n", tidy("total", 3).alias("total"))


@query
def events_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = master.sessions(load_table(spark, sf_dir, "events", "ts", "user_id"), "12 hours")
    return out.select("user_id", micros("start").alias("start"), "n")


@query
def events_rolling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each event's sum over the user's last day, by a range window."""
    e = load_table(spark, sf_dir, "events", "event_id", "ts", "user_id", "value").withColumn("us", micros("ts"))
    w = Window.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)
    return e.select("event_id", tidy(F.sum("value").over(w), 3).alias("day_value"))


def through_a_stream(df: DataFrame, made, label: str) -> DataFrame:
    """df written to the shared folder, read as a stream, put through made, and the sink's rows."""
    spark, folder = df.sparkSession, f"{shared_folder(df.sparkSession)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(f"{folder}/in")
    out = made(spark.readStream.schema(df.schema).parquet(f"{folder}/in"))
    out.writeStream.format("parquet").option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start(f"{folder}/out").awaitTermination()
    return spark.read.schema(out.schema).parquet(f"{folder}/out")


@query
def stateful_master_steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Forty messages through the stateful master: which make a step, which are held, how far they are behind."""
    groups, scheme = GroupLayout(NetSpec(2, (2,)), 2), lanes.coded_scheme(P842)
    sent = arrivals.batch_arrivals(spark, 8, 4, 10, DELAYS).select(F.lit("r").alias("run_id"), "seq", "lane", "read_version", F.array_repeat(F.lit(1.0), groups.block).alias("payload"))
    out = through_a_stream(sent.coalesce(1), lambda s: master.stateful_master(s, scheme, groups, 4, 0.1, 100, 100), "steps")
    return out.select("lane", "version", "staleness", "outcome")


@query
def stream_notice_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Messages with the notices of the ten minutes before them, two streams joined by interval."""
    folder, start = f"{shared_folder(spark)}/notices-{uuid.uuid4().hex}", F.lit(1704067200)
    told = spark.range(3).select(F.lit("r").alias("run_id"), F.col("id").alias("version"), F.timestamp_seconds(start + F.col("id") * 600).alias("told_at"))
    told.write.parquet(folder)
    notices = spark.readStream.schema(told.schema).parquet(folder)
    sent = spark.range(6).select(F.lit("r").alias("run_id"), F.col("id").cast("int").alias("lane"), F.timestamp_seconds(start + F.col("id") * 300).alias("sent_at"))
    return through_a_stream(sent, lambda s: master.messages_with_notices(s, notices), "messages").select("lane", "version")


@query
def formats_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A table written and read with its schema in four file formats."""
    nation, folder, out = load_table(spark, sf_dir, "nation"), f"{shared_folder(spark)}/formats-{uuid.uuid4().hex}", None
    for fmt in ("json", "csv", "orc", "parquet"):
        nation.write.format(fmt).option("header", True).save(f"{folder}/{fmt}")
        row = read_any(spark, f"{folder}/{fmt}", fmt, nation.schema).agg(F.count("*").alias("n"), F.sum("n_nationkey").alias("keys"), F.max("n_name").alias("last_name")).withColumn("format", F.lit(fmt))
        out = row if out is None else out.union(row)
    return out


# Relations around the methods


@query
def code_matrix_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The code as a matrix: a row per lane, a column per shard."""
    wide = codes.projective_code(spark, 4, 2).groupBy("lane").pivot("theta", [0, 1, 2, 3]).agg(F.first("sign"))
    return wide.select("lane", *[F.coalesce(F.col(str(j)), F.lit(0)).alias(f"theta_{j}") for j in range(4)])


@query
def common_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shards that lanes 0 and 9 both hold."""
    held = layout.allocate_shards(codes.projective_code(spark, 8, 4))
    return held.where("lane = 0").select("part_id").intersect(held.where("lane = 9").select("part_id"))


@query
def shards_out_of_reach(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shards that none of the first five lanes holds."""
    held = layout.allocate_shards(codes.projective_code(spark, 8, 4))
    return spark.range(8).select(F.col("id").cast("int").alias("part_id")).exceptAll(held.where("lane < 5").select("part_id").distinct())


@query
def updates_by_arrival(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Messages put to the update whose span (after the last one's end, up to its own) their arrival falls into."""
    sent = arrivals.batch_arrivals(spark, 8, 4, 10, DELAYS)
    closes = sent.groupBy("update_no").agg(F.max("arrive_at").alias("closed"))
    spans = closes.withColumn("opened", F.coalesce(F.lag("closed").over(Window.orderBy("update_no")), F.lit(0.0)))  # a row an update
    met = sent.select("lane", "seq", "arrive_at").join(F.broadcast(spans), (F.col("arrive_at") > F.col("opened")) & (F.col("arrive_at") <= F.col("closed")))
    return met.select("seq", "lane", "update_no")


@query
def cost_grouping_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Numbers sent and shard copies by scheme, by size, and in all."""
    measures.cost_table(spark, SIZES, 650).createOrReplaceTempView("scheme_costs")
    return spark.sql("SELECT scheme, n, sum(floats_per_message) AS floats, max(copies) AS most_copies FROM scheme_costs GROUP BY GROUPING SETS ((scheme, n), (scheme), (n), ())")


@query
def cost_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.cost_table(spark, SIZES, 650).cube("scheme", "t").agg(F.sum("decode_adds").alias("adds"), F.count("*").alias("rows"))


@query
def hardest_examples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ten lines with the largest score of a class that is not theirs, and their rank in their shard."""
    ex = workloads.lineitem_examples(spark, sf_dir, 4)
    top = ex.select("row_key", "part_id", tidy(F.col("x")[1] - F.col("x")[0]).alias("score")).orderBy(F.desc("score"), "row_key").limit(10)
    return top.withColumn("place", F.dense_rank().over(Window.partitionBy("part_id").orderBy(F.desc("score"))).cast("long"))


@query
def fastest_lanes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The three first lanes of every update, and how far each is behind the first."""
    w = Window.partitionBy("update_no").orderBy("arrive_at", "lane")
    sent = arrivals.sync_arrivals(spark, 8, 4, 12, DELAYS).withColumn("behind", F.col("arrive_at") - F.first("arrive_at").over(w))
    return sent.where("place <= 3").select("update_no", "lane", F.col("place").cast("long").alias("place"), tidy("behind").alias("behind"))


@query
def value_quarters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events by quarter of their value within their type: size and bounds."""
    e = load_table(spark, sf_dir, "events", "event_id", "event_type", "value")
    q = e.withColumn("quarter", F.ntile(4).over(Window.partitionBy("event_type").orderBy("value", "event_id")))
    return q.groupBy("event_type", F.col("quarter").cast("long").alias("quarter")).agg(F.count("*").alias("n"), F.min("value").alias("low"), F.max("value").alias("high"))


@query
def schemes_side_by_side(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Full outer join of two schemes' schedules by update and lane: who delivered in one and not in the other."""
    a = arrivals.sync_arrivals(spark, 8, 4, 6, DELAYS).where("taken").select("update_no", "lane", F.lit(True).alias("four"))
    b = arrivals.sync_arrivals(spark, 8, 6, 6, DELAYS).where("taken").select("update_no", "lane", F.lit(True).alias("six"))
    both = a.join(b, ["update_no", "lane"], "full")
    return both.select("update_no", "lane", F.coalesce("four", F.lit(False)).alias("four"), F.coalesce("six", F.lit(False)).alias("six"))


# Runs of the experiments: curves, without SQL. Few updates here; bench.py and the tests run longer ones.


def curves(spark: SparkSession, results: list[training.FitResult]) -> DataFrame:
    rows = [r for x in results for r in x.curve]
    return spark.createDataFrame(rows, training.CURVE)


def compare(spark, make, spec: NetSpec, p: CodeParams, updates: int, lr: float, exact: bool = True, delays=DELAYS, every: int = 4, costs=training.Costs()) -> list[training.FitResult]:
    """Coded, uncoded, exact (with as many lanes lost as its weight allows) and synchronous descent on make(shards)."""
    start = spec.start(1)
    label = f"{p.n}_{p.k}_{p.t}"
    data = make(p.k).persist()
    out = [
        training.fit_coded(data, spec, p, updates, lr, delays=delays, costs=costs, every=every, start=start, run_id=f"coded_{label}"),
        training.fit_uncoded(data, spec, p, updates, lr, delays=delays, costs=costs, every=every, start=start, run_id=f"uncoded_{label}"),
    ]
    if exact:
        code = exact_coding.exact_cyclic(p.n, p.n - p.t + 1)
        other = make(p.n).persist()
        out.append(training.fit_exact(other, spec, code, updates, lr, delays, costs, every=every, start=start, run_id=f"exact_{label}"))
        out.append(training.fit_sync(other, spec, p.n, updates, lr, delays, costs, every=every, start=start, run_id=f"sync_{label}"))
        other.unpersist()
    data.unpersist()
    return out


def _mixture(spark, rows=3200, u=16, v=8, components=16):
    return lambda k: mixture.gaussian_mixture(spark, rows, u, v, components, sep=6.0, seed=3, k=k)


def _rows(sf_dir: str) -> int:
    """3,200 rows at the smallest tables, and as many times more as orders has."""
    scale = re.search(r"/sf([0-9]+\.?[0-9]*)/?$", sf_dir)
    return int(3200 * max(1.0, float(scale[1]) / 0.001)) if scale else 3200


def mixture_run(spark: SparkSession, sf_dir: str, sizes, updates: int, **more) -> DataFrame:
    out = []
    for size in sizes:
        out += compare(spark, _mixture(spark, _rows(sf_dir)), NetSpec(16, (8,)), CodeParams(*size), updates, 0.5, **more)
    return curves(spark, out)


add("run_mixture_softmax", lambda spark, sf: mixture_run(spark, sf, SIZES[:1], 8))
add("run_mixture_16", lambda spark, sf: mixture_run(spark, sf, SIZES[1:3], 5, every=5))
add("run_mixture_32", lambda spark, sf: mixture_run(spark, sf, SIZES[3:], 4, every=4))
# Work by the rows that a lane handles, five thousandths of a second a number sent, and a solve: all on the virtual clock.
CHARGED = training.Costs(rows=True, sent=0.005, solve=0.01)
add("run_mixture_charged", lambda spark, sf: mixture_run(spark, sf, SIZES[:1], 8, costs=CHARGED))


@query
def run_embeddings_softmax(spark: SparkSession, sf_dir: str) -> DataFrame:
    return curves(spark, compare(spark, lambda k: workloads.embedding_examples(spark, sf_dir, k, 0.5), EMB, P842, 8, 4.0))


@query
def run_embeddings_16_32(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = []
    for size in ((16, 8, 4), (32, 16, 4)):
        out += compare(spark, lambda k: workloads.embedding_examples(spark, sf_dir, k, 0.5), EMB, CodeParams(*size), 4, 4.0)
    return curves(spark, out)


@query
def run_lineitem_softmax(spark: SparkSession, sf_dir: str) -> DataFrame:
    return curves(spark, compare(spark, lambda k: workloads.lineitem_examples(spark, sf_dir, k), NetSpec(6, (4,)), P842, 8, 0.5))


@query
def run_relu_network(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A hidden layer of 16; coded against uncoded alone."""
    return curves(spark, compare(spark, _mixture(spark), NetSpec(16, (16, 8), "xent_relu_mlp"), P842, 8, 0.3, exact=False))


@query
def run_relu_16_32(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two hidden layers on 16 and 32 lanes; coded against uncoded."""
    spec, out = NetSpec(16, (16, 16, 8), "xent_relu_mlp"), []
    for size in ((16, 8, 4), (32, 16, 4)):
        out += compare(spark, _mixture(spark), spec, CodeParams(*size), 5, 0.3, exact=False, every=5)
    return curves(spark, out)


@query
def run_nested_network(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The hidden layer cut flat and by repeated splitting, at one step."""
    spec, data = NetSpec(16, (16, 8), "xent_relu_mlp"), _mixture(spark)(4).persist()
    return curves(spark, [training.fit_coded(data, spec, P842, 8, 0.3, delays=DELAYS, every=4, start=spec.start(1), run_id=name, nested=name == "nested") for name in ("flat", "nested")])


@query
def reference_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Test errors on planted embeddings of Spark's own logistic regression and of coded descent with all lanes."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.functions import array_to_vector

    ex = workloads.embedding_examples(spark, sf_dir, 4, 0.5).persist()
    frame = ex.select("split", array_to_vector("x").alias("features"), F.col("y").cast("double").alias("label"))
    judged = LogisticRegression(maxIter=50, regParam=0.001).fit(frame.where("split = 'train'")).transform(frame.where("split = 'test'"))
    error = judged.agg(F.avg((F.col("prediction") != F.col("label")).cast("double"))).first()[0]
    coded = training.fit_coded(ex, EMB, P842, 20, 8.0, K=8, policy="k_sync", delays=DELAYS, every=20).curve[-1]
    return spark.createDataFrame([("spark_logistic_regression", error), ("coded_all_lanes", coded[7])], "method string, test_error double")


@query
def run_with_failures(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two lanes dead, one eight times as slow."""
    hurt = arrivals.Delays(seed=5, dead=(2, 5), slow=(1,))
    data = _mixture(spark)(4).persist()
    spec = NetSpec(16, (8,))
    out = [f(data, spec, P842, 8, 0.5, delays=hurt, every=4, run_id=name) for f, name in ((training.fit_coded, "coded_hurt"), (training.fit_uncoded, "uncoded_hurt"))]
    code = exact_coding.exact_cyclic(8, 6)
    out.append(training.fit_exact(_mixture(spark)(8), spec, code, 8, 0.5, hurt, every=4, run_id="exact_hurt"))
    return curves(spark, out)


@query
def run_rotated_general_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sizes that are no powers of two: the allocation moves on the torus with every update."""
    out = []
    for n, k, t, d in ((5, 3, 2, 5), (6, 3, 2, 5), (12, 6, 2, 5), (12, 5, 2, 3), (13, 7, 2, 3)):
        e, data = embed_parameters(n, k, t, d), _mixture(spark)(k).persist()
        out.append(training.fit_coded(data, NetSpec(16, (8,)), e, 6, 0.5, rotate=True, delays=DELAYS, every=6, run_id=f"rotated_{n}_{k}_{t}"))
        data.unpersist()
    return curves(spark, out)


@query
def run_ablations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scaling, data mode, K, policy and scan of the coded scheme at one nominal step."""
    data, spec = _mixture(spark)(4).persist(), NetSpec(16, (8,))
    runs = []
    plain = [("sign_support", {}), ("unit_support", {"scaling": "unit"}), ("sign_pure", {"mode": "pure"}), ("per_lane", {"scan": "per_lane"}), ("k_sync", {"policy": "k_sync"}), ("k_batch_async", {"policy": "k_batch_async"})]
    for name, more in plain + [(f"K_{K}", {"K": K}) for K in (1, 2, 3, 5, 6, 7, 8)]:
        runs.append(training.fit_coded(data, spec, P842, 4, 0.5, delays=DELAYS, every=4, run_id=name, **more))
    return curves(spark, runs)


@query
def run_weight_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """t from 2 to n/4 on 16 and 32 lanes, and the allocation fixed or moved on the torus."""
    spec, runs = NetSpec(16, (8,)), []
    for n, k, ts in ((16, 8, (2, 4)), (32, 16, (2, 4, 8))):
        data = _mixture(spark)(k).persist()
        for t in ts:
            runs.append(training.fit_coded(data, spec, CodeParams(n, k, t), 4, 0.5, delays=DELAYS, every=4, run_id=f"t_{n}_{k}_{t}"))
            if n == 16:
                runs.append(training.fit_coded(data, spec, embed_parameters(n, k, t), 4, 0.5, rotate=True, delays=DELAYS, every=4, run_id=f"rotated_{n}_{k}_{t}"))
        data.unpersist()
    return curves(spark, runs)


@query
def run_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality and toxicity of labelled documents, two logistic models; copies of a text stand in one split."""
    out = []
    for target in ("quality", "toxic"):
        data = workloads.document_examples(spark, sf_dir, 4, target, 32).persist()
        out.append(training.fit_coded(data, NetSpec(32, (1,), "xent_logistic"), P842, 8, 2.0, axis="input", delays=DELAYS, every=4, run_id=f"coded_{target}"))
        out.append(training.fit_uncoded(data, NetSpec(32, (1,), "xent_logistic"), P842, 8, 2.0, delays=DELAYS, every=4, run_id=f"uncoded_{target}"))
        data.unpersist()
    return curves(spark, out)


@query
def run_conversation_roles(spark: SparkSession, sf_dir: str) -> DataFrame:
    return curves(spark, compare(spark, lambda k: workloads.conversation_examples(spark, sf_dir, k), NetSpec(3, (3,)), P842, 8, 1.0, exact=False))


@query
def run_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return curves(spark, compare(spark, lambda k: workloads.page_examples(spark, sf_dir, k), NetSpec(3, (4,)), P842, 8, 1.0, exact=False))


@query
def run_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order priorities, whose five classes are padded to six."""
    return curves(spark, compare(spark, lambda k: workloads.priority_examples(spark, sf_dir, k), NetSpec(8, (5,)), P842, 8, 0.5, exact=False))


@query
def run_regression(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Least squares with one output: the groups are blocks of its weights."""
    data = workloads.regression_examples(spark, sf_dir, 4).persist()
    runs = [training.fit_coded(data, NetSpec(3, (1,), "mse_linear"), P842, 8, 0.3, axis="input", delays=DELAYS, every=4, run_id="coded_inputs")]
    runs.append(training.fit_uncoded(data, NetSpec(3, (1,), "mse_linear"), P842, 8, 0.3, delays=DELAYS, every=4, run_id="uncoded"))
    return curves(spark, runs)


@query
def run_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Replication, the uncoded scheme, random signs and a dense MDS code beside the code, at the same number of messages."""
    data, spec = _mixture(spark)(4).persist(), NetSpec(16, (8,))
    schedule = arrivals.arrival_schedule(8, 4, 8, "k_async_wait", DELAYS)
    random = lanes.ray_scheme("random_signs", [(r.lane, r.theta, float(r.sign)) for r in codes.random_sign_code(spark, 8, 4, 2, seed=3).collect()], 4, 2)
    dense = lanes.ray_scheme("mds", [(r.lane, r.theta, r.coef) for r in codes.mds_code(spark, 8, 4).collect()], 4, 2)
    schemes = (lanes.coded_scheme(P842), lanes.uncoded_scheme(P842), lanes.repeated_scheme(4, 2), random, dense)
    return curves(spark, [training.fit(data, spec, s, schedule, 0.5, every=4, run_id=s.name) for s in schemes])


@query
def run_live(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three updates with a Spark job per lane and real arrivals."""
    r = training.fit_live(_mixture(spark, 800)(4).persist(), NetSpec(16, (8,)), lanes.coded_scheme(P842), 4, 3, 0.5)
    return r.table(spark).select("update_no", "scheme", "floats_sent")


@query
def run_event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream: a coded step per micro-batch; losses before and after."""
    stream = spark.readStream.schema(load_table(spark, sf_dir, "events").schema).option("maxFilesPerTrigger", 1).parquet(f"{sf_dir}/events.parquet*")
    sink = master.MiniBatchDescent(NetSpec(4, (4,)), lanes.coded_scheme(P842), 0.5, list(range(8)))
    workloads.event_examples(stream, 4).writeStream.foreachBatch(sink).option("checkpointLocation", f"{shared_folder(spark)}/events-{uuid.uuid4().hex}").trigger(availableNow=True).start().awaitTermination()
    ex = workloads.event_examples(load_table(spark, sf_dir, "events"), 4)
    return gradients.evaluate(ex.where("split = 'test'"), {0: sink.layout.spec.start(), len(sink.history): sink.weights}, sink.layout.spec)


@query
def curve_measures(spark: SparkSession, sf_dir: str) -> DataFrame:
    """First point at or below a loss, how many points overfit and the last smoothed loss, for curves whose points are given:
    one that reaches the target and overfits later, one that never does, one without test rows."""
    rows = [(f"run_{r}", "coded", u, 1.5 * u + r, 0.0, 2.0 / (u + 1), None if r == 2 else round(2.0 - 0.3 * u + (0.02 + 0.01 * r) * u * u + 0.1 * (r * u % 3), 6), None, 100 * u * (r + 1)) for r in range(3) for u in range(12)]
    curve = spark.createDataFrame(rows, training.CURVE)
    first = measures.time_to_target(curve, 1.05)
    over = measures.overfit_points(curve).groupBy("run_id").agg(F.sum(F.col("overfits").cast("long")).alias("overfit_points"))
    last = measures.smoothed(curve, 3).groupBy("run_id").agg(tidy(F.max_by("test_loss_smooth", "update_no")).alias("last_smooth"))
    return first.join(over, "run_id").join(last, "run_id").select("run_id", "scheme", "update_no", tidy("virtual_time").alias("virtual_time"), "floats_sent", "overfit_points", "last_smooth")


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ten updates of coded descent on planted embeddings, eight lanes, four messages an update."""
    data = workloads.embedding_examples(spark, sf_dir, 4, 0.5).persist()
    return training.fit_coded(data, EMB, P842, 10, 4.0, K=4, delays=DELAYS, every=2, run_id="flagship").table(spark)


add("flagship", flagship)
