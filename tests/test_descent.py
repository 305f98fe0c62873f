"""Gradients against differences, descent against a plain loop, rivals, failures, streams, plans."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from raydescent.operators import arrivals, exact_coding, gradients, training
from raydescent.operators.lanes import coded_scheme, rotated_scheme
from raydescent.plans.models import GroupLayout, NetSpec, gradients as gradient_kernel, losses
from raydescent.plans.params import CodeParams, embed_parameters
from raydescent.sources import mixture, tables, workloads

P = CodeParams(8, 4, 2)
SPEC = NetSpec(16, (8,))
DELAYS = arrivals.Delays(seed=5)


@pytest.fixture(scope="module")
def mix(spark):
    return {k: mixture.gaussian_mixture(spark, 800, 16, 8, 16, sep=6.0, seed=3, k=k).persist() for k in (4, 8)}


@pytest.mark.parametrize("loss,outs,form", [("xent_softmax", (3,), "standard"), ("xent_softmax", (3,), "reference"), ("mse_softmax", (3,), "standard"), ("mse_linear", (1,), "standard"), ("xent_logistic", (1,), "standard"), ("xent_relu_mlp", (5, 3), "standard")])
def test_gradients_by_differences(loss, outs, form):
    rng = np.random.default_rng(0)
    spec = NetSpec(4, outs, loss, form)
    w = [rng.standard_normal(s) * 0.5 for s in spec.shapes]
    x, y = rng.standard_normal((7, 4)), rng.integers(0, 2 if outs[-1] == 1 else 3, 7).astype(float)
    g = gradient_kernel(spec, w, x, y)
    for layer, shape in enumerate(spec.shapes):
        for _ in range(6):
            at = tuple(rng.integers(0, s) for s in shape)
            up, down = [v.copy() for v in w], [v.copy() for v in w]
            up[layer][at] += 1e-6
            down[layer][at] -= 1e-6
            slope = (losses(spec, up, x, y)[0].sum() - losses(spec, down, x, y)[0].sum()) / 2e-6
            assert abs(slope - g[layer][at]) < 1e-5


@pytest.mark.parametrize("outs,axis", [((10,), "output"), ((6, 10), "output"), ((1,), "input")])
def test_groups_split_and_merge(outs, axis):
    spec = NetSpec(5, outs, "xent_relu_mlp" if len(outs) > 1 else "mse_linear" if outs == (1,) else "xent_softmax")
    layout = GroupLayout(spec, 4, axis)
    g = [np.random.default_rng(0).standard_normal(s) for s in spec.shapes]
    blocks = layout.split(g)
    assert blocks.shape == (4, layout.block)
    assert all(np.array_equal(a, b) for a, b in zip(layout.merge(blocks), g))
    assert layout.block < spec.parameters / 2


def plain_loop(x, y, parts, scheme, schedule, lr):
    layout, n = GroupLayout(SPEC, scheme.t), len(x)
    versions, w = {0: SPEC.start()}, SPEC.start()
    for u in schedule:
        total = np.zeros((scheme.t, layout.block))
        for lane, v, _ in u.messages:
            message = np.zeros(layout.block)
            for i, p, g, _, c in scheme.encode:
                if i == lane:
                    at = parts == p
                    message += c * layout.split(gradient_kernel(SPEC, versions[v], x[at], y[at]))[g]
            for i, _, g, c in scheme.decode:
                if i == lane:
                    total[g] += c * message
        total /= n * scheme.rows_share * len(u.messages)
        w = [a - lr * b for a, b in zip(w, layout.merge(total))]
        versions[u.number + 1] = w
    return w


@pytest.mark.parametrize("policy", ["k_async_wait", "k_batch_async", "k_sync"])
def test_descent_equals_a_plain_loop(spark, mix, policy):
    rows = mix[4].where("split = 'train'").toPandas()
    schedule = arrivals.arrival_schedule(8, 4, 6, policy, DELAYS)
    want = plain_loop(np.stack(rows.x), rows.y.to_numpy(), rows.part_id.to_numpy(), coded_scheme(P), schedule, 0.5)
    got = training.fit_coded(mix[4], SPEC, P, 6, 0.5, policy=policy, delays=DELAYS, every=100).weights
    assert np.allclose(got[0], want[0], atol=1e-9)


def test_all_lanes_make_plain_descent_and_scans_agree(spark, mix):
    full = training.fit_coded(mix[4], SPEC, P, 3, 0.5, K=8, policy="k_sync", delays=DELAYS, every=100).weights
    sync = training.fit_sync(mix[8], SPEC, 8, 3, 0.5, DELAYS, every=100).weights
    exact = training.fit_exact(mix[8], SPEC, exact_coding.exact_cyclic(8, 5), 3, 0.5, DELAYS, every=100).weights
    lanes = training.fit_coded(mix[4], SPEC, P, 3, 0.5, K=8, policy="k_sync", delays=DELAYS, every=100, scan="per_lane").weights
    unit = training.fit_coded(mix[4], SPEC, P, 3, 1.0, K=8, policy="k_sync", scaling="unit", delays=DELAYS, every=100).weights
    for other in (sync, exact, lanes, unit):
        assert np.allclose(full[0], other[0], atol=1e-7)


def test_coded_messages_are_shorter_and_loss_falls(spark, mix):
    coded = training.fit_coded(mix[4], SPEC, P, 12, 0.5, delays=DELAYS, every=12)
    rival = training.fit_uncoded(mix[4], SPEC, P, 12, 0.5, delays=DELAYS, every=12)
    assert coded.curve[-1][8] * 2 == rival.curve[-1][8]
    assert coded.curve[-1][6] < 0.6 * coded.curve[0][6]


def test_dead_lanes(spark, mix):
    hurt = arrivals.Delays(seed=5, dead=(1, 4, 6))
    assert training.fit_coded(mix[4], SPEC, P, 4, 0.5, K=4, delays=hurt, every=4).updates == 4
    assert training.fit_exact(mix[8], SPEC, exact_coding.exact_cyclic(8, 5), 3, 0.5, hurt, every=4).updates == 3
    with pytest.raises(arrivals.LanesLost):
        training.fit_exact(mix[8], SPEC, exact_coding.exact_cyclic(8, 6), 3, 0.5, hurt, every=4)
    assert training.fit_exact(mix[8], SPEC, exact_coding.RepetitionCode(8, 5), 2, 0.5, hurt, every=4).updates == 2
    with pytest.raises(ValueError):
        exact_coding.RepetitionCode(8, 5).solve([0, 1, 2, 3])


def test_costs_delay_what_comes_after():
    """Work by rows and transfer are part of a job, a solve comes before the next one; nothing is added afterwards."""
    p, flat = P, arrivals.Delays(work=1.0, mean=0.0)
    costs = training.Costs(rows=True, sent=0.01, solve=0.5)
    coded = coded_scheme(p)
    assert coded.load == 4.0 and coded_scheme(p, "pure").load == 8 * 1.0 and exact_coding.exact_cyclic(8, 7).weight == 2
    layout = GroupLayout(SPEC, 2)
    u = arrivals.arrival_schedule(8, 8, 3, "k_sync", costs.on(flat, coded.load, layout.block))
    assert np.allclose([x.at for x in u], np.arange(1, 4) * (4 + 0.01 * layout.block))
    u = arrivals.arrival_schedule(8, 7, 3, "k_sync", costs.on(flat, 2, 136), 0.5)
    assert np.allclose([x.at for x in u], np.arange(1, 4) * (2 + 1.36 + 0.5))
    late = costs.on(arrivals.Delays(seed=3), 4.0, 68)
    free, charged = (arrivals.arrival_schedule(8, 4, 30, "k_async_wait", d) for d in (arrivals.Delays(seed=3), late))
    assert [x.messages for x in free] != [x.messages for x in charged] and charged[-1].at > 2 * free[-1].at


def test_long_blocks_are_added_up_as_slices(spark, mix, monkeypatch):
    want = training.fit_coded(mix[4], SPEC, P, 2, 0.5, delays=DELAYS, every=100).weights
    for module in (gradients, training):
        monkeypatch.setattr(module, "LONG_BLOCK", 10)
    got = training.fit_coded(mix[4].repartition(5), SPEC, P, 2, 0.5, delays=DELAYS, every=100).weights
    assert np.allclose(want[0], got[0], atol=1e-9)
    blocks = spark.createDataFrame([(1, g % 2, 3 * (g % 3), [1.0 * g, 2.0, 3.0]) for g in range(60)], "lane int, version long, first int, values array<double>").repartition(6)
    out = {(r.lane, r.version, r["first"]): r["values"] for r in gradients.summed_slices(blocks, ["lane", "version"]).collect()}
    assert len(out) == 6 and all(v[0] == sum(g for g in range(60) if (1, g % 2, 3 * (g % 3)) == k) and v[1:] == [20.0, 30.0] for k, v in out.items())


def test_curves_are_judged_in_portions(spark, mix, monkeypatch):
    whole = training.fit_coded(mix[4], SPEC, P, 5, 0.5, delays=DELAYS, every=1).curve
    monkeypatch.setattr(training, "JUDGED", 2)
    parts = training.fit_coded(mix[4], SPEC, P, 5, 0.5, delays=DELAYS, every=1).curve
    assert [r[2] for r in parts] == list(range(6)) and np.allclose([r[6] for r in whole], [r[6] for r in parts])


def test_nested_network(spark, mix):
    """Groups of repeated splitting come apart and together again; all lanes give the gradient plus that of the groups
    whose digits are those of the group in another order."""
    from raydescent.operators.lanes import nested_scheme
    from raydescent.plans.models import NestedLayout

    spec = NetSpec(16, (10, 7, 8), "xent_relu_mlp")
    layout, scheme = NestedLayout(spec, 2), nested_scheme(P, 3)
    assert (layout.groups, layout.t, scheme.t, scheme.slots) == ([8, 4, 2], 14, 14, 3)
    g = [np.random.default_rng(1).standard_normal(s) for s in spec.shapes]
    assert all(np.array_equal(a, b) for a, b in zip(layout.merge(layout.split(g)), g))
    assert layout.numbers < 0.3 * spec.parameters
    cells = {(a, b): 0.0 for a in range(14) for b in range(14)}
    for lane in range(8):
        on = {r[2]: r[4] for r in scheme.encode if r[0] == lane}
        slot = {r[2]: r[3] for r in scheme.encode if r[0] == lane}
        for a in on:
            for b in on:
                cells[a, b] += on[a] * on[b] * (slot[a] == slot[b])
    digits = lambda a: (0, tuple(sorted(f"{a:03b}"))) if a < 8 else (1, tuple(sorted(f"{a - 8:02b}"))) if a < 12 else (2, a)
    assert all(v == 8.0 for (a, b), v in cells.items() if a == b)
    assert all(v == 8.0 for (a, b), v in cells.items() if digits(a) == digits(b))
    r = training.fit_coded(mix[4], spec, P, 6, 0.3, delays=DELAYS, every=6, nested=True)
    assert r.curve[-1][6] < r.curve[0][6] and r.curve[-1][8] == 6 * 4 * layout.numbers


def test_entry_hides_only_a_missing_subpackage(tmp_path, monkeypatch):
    """Without the training-text operators the entry imports; an import that fails within them is an error."""
    import shutil
    import subprocess
    import sys
    from pathlib import Path

    root = Path(__file__).resolve().parent.parent
    shutil.copy(root / "__spark_entry__.py", tmp_path)
    shutil.copytree(root / "raydescent", tmp_path / "raydescent", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    ask = [sys.executable, "-B", "-c", "import __spark_entry__ as e; print(len(e.queries()), any(q.startswith('op') and q[2].isdigit() for q in e.queries()))"]
    said = subprocess.run(ask, cwd=tmp_path, capture_output=True, text=True, env={"PATH": "/usr/bin:/bin"})
    assert said.stdout.split()[-1] == "False" and int(said.stdout.split()[-2]) > 100, said.stderr
    (tmp_path / "raydescent/llm").mkdir()
    (tmp_path / "raydescent/llm/__init__.py").write_text("")
    (tmp_path / "raydescent/llm/queries.py").write_text("import no_such_library\n")
    broken = subprocess.run(ask, cwd=tmp_path, capture_output=True, text=True, env={"PATH": "/usr/bin:/bin"})
    assert broken.returncode and "no_such_library" in broken.stderr


def test_a_cluster_needs_a_shared_folder():
    from raydescent.session import shared_folder

    class Conf:
        def get(self, *_):
            return None

    class Context:
        master = "spark://host:7077"

        def getCheckpointDir(self):
            return None

    class Session:
        conf, sparkContext = Conf(), Context()

    with pytest.raises(RuntimeError, match="checkpoint"):
        shared_folder(Session())


def test_network_and_rotation(spark, mix):
    spec = NetSpec(16, (16, 8), "xent_relu_mlp")
    r = training.fit_coded(mix[4], spec, P, 6, 0.5, delays=DELAYS, every=6)
    assert r.curve[-1][6] < r.curve[0][6]
    e = embed_parameters(13, 7, 2, 3)
    assert rotated_scheme(e, 1).shards_of(0) != rotated_scheme(e, 0).shards_of(0)
    data = mixture.gaussian_mixture(spark, 800, 16, 8, 16, sep=6.0, seed=3, k=7)
    r = training.fit_coded(data, SPEC, e, 4, 0.5, K=6, rotate=True, delays=DELAYS, every=4)
    assert r.curve[-1][6] < r.curve[0][6]


def test_live_arrivals(spark, mix):
    r = training.fit_live(mix[4], SPEC, coded_scheme(P), 4, 3, 0.5, slow={0: 5.0})
    assert r.updates == 3 and np.isfinite(r.weights[0]).all()


def test_reference_accuracy(spark, data):
    """Plain Spark's classifier and full coded descent come to like test errors on planted vectors."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.functions import array_to_vector

    ex = workloads.embedding_examples(spark, data, 4, 0.5).persist()
    r = training.fit_coded(ex, NetSpec(64, (10,)), P, 30, 8.0, K=8, policy="k_sync", delays=DELAYS, every=30)
    frame = ex.select("split", array_to_vector("x").alias("features"), F.col("y").alias("label"))
    model = LogisticRegression(maxIter=50, regParam=0.001).fit(frame.where("split = 'train'"))
    test = model.transform(frame.where("split = 'test'"))
    error = test.where("prediction <> label").count() / test.count()
    assert r.curve[-1][7] <= error + 0.05


def test_null_examples_are_left_out(spark, mix):
    gap = spark.createDataFrame([(1, None, 1.0, 0, "train"), (2, [0.0] * 16, None, 0, "train")], "row_key long, x array<double>, y double, part_id int, split string")
    both = mix[4].unionByName(gap)
    a, b = (gradients.evaluate(d.where("split = 'train'"), {0: SPEC.start()}, SPEC).first() for d in (mix[4], both))
    assert a == b


def test_storage(spark, mix, tmp_path):
    path = f"file://{tmp_path}/shards"
    tables.write_shards(mix[4], path, files_per_shard=2)
    back = tables.read_shards(spark, path, [1, 2])
    assert "PartitionFilters" in back._jdf.queryExecution().toString()
    assert back.count() == mix[4].where("part_id IN (1, 2)").count()
    w = [np.arange(6.0).reshape(2, 3), np.ones((1, 3))]
    tables.save_weights(spark, w, f"file://{tmp_path}/weights", "a", 3)
    tables.save_weights(spark, [v + 1 for v in w], f"file://{tmp_path}/weights", "a", 4)
    version, got = tables.load_weights(spark, f"file://{tmp_path}/weights", "a")
    assert version == 4 and all(np.array_equal(g, v + 1) for g, v in zip(got, w))


def test_plan_shape(spark, data, tmp_path):
    """One pruned scan of the examples, broadcast of the code, no Cartesian product."""
    from raydescent.operators.lanes import lane_messages

    workloads.lineitem_examples(spark, data, 4).write.parquet(f"file://{tmp_path}/ex")
    ex = spark.read.parquet(f"file://{tmp_path}/ex")
    layout = GroupLayout(NetSpec(6, (4,)), 2)
    cells = gradients.shard_gradients(ex, {0: layout.spec.start()}, {s: [0] for s in range(4)}, layout)
    plan = lane_messages(cells, coded_scheme(P).encode_table(spark))._jdf.queryExecution().executedPlan().toString()
    assert plan.count("FileScan parquet") == 1 and "BroadcastHashJoin" in plan and "CartesianProduct" not in plan
    assert "row_key" not in plan.split("FileScan parquet")[1].split("ReadSchema")[1]


def test_stateful_master(spark, tmp_path):
    from raydescent.streaming.master import stateful_master

    layout, scheme = GroupLayout(NetSpec(2, (2,)), 2), coded_scheme(P)
    schema = "run_id string, seq long, lane int, read_version long, payload array<double>"
    rows = [("r", i, i % 8, 0, [1.0] * layout.block) for i in range(8)] + [("r", 3, 3, 0, [1.0] * layout.block)]
    spark.createDataFrame(rows, schema).coalesce(1).write.parquet(f"{tmp_path}/in")
    steps = stateful_master(spark.readStream.schema(schema).parquet(f"{tmp_path}/in"), scheme, layout, 4, 0.1, 100)
    q = steps.writeStream.format("memory").queryName("steps").option("checkpointLocation", f"{tmp_path}/ck").trigger(availableNow=True).start()
    q.awaitTermination(120)
    got = spark.table("steps").collect()
    assert [r.outcome for r in got].count("step") == 2 and [r.outcome for r in got].count("repeated") == 1
    assert max(r.version for r in got) == 2


def test_mini_batches_from_a_stream(spark, data, tmp_path):
    from raydescent.streaming.master import MiniBatchDescent

    events = spark.read.parquet(f"{data}/events.parquet")
    events.repartition(4).write.parquet(f"{tmp_path}/events")
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 2).parquet(f"{tmp_path}/events")
    sink = MiniBatchDescent(NetSpec(4, (4,)), coded_scheme(P), 0.5, list(range(8)))
    q = workloads.event_examples(stream, 4).writeStream.foreachBatch(sink).option("checkpointLocation", f"{tmp_path}/ck").trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert len(sink.history) == 2
    ex = workloads.event_examples(events, 4)
    before, after = (gradients.evaluate(ex, {0: w}, sink.layout.spec).first()["loss"] for w in (sink.layout.spec.start(), sink.weights))
    assert after < before
    seen = [w.copy() for w in sink.weights]
    sink(ex, 0)  # delivered again
    assert all(np.array_equal(a, b) for a, b in zip(seen, sink.weights))


def test_stream_joins_and_duplicates(spark, tmp_path):
    from datetime import datetime, timedelta

    from raydescent.streaming.master import deduplicated, messages_with_notices

    t0 = datetime(2024, 1, 1)
    spark.createDataFrame([("r", i, t0 + timedelta(minutes=5 * i)) for i in range(6)], "run_id string, lane int, sent_at timestamp").write.parquet(f"{tmp_path}/m")
    spark.createDataFrame([("r", v, t0 + timedelta(minutes=10 * v)) for v in range(3)], "run_id string, version long, told_at timestamp").write.parquet(f"{tmp_path}/n")
    m, n = (spark.readStream.schema(spark.read.parquet(f"{tmp_path}/{x}").schema).parquet(f"{tmp_path}/{x}") for x in "mn")
    q = messages_with_notices(m, n).writeStream.format("memory").queryName("met").option("checkpointLocation", f"{tmp_path}/c1").trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert {(r.lane, r.version) for r in spark.table("met").collect()} == {(i, v) for i in range(6) for v in range(3) if 0 <= 5 * i - 10 * v <= 10}
    spark.createDataFrame([(1, t0), (1, t0 + timedelta(minutes=1)), (2, t0)], "event_id long, ts timestamp").write.parquet(f"{tmp_path}/e")
    e = spark.readStream.schema("event_id long, ts timestamp").parquet(f"{tmp_path}/e")
    q = deduplicated(e).writeStream.format("memory").queryName("once").option("checkpointLocation", f"{tmp_path}/c2").trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert sorted(r.event_id for r in spark.table("once").collect()) == [1, 2]
