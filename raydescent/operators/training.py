"""Descent with coded messages and its rivals, on a virtual clock over real gradients.

The schedule of arrivals is made first. For each update one Spark job computes the gradients that its messages need (all
read versions in one scan, only the shards of its lanes), encodes them in the tasks, adds the parts up and brings
K messages to the driver, which adds them into the weights. Weights of versions that no lane will read again are let go;
those to be judged are judged some at a time.
"""

from __future__ import annotations

import time
from concurrent.futures import FIRST_COMPLETED, ThreadPoolExecutor, wait
from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from raydescent.operators.arrivals import Delays, Update, arrival_schedule
from raydescent.operators.exact_coding import ExactCode, RepetitionCode
from raydescent.operators.gradients import LONG_BLOCK, Kernel, coded_sums, evaluate
from raydescent.operators.lanes import Scheme, apply_message, rotated_scheme
from raydescent.plans.models import GroupLayout, NestedLayout, NetSpec, gradients
from raydescent.plans.params import Embedding

CURVE = "run_id string, scheme string, update_no long, virtual_time double, wall_time double, train_loss double, test_loss double, test_error double, floats_sent long"


#: Versions that are judged in one scan.
JUDGED = 16


@dataclass(frozen=True)
class Costs:
    """What the virtual clock charges besides the delays: rows (whether work grows with the rows that a lane handles),
    seconds for a number sent, and for the master's solve, solve times k^2.38. All of it delays what comes after."""

    rows: bool = False
    sent: float = 0.0
    solve: float = 0.0

    def on(self, delays: Delays, load: float, numbers: int) -> Delays:
        return replace(delays, load=load if self.rows else delays.load, transfer=delays.transfer + self.sent * numbers)


@dataclass
class FitResult:
    weights: list[np.ndarray]
    curve: list[tuple] = field(default_factory=list)
    updates: int = 0

    def table(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.curve, CURVE)


def collect_messages(examples: DataFrame, versions: dict[int, list[np.ndarray]], scheme: Scheme, messages: tuple[tuple[int, int, float], ...], layout: GroupLayout, kernel: Kernel = gradients, scan: str = "shared") -> list[np.ndarray]:
    """The payloads (slots x block) of one update's messages, in their order.

    scan 'shared' computes each shard's gradient once per version, whatever the number of its lanes; 'per_lane' has every
    lane's shards computed for itself, as separate machines would.
    """
    out = {m[:2]: np.zeros((scheme.slots, layout.block)) for m in messages}
    for some in [list(out)] if scan == "shared" else [[m] for m in out]:
        on = {m[0] for m in some}
        encode = [r for r in scheme.encode if r[0] in on]
        if not encode:
            continue
        sent: list = []
        got = coded_sums(examples, versions, some, encode, scheme.slots, layout, kernel, sent).toArrow()  # K messages
        lane, version, slot, first = (got.column(c).to_numpy() for c in ("lane", "version", "slot", "first"))
        if layout.block <= LONG_BLOCK:
            value = got.column("values").combine_chunks().flatten().to_numpy()
            for m in some:
                at = (lane == m[0]) & (version == m[1])
                out[m][slot[at], first[at]] = value[at]
        else:
            for i, values in enumerate(got.column("values")):
                x = values.values.to_numpy()
                out[int(lane[i]), int(version[i])][slot[i], first[i] : first[i] + len(x)] = x
        for held in sent:
            held.destroy()
    return [out[m[:2]] for m in messages]


def _step(spec, layout, weights, total, lr):
    return [w - lr * g for w, g in zip(weights, layout.merge(total))]


def fit(
    examples: DataFrame,
    spec: NetSpec,
    scheme: Scheme | ExactCode | RepetitionCode | Embedding,
    schedule: list[Update],
    lr: float,
    *,
    run_id: str = "run",
    every: int = 5,
    start: list[np.ndarray] | None = None,
    axis: str = "output",
    layout: GroupLayout | NestedLayout | None = None,
    kernel: Kernel = gradients,
    scan: str = "shared",
) -> FitResult:
    """Train on the rows of examples (part_id, split, x, y) whose split is train, by the given schedule.

    Averaging schemes divide a message by the number of examples it is expected to speak for, and their sum by the
    number of messages, so that lr is the step on the mean gradient. An exact code solves for the whole sum. An
    Embedding takes the allocation of a new wave at every update. The curve has the mean losses on train and test.
    layout: how the model is cut into groups, where it is not GroupLayout(spec, scheme.t, axis).
    """
    exact = scheme if isinstance(scheme, (ExactCode, RepetitionCode)) else None
    torus = scheme if isinstance(scheme, Embedding) else None
    plan = exact.scheme() if exact else rotated_scheme(torus, 0) if torus else scheme
    layout = layout or GroupLayout(spec, plan.t, axis)
    train, test = examples.where("split = 'train'"), examples.where("split = 'test'")
    n_train = train.count()
    weights = [w.copy() for w in start] if start else spec.start()
    versions = {0: weights}
    result = FitResult(weights)
    began, sent, clock, pending = time.time(), 0, 0.0, []
    last_read: dict[int, int] = {}
    for u in schedule:
        for _, v, _ in u.messages:
            last_read[v] = u.number

    def judge() -> None:
        broadcasts: list = []
        held = {p[0]: p[4] for p in pending}
        on_train, on_test = ({r["version"]: r for r in evaluate(rows, held, spec, sent=broadcasts).collect()} for rows in (train, test))
        for number, at, wall, floats, _ in pending:
            a, b = on_train.get(number), on_test.get(number)
            result.curve.append((run_id, plan.name if not torus else "coded_rotated", number, at, wall, a and a["loss"], b and b["loss"], b and b["error"], floats))
        for x in broadcasts:
            x.destroy()
        pending.clear()

    def record(number: int) -> None:
        pending.append((number, clock, time.time() - began, sent, weights))
        if len(pending) == JUDGED:
            judge()

    record(0)
    for u in schedule:
        if torus:
            plan = rotated_scheme(torus, u.number)
        payloads = collect_messages(train, versions, plan, u.messages, layout, kernel, scan)
        total = np.zeros((plan.t, layout.block))
        if exact:
            for c, payload in zip(exact.solve([m[0] for m in u.messages]), payloads):
                total += c * payload
            total /= n_train
        else:
            for (lane, _, _), payload in zip(u.messages, payloads):
                apply_message(total, payload, [r[1:] for r in plan.decode if r[0] == lane])
            total /= n_train * plan.rows_share * len(u.messages)
        sent += len(u.messages) * message_numbers(plan, layout)
        clock = u.at
        weights = _step(spec, layout, weights, total, lr)
        versions[u.number + 1] = weights
        for v in [v for v in versions if v <= u.number and last_read.get(v, -1) <= u.number]:
            del versions[v]
        result.updates += 1
        if (u.number + 1) % every == 0 or u is schedule[-1]:
            record(u.number + 1)
    if pending:
        judge()
    result.weights = weights
    return result


def message_numbers(scheme: Scheme, layout: GroupLayout | NestedLayout) -> int:
    return layout.numbers if isinstance(layout, NestedLayout) else scheme.slots * layout.block


def fit_coded(examples, spec, params, updates, lr, K=None, policy="k_async_wait", delays=Delays(), mode="support", scaling="sign", rotate=False, nested=False, costs=Costs(), axis="output", **more) -> FitResult:
    """Coded descent; K defaults to k, the number of shards. rotate: params is an Embedding and the allocation moves each
    update. nested: the layers of a network are cut by repeated splitting."""
    from raydescent.operators.lanes import coded_scheme, nested_scheme

    if nested:
        scheme, layout = nested_scheme(params, len(spec.outputs)), NestedLayout(spec, params.t)
    else:
        scheme = rotated_scheme(params, 0) if rotate else coded_scheme(params, mode, scaling)
        layout = GroupLayout(spec, scheme.t, axis)
    schedule = arrival_schedule(params.n, K or params.k, updates, policy, costs.on(delays, scheme.load, message_numbers(scheme, layout)))
    return fit(examples, spec, params if rotate else scheme, schedule, lr, layout=layout, **more)


def fit_uncoded(examples, spec, params, updates, lr, K=None, policy="k_async_wait", delays=Delays(), costs=Costs(), **more) -> FitResult:
    from raydescent.operators.lanes import uncoded_scheme

    scheme = uncoded_scheme(params)
    return fit(examples, spec, scheme, arrival_schedule(params.n, K or params.k, updates, policy, costs.on(delays, scheme.load, GroupLayout(spec, 1).block)), lr, **more)


def fit_exact(examples, spec, code: ExactCode | RepetitionCode, updates, lr, delays=Delays(), costs=Costs(), **more) -> FitResult:
    """Exact coding is synchronous: every lane works on the newest weights and the first k messages give the sum. examples
    must have n shards. With more than n - k lanes lost the run is refused (LanesLost)."""
    charged = costs.on(delays, code.weight, GroupLayout(spec, 1).block)
    solve = costs.solve * code.k**2.38 if isinstance(code, ExactCode) else 0.0  # repetition has nothing to solve
    return fit(examples, spec, code, arrival_schedule(code.n, code.k, updates, "k_sync", charged, solve), lr, **more)


def fit_sync(examples, spec, n: int, updates, lr, delays=Delays(), costs=Costs(), **more) -> FitResult:
    from raydescent.operators.lanes import synchronous_scheme

    return fit(examples, spec, synchronous_scheme(n), arrival_schedule(n, n, updates, "full_sync", costs.on(delays, 1.0, GroupLayout(spec, 1).block)), lr, **more)


def fit_live(examples: DataFrame, spec: NetSpec, scheme: Scheme, K: int, updates: int, lr: float, start: list[np.ndarray] | None = None, slow: dict[int, float] | None = None) -> FitResult:
    """The same descent with real arrivals: a Spark job per lane from a pool of driver threads.

    The master steps as soon as K jobs have come in, the lanes that delivered start on the new weights, and the others'
    jobs go on. slow: extra seconds per lane, for trials.
    """
    spark = examples.sparkSession
    layout, train = GroupLayout(spec, scheme.t), examples.where("split = 'train'")
    n_train = train.count()
    weights = start or spec.start()
    result, sent, began = FitResult(weights), 0, time.time()

    def work(lane: int, version: int, w: list[np.ndarray]):
        time.sleep((slow or {}).get(lane, 0.0))
        spark.addTag(f"lane-{lane}")
        (payload,) = collect_messages(train, {version: w}, scheme, ((lane, version, 0.0),), layout)
        return lane, version, payload

    with ThreadPoolExecutor(scheme.n) as pool:
        running = {pool.submit(work, lane, 0, weights) for lane in range(scheme.n)}
        held: list[tuple] = []
        while result.updates < updates:
            done, running = wait(running, return_when=FIRST_COMPLETED)
            held += [d.result() for d in done]
            while len(held) >= K and result.updates < updates:
                some, held = held[:K], held[K:]
                total = np.zeros((scheme.t, layout.block))
                for lane, _, payload in some:
                    apply_message(total, payload, [r[1:] for r in scheme.decode if r[0] == lane])
                weights = _step(spec, layout, weights, total / (n_train * scheme.rows_share * K), lr)
                result.updates += 1
                sent += K * scheme.slots * layout.block
                result.curve.append(("live", scheme.name, result.updates, time.time() - began, time.time() - began, None, None, None, sent))
                if result.updates < updates:
                    running |= {pool.submit(work, lane, result.updates, weights) for lane, _, _ in some}
        for f in running:
            f.cancel()
        for lane in range(scheme.n):
            spark.interruptTag(f"lane-{lane}")
    result.weights = weights
    return result
