"""Live masters: the step on arrival as a stateful stream, and mini-batch descent over a stream of examples."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from raydescent.operators.lanes import Scheme, apply_message, lane_messages
from raydescent.operators.gradients import shard_gradients
from raydescent.plans.models import GroupLayout, NetSpec

STEP_SCHEMA = "run_id string, version long, lane int, staleness long, outcome string, norm double"
STEP_COLUMNS = [c.split()[0] for c in STEP_SCHEMA.split(", ")]


def stateful_master(messages: DataFrame, scheme: Scheme, layout: GroupLayout, K: int, lr: float, n_train: int, most_stale: int = 8, idle: int | None = None) -> DataFrame:
    """messages (run_id, seq, lane, read_version, payload array<double>) as a stream to the steps they cause.

    State of a run: weights, version and the messages waiting. A step is made of K messages in order of seq. A message
    more than most_stale versions behind is dropped and reported as such; a lane's repeated message (same seq) too. The
    state of a run that sends nothing for idle milliseconds is let go, which is reported as expired; with idle, the stream
    makes batches for ever, also under a trigger that takes what is there.
    """
    by_lane = {lane: [r[1:] for r in scheme.decode if r[0] == lane] for lane in range(scheme.n)}
    parameters = scheme.t * layout.block

    def run(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            version, *_ = state.get
            state.remove()
            yield pd.DataFrame([(key[0], version, -1, 0, "expired", 0.0)], columns=STEP_COLUMNS)
            return
        version, last, flat, waiting = state.get if state.exists else (0, -1, [0.0] * parameters, [0.0] * 0)
        weights = np.array(flat).reshape(scheme.t, layout.block)
        total, held = np.zeros_like(weights), 0
        if len(waiting):
            total, held = np.array(waiting[1:]).reshape(total.shape), int(waiting[0])
        out = []
        rows = pd.concat(list(frames)).sort_values(["seq", "lane"])
        for r in rows.itertuples():
            behind = version - r.read_version
            if r.seq <= last:
                out.append((key[0], version, r.lane, behind, "repeated", 0.0))
                continue
            last = r.seq
            if behind > most_stale:
                out.append((key[0], version, r.lane, behind, "stale", 0.0))
                continue
            apply_message(total, np.asarray(r.payload, float).reshape(scheme.slots, layout.block), by_lane[r.lane])
            held += 1
            outcome = "held"
            if held == K:
                step = lr * total / (n_train * scheme.rows_share * K)
                weights = weights - step
                total, held, version, outcome = np.zeros_like(total), 0, version + 1, "step"
            out.append((key[0], version, r.lane, behind, outcome, float(np.sqrt((weights**2).sum()))))
        state.update((version, int(last), weights.ravel().tolist(), [float(held), *total.ravel().tolist()] if held else []))
        if idle is not None:
            state.setTimeoutDuration(idle)
        yield pd.DataFrame(out, columns=STEP_COLUMNS)

    schema = "version long, last long, weights array<double>, waiting array<double>"
    return messages.groupBy("run_id").applyInPandasWithState(run, STEP_SCHEMA, schema, "append", GroupStateTimeout.NoTimeout if idle is None else GroupStateTimeout.ProcessingTimeTimeout)


class MiniBatchDescent:
    """foreachBatch sink: every micro-batch of examples makes one coded step from the lanes given. Batches are known by
    their number, so that one that is delivered again changes nothing."""

    def __init__(self, spec: NetSpec, scheme: Scheme, lr: float, lanes: list[int]):
        self.layout = GroupLayout(spec, scheme.t)
        self.scheme, self.lr, self.lanes = scheme, lr, lanes
        self.weights, self.seen, self.history = spec.start(), -1, []

    def __call__(self, batch: DataFrame, number: int) -> None:
        if number <= self.seen:
            return
        self.seen = number
        rows = batch.where("split = 'train'")
        n = rows.count()
        if not n:
            return
        wanted = {s: [0] for lane in self.lanes for s in self.scheme.shards_of(lane)}
        cells = shard_gradients(rows, {0: self.weights}, wanted, self.layout)
        sent = lane_messages(cells, self.scheme.encode_table(batch.sparkSession).where(F.col("lane").isin(self.lanes)))
        total = np.zeros((self.scheme.t, self.layout.block))
        for r in sent.groupBy("lane", "slot").agg(F.collect_list("pos").alias("p"), F.collect_list("value").alias("v")).collect():
            payload = np.zeros((self.scheme.slots, self.layout.block))
            payload[r["slot"], r["p"]] = r["v"]
            apply_message(total, payload, [d[1:] for d in self.scheme.decode if d[0] == r["lane"]])
        total /= n * self.scheme.rows_share * len(self.lanes)
        self.weights = [w - self.lr * g for w, g in zip(self.weights, self.layout.merge(total))]
        self.history.append((number, n))


def deduplicated(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Events without those whose id came before within the watermark."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def window_sums(events: DataFrame, width: str = "1 hour", slide: str | None = None, delay: str = "1 hour") -> DataFrame:
    """window start, event_type, n, total of tumbling or sliding windows; late beyond the delay is dropped."""
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.withWatermark("ts", delay).groupBy(window.alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", "total")


def sessions(events: DataFrame, gap: str = "30 minutes", delay: str = "1 hour") -> DataFrame:
    """user_id, start, n of each user's sessions."""
    s = events.withWatermark("ts", delay).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return s.select("user_id", F.col("w.start").alias("start"), "n")


def messages_with_notices(messages: DataFrame, notices: DataFrame, reach: str = "10 minutes", delay: str = "10 minutes") -> DataFrame:
    """Two streams joined by interval: messages (run_id, lane, sent_at) with the update notices (run_id, version, told_at)
    that came within reach before them. State older than the watermarks is let go."""
    m = messages.withWatermark("sent_at", delay).alias("m")
    n = notices.withWatermark("told_at", delay).alias("n")
    met = F.expr(f"m.run_id = n.run_id AND n.told_at <= m.sent_at AND n.told_at >= m.sent_at - INTERVAL {reach}")
    return m.join(n, met).select("m.run_id", "m.lane", "m.sent_at", "n.version", "n.told_at")
