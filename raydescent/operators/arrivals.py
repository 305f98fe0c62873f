"""When messages arrive. Delays do not depend on gradient values, so the whole schedule of a run is made before it."""

from __future__ import annotations

import heapq
import math
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from raydescent.operators.layout import uniform


@dataclass(frozen=True)
class Delays:
    """A job takes work for every n-th of the rows that its lane handles (load of them), plus an exponential wait of this
    mean; slow lanes take slow_factor times as long, dead ones for ever. Its message then is under way for transfer."""

    work: float = 1.0
    mean: float = 1.0
    seed: int = 1
    slow: tuple[int, ...] = ()
    slow_factor: float = 8.0
    dead: tuple[int, ...] = ()
    load: float = 1.0
    transfer: float = 0.0

    def key(self, lane: int, job: int) -> int:
        return self.seed * 1_000_003 + lane * 10_007 + job * 101 + 17

    def of(self, lane: int, job: int) -> float:
        if lane in self.dead:
            return math.inf
        u = (self.key(lane, job) % 2147483647 * 48271 % 2147483647 + 0.5) / 2147483647.0
        return (self.work * self.load - self.mean * math.log(u)) * (self.slow_factor if lane in self.slow else 1.0) + self.transfer

    def column(self, lane: Column, job: Column) -> Column:
        u = uniform(F.lit(self.seed * 1_000_003 + 17) + lane * 10_007 + job * 101)
        base = F.lit(self.work * self.load) - self.mean * F.log(u)
        slow = (base * F.when(lane.isin(*self.slow), self.slow_factor).otherwise(1.0) if self.slow else base) + self.transfer
        return F.when(lane.isin(*self.dead), F.lit(None)).otherwise(slow) if self.dead else slow


@dataclass(frozen=True)
class Update:
    """The messages (lane, version read, arrival) that make an update, and when it is made."""

    number: int
    messages: tuple[tuple[int, int, float], ...]
    at: float


class LanesLost(RuntimeError):
    """Fewer lanes are alive than an update needs."""


def arrival_schedule(n: int, K: int, updates: int, policy: str = "k_async_wait", delays: Delays = Delays(), solve: float = 0.0) -> list[Update]:
    """The updates of a run, by policy; each is made solve after its last message.

    k_async_wait: after K messages the weights are changed and only the lanes that delivered start anew, on them.
    k_batch_async: a lane starts again at once, on the weights of that moment.
    k_sync: all lanes start on each version, and those that are not among the first K are stopped.
    full_sync: K = n. With fewer than K lanes alive (for k_batch_async: none) a run is refused: LanesLost.
    """
    if policy == "full_sync":
        K, policy = n, "k_sync"
    alive = n - len({lane for lane in delays.dead if 0 <= lane < n})
    if alive < (1 if policy == "k_batch_async" else K):
        raise LanesLost(f"{alive} of {n} lanes are alive, and an update by {policy} needs {K} messages")
    out: list[Update] = []
    jobs = [0] * n

    def start(lane: int, now: float, version: int) -> tuple[float, int, int]:
        jobs[lane] += 1
        return now + delays.of(lane, jobs[lane] - 1), lane, version

    if policy == "k_sync":
        now = 0.0
        for u in range(updates):
            due = sorted(start(lane, now, u) for lane in range(n))[:K]
            now = due[-1][0] + solve
            out.append(Update(u, tuple((lane, v, at) for at, lane, v in due), now))
        return out
    if policy not in ("k_async_wait", "k_batch_async"):
        raise ValueError(f"unknown policy {policy}")
    heap = [start(lane, 0.0, 0) for lane in range(n)]
    heapq.heapify(heap)
    while len(out) < updates:
        got: list[tuple[int, int, float]] = []
        while len(got) < K:
            at, lane, version = heapq.heappop(heap)
            got.append((lane, version, at))
            if policy == "k_batch_async":
                heapq.heappush(heap, start(lane, at, len(out) + (len(got) == K)))
        now = got[-1][2] + solve
        out.append(Update(len(out), tuple(got), now))
        if policy == "k_async_wait":
            for lane, _, _ in got:
                heapq.heappush(heap, start(lane, now, len(out)))
    return out


def schedule_table(spark: SparkSession, schedule: list[Update]) -> DataFrame:
    """update_no, lane, read_version, arrive_at, updated_at."""
    rows = [(u.number, lane, v, at, u.at) for u in schedule for lane, v, at in u.messages]
    return spark.createDataFrame(rows, "update_no long, lane int, read_version long, arrive_at double, updated_at double")


def sync_arrivals(spark: SparkSession, n: int, K: int, updates: int, delays: Delays = Delays()) -> DataFrame:
    """k_sync as a relation: update_no, lane, read_version, arrive_at (from the update's start), place, taken."""
    jobs = spark.range(n * updates).select((F.col("id") / n).cast("long").alias("update_no"), (F.col("id") % n).cast("int").alias("lane"))
    due = jobs.withColumn("arrive_at", delays.column(F.col("lane"), F.col("update_no"))).where("arrive_at IS NOT NULL")
    place = F.row_number().over(Window.partitionBy("update_no").orderBy("arrive_at", "lane"))
    return due.withColumn("place", place).select("update_no", "lane", F.col("update_no").alias("read_version"), "arrive_at", "place", (F.col("place") <= K).alias("taken"))


def batch_arrivals(spark: SparkSession, n: int, K: int, updates: int, delays: Delays = Delays()) -> DataFrame:
    """k_batch_async as a relation: every lane's arrivals are running sums of its delays; each K in order make an update."""
    jobs = spark.range(n * (updates * K + 1)).select((F.col("id") % n).cast("int").alias("lane"), (F.col("id") / n).cast("long").alias("job"))
    due = jobs.withColumn("d", delays.column(F.col("lane"), F.col("job"))).where("d IS NOT NULL")
    clock = due.withColumn("arrive_at", F.sum("d").over(Window.partitionBy("lane").orderBy("job").rowsBetween(Window.unboundedPreceding, 0)))
    seq = F.row_number().over(Window.orderBy("arrive_at", "lane")) - 1  # of a schedule, whose length is lanes times updates
    placed = clock.withColumn("seq", seq.cast("long")).withColumn("update_no", F.expr(f"seq div {K}"))
    read = F.coalesce(F.expr(f"(lag(seq) OVER (PARTITION BY lane ORDER BY job) + 1) div {K}"), F.lit(0).cast("long"))
    return placed.withColumn("read_version", read).where(F.col("update_no") < updates).select("update_no", "lane", "read_version", "arrive_at", "seq")


def staleness(schedule: DataFrame) -> DataFrame:
    """staleness, messages: how many versions behind the messages are."""
    return schedule.groupBy((F.col("update_no") - F.col("read_version")).alias("staleness")).agg(F.count("*").alias("messages"))


def wait_profile(schedule: DataFrame) -> DataFrame:
    """update_no, first_at, last_at, waited: how long the first message of an update lies before the last."""
    by = schedule.groupBy("update_no").agg(F.min("arrive_at").alias("first_at"), F.max("arrive_at").alias("last_at"))
    return by.withColumn("waited", F.col("last_at") - F.col("first_at"))


#: Arrivals of a table's jobs are whole numbers of ticks to the second: sums come out the same in any order, and equal ones stay equal.
TICKS = 1_000_000


def event_jobs(events: DataFrame, delays: Delays, mean: float = 50.0) -> DataFrame:
    """event_id, took (ticks): every event is a job. Its wait is its value over the values' mean, in place of the wait by hash.

    An event without a number, or whose value is null, negative, not finite or over a thousand million, is a job that never ends.
    """
    if delays.slow or delays.dead:
        raise ValueError("slow and dead lanes of a table's jobs are those of its values")
    base = round((delays.work * delays.load + delays.transfer) * TICKS)
    wait = F.floor(F.col("value") * (delays.mean * TICKS / mean)).cast("long")
    return events.where("event_id IS NOT NULL AND value BETWEEN 0 AND 1e9").select("event_id", (F.lit(base) + wait).alias("took"))


def event_sync_arrivals(jobs: DataFrame, n: int, K: int) -> DataFrame:
    """k_sync over a whole table: each n events in a row are the jobs of an update. update_no, lane, arrive_at (from the update's start), place, taken."""
    due = jobs.select(F.expr(f"event_id div {n}").alias("update_no"), (F.col("event_id") % n).cast("int").alias("lane"), "took")
    place = F.row_number().over(Window.partitionBy("update_no").orderBy("took", "lane"))
    return due.withColumn("place", place).select("update_no", "lane", (F.col("took") / TICKS).alias("arrive_at"), "place", (F.col("place") <= K).alias("taken"))


def event_batch_arrivals(jobs: DataFrame, n: int, K: int, updates: int) -> DataFrame:
    """k_batch_async over a whole table: each K times updates events in a row are the jobs of a run, dealt to its lanes in turn.

    run, update_no, lane, read_version, arrive_at (from the run's start). Every job has a row; only a run with jobs that never end can have
    a last update of fewer than K messages.
    """
    size = K * updates
    dealt = jobs.select(F.expr(f"event_id div {size}").alias("run"), (F.col("event_id") % size % n).cast("int").alias("lane"), F.expr(f"event_id % {size} div {n}").alias("job"), "took")
    turn = Window.partitionBy("run", "lane").orderBy("job", "took")
    clock = dealt.withColumn("at", F.sum("took").over(turn.rowsBetween(Window.unboundedPreceding, 0)))
    placed = clock.withColumn("seq", (F.row_number().over(Window.partitionBy("run").orderBy("at", "lane")) - 1).cast("long"))
    read = placed.withColumn("before", F.lag("seq").over(turn))
    return read.select("run", F.expr(f"seq div {K}").alias("update_no"), "lane", F.expr(f"coalesce((before + 1) div {K}, 0L)").alias("read_version"), (F.col("at") / TICKS).alias("arrive_at"))


def drain(took: list, n: int, K: int, solve=0) -> list[Update]:
    """k_async_wait until a queue of jobs is done: the first n start at once, and after each update its lanes take the next ones.

    The last update has the messages that are left, which may be fewer than K.
    """
    heap = [(t, lane, 0) for lane, t in enumerate(took[:n])]
    heapq.heapify(heap)
    out: list[Update] = []
    ahead = iter(took[n:])
    while heap:
        got = [heapq.heappop(heap) for _ in range(min(K, len(heap)))]
        now = got[-1][0] + solve
        out.append(Update(len(out), tuple((lane, v, at) for at, lane, v in got), now))
        for (_, lane, _), t in zip(got, ahead):
            heapq.heappush(heap, (now + t, lane, len(out)))
    return out


def event_wait_arrivals(jobs: DataFrame, n: int, K: int, updates: int, solve: float = 0.0) -> DataFrame:
    """k_async_wait over a whole table: each K times updates events in a row are the jobs of a run, started in their order.

    run, update_no, lane, read_version, arrive_at, updated_at (from the run's start). Every job has a row.
    """
    late = round(solve * TICKS)
    queues = jobs.groupBy(F.expr(f"event_id div {K * updates}").alias("run")).agg(F.sort_array(F.collect_list(F.struct("event_id", "took"))).alias("q")).select("run", F.col("q.took").alias("took"))

    def play(batches):
        for pdf in batches:
            for first in range(0, len(pdf), 256):  # a run has as many rows as jobs
                some = pdf.iloc[first : first + 256]
                rows = [(run, u.number, lane, v, at, u.at) for run, took in zip(some["run"].tolist(), some["took"]) for u in drain(took.tolist(), n, K, late) for lane, v, at in u.messages]
                yield pd.DataFrame(rows, columns=["run", "update_no", "lane", "read_version", "at", "made"])

    played = queues.mapInPandas(play, "run long, update_no long, lane int, read_version long, at long, made long")
    return played.select("run", "update_no", "lane", "read_version", (F.col("at") / TICKS).alias("arrive_at"), (F.col("made") / TICKS).alias("updated_at"))
