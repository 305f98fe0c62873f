"""Queries that once made their data up: they read a given table, the whole of it, and follow what it holds."""

import math
from collections import Counter

import duckdb
import pytest

from compare import difference
from raydescent.operators import arrivals, codes, geometry, layout
from raydescent.plans.catalog import QUERIES
from raydescent.plans.oracles import ORACLES

#: The table that each reads.
READS = {
    "char_gram_is_identity": "lineitem",
    "char_kron_equals_direct": "lineitem",
    "char_table_t16": "lineitem",
    "char_table_t2": "lineitem",
    "char_table_t4": "lineitem",
    "arrival_charged": "events",
    "arrival_kasync_wait": "events",
    "arrival_kbatch": "events",
    "arrival_ksync": "events",
    "angle_profile_8_4_2": "lineitem",
    "angle_profile_64_32_8": "lineitem",
    "angle_profile_16_8_4": "lineitem",
}


@pytest.mark.parametrize("name", sorted(READS))
def test_reads_its_table(spark, data, name):
    assert [f.rsplit("/", 1)[-1] for f in QUERIES[name](spark, data).inputFiles()] == [f"{READS[name]}.parquet"]


@pytest.mark.parametrize("name", sorted(n for n in READS if n.startswith("angle_profile")))
def test_angles_of_all_pairs(spark, data, name):
    n = int(name.split("_")[2])
    rows = QUERIES[name](spark, data).collect()
    assert sum(r.pairs for r in rows) == n * (n - 1) // 2
    assert any(r.product > n for r in rows)  # rows of the table, not the few columns that lanes share


def test_angles_over_rows_by_hand(spark):
    """Shards of 4, 1, 0 and 9 rows: lanes (0,1), (2,3), (1,2) and (3,0), each with + + and + -."""
    counts = spark.createDataFrame([(0, 4), (1, 1), (3, 9)], "part_id int, rows long")
    got = Counter({(r.product, r.angle): r.pairs for r in geometry.row_angle_profile(codes.projective_code(spark, 4, 2), counts, 8).collect()})
    at = lambda p, a, b: (p, round(math.acos(p / math.sqrt(a * b)), 6))
    want = Counter({at(3, 5, 5): 1, at(9, 9, 9): 1, at(1, 1, 1): 1, at(5, 13, 13): 1, at(1, 5, 1): 4, at(4, 5, 13): 4, at(9, 9, 13): 4})
    want[(0, round(math.pi / 2, 6))] = 28 - sum(want.values())
    assert got == want


def test_angles_of_even_shards_are_the_codes(spark):
    counts = spark.range(8).selectExpr("cast(id AS int) AS part_id", "7L AS rows")
    got = {(r.product, r.pairs) for r in geometry.row_angle_profile(codes.projective_code(spark, 8, 4), counts, 16).collect()}
    assert got == {(0, 88), (14, 32)}


def test_angles_without_rows(spark):
    none = layout.rows_by_shard(spark.createDataFrame([(None,)], "k long"), codes.F.col("k"), 4)
    got = [tuple(r) for r in geometry.row_angle_profile(codes.projective_code(spark, 4, 2), none, 8).collect()]
    assert got == [(0, round(math.pi / 2, 6), 28)]


ARRIVALS = sorted(n for n in READS if n.startswith("arrival"))


@pytest.mark.parametrize("name", ARRIVALS)
def test_every_event_is_a_message(spark, data, name):
    df = QUERIES[name](spark, data)
    run = ["run", "update_no"] if "run" in df.columns else ["update_no"]
    sizes = Counter(r["count"] for r in df.groupBy(*run).count().collect())
    events = spark.read.parquet(f"{data}/events.parquet").count()
    per = 8 if name == "arrival_ksync" else 4
    assert sizes == Counter({per: events // per} | ({events % per: 1} if events % per else {}))


@pytest.mark.parametrize("name", ARRIVALS)
def test_odd_events(spark, tmp_path, name):
    """Gaps, nulls, values that are no waits, equal values, and a first run without any job."""
    odd = [None, math.nan, math.inf, -1.0, 2e9, 0.0, 50.0, 50.0]
    rows = [(i if i % 11 else None, odd[i % 8] if i % 3 == 0 else float(i * 37 % 40)) for i in range(200, 900) if not 400 <= i < 470]
    spark.createDataFrame(rows, "event_id long, value double").repartition(3).write.parquet(f"{tmp_path}/events.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM read_parquet('{tmp_path}/events.parquet/*.parquet')")
    df = QUERIES[name](spark, str(tmp_path))
    assert difference(df, con, ORACLES[name]) == ""
    assert df.count() == sum(i is not None and v is not None and 0 <= v <= 1e9 for i, v in rows)


def test_drain_is_the_schedule_of_a_queue():
    took = [i * 48271 % 997 + 1 for i in range(60)]

    class Queue:
        dead = ()

        def __init__(self):
            self.left = iter(took)

        def of(self, lane, job):
            return next(self.left)

    made = arrivals.drain(took, 8, 4, 5)
    assert made[:13] == arrivals.arrival_schedule(8, 4, 13, "k_async_wait", Queue(), 5)
    assert [len(u.messages) for u in made] == [4] * 15 and sorted(lane for lane, _, _ in made[-1].messages + made[-2].messages) == list(range(8))
    assert [len(u.messages) for u in arrivals.drain(took[:10], 8, 4)] == [4, 4, 2] and arrivals.drain([], 8, 4) == []


def test_charged_jobs_by_hand(spark):
    """Work 3 and transfer 0.5 before a wait of value over 50: lanes 0 and 1 start, the first to deliver takes the third event."""
    events = spark.createDataFrame([(0, 100.0), (1, 50.0), (2, 25.0)], "event_id long, value double")
    jobs = arrivals.event_jobs(events, arrivals.Delays(load=3.0, transfer=0.5))
    got = [tuple(r) for r in arrivals.event_wait_arrivals(jobs, 2, 1, 3, 0.25).orderBy("update_no").collect()]
    assert got == [(0, 0, 1, 0, 4.5, 4.75), (0, 1, 0, 0, 5.5, 5.75), (0, 2, 1, 1, 8.75, 9.0)]
    with pytest.raises(ValueError):
        arrivals.event_jobs(events, arrivals.Delays(dead=(1,)))


def test_batch_by_hand(spark):
    """Two lanes, an update each two messages: lane 1 delivers at 1 and 2, lane 0 at 3 and 4."""
    jobs = spark.createDataFrame([(8, 3_000_000), (9, 1_000_000), (10, 1_000_000), (11, 1_000_000)], "event_id long, took long")
    got = [tuple(r) for r in arrivals.event_batch_arrivals(jobs, 2, 2, 2).orderBy("arrive_at").collect()]
    assert got == [(2, 0, 1, 0, 1.0), (2, 0, 1, 0, 2.0), (2, 1, 0, 0, 3.0), (2, 1, 0, 1, 4.0)]


def test_sync_by_hand(spark):
    """Equal arrivals go by lane; an update with a lane that never delivers has one place less."""
    jobs = spark.createDataFrame([(0, 2_000_000), (1, 1_500_000), (2, 1_500_000), (4, 7), (3, 9_000_000)], "event_id long, took long")
    got = sorted(tuple(r) for r in arrivals.event_sync_arrivals(jobs, 3, 2).collect())
    assert got == [(0, 0, 2.0, 3, False), (0, 1, 1.5, 1, True), (0, 2, 1.5, 2, True), (1, 0, 9.0, 2, True), (1, 1, 0.000007, 1, True)]


@pytest.mark.parametrize("name", sorted(n for n in READS if n.startswith("char_table")))
def test_first_lane_counts_all_rows(spark, data, name):
    """Lane 0 gives every row a plus."""
    rows = QUERIES[name](spark, data).collect()
    assert sum(r.signed_rows for r in rows if r.alpha == 0) == spark.read.parquet(f"{data}/lineitem.parquet").count()
    assert all(r.sign in (1, -1) and r.signed_rows * r.sign > 0 for r in rows)


SHARDS = [(0, 4), (1, 1), (3, 9)]


def test_signs_by_hand(spark):
    counts = spark.createDataFrame(SHARDS, "part_id int, rows long")
    got = {tuple(r) for r in codes.row_sign_table(counts, 4).collect()}
    signs = {0: (1, 1, 1), 1: (1, -1, -1), 2: (1, 1, -1), 3: (1, -1, 1)}
    assert got == {(a, b, s, s * n) for a, row in signs.items() for (b, n), s in zip(SHARDS, row)}
    with pytest.raises(ValueError):
        codes.row_sign_table(counts, 6)


def test_gram_gives_the_rows_back(spark):
    counts = spark.createDataFrame(SHARDS, "part_id int, rows long")
    signed = codes.row_sign_table(counts, 4).select("beta", "alpha", "signed_rows")
    got = {tuple(r) for r in codes.hadamard_report(codes.sign_table(spark, 4), signed).collect()}
    assert got == {(a, b, 4 * n if a == b else 0) for b, n in SHARDS for a in range(b + 1)}


@pytest.mark.parametrize("t", [1, 2, 8])
def test_doubling_gives_the_same_signs(spark, t):
    counts = spark.range(t).selectExpr("cast(id AS int) AS part_id", "id * id + 1 AS rows")
    assert sorted(codes.row_sign_table_kron(counts, t).collect()) == sorted(codes.row_sign_table(counts, t).collect())
    assert sorted(codes.sign_table_kron(spark, t).collect()) == sorted(codes.sign_table(spark, t).collect())
