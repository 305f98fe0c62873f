"""The registered queries against their SQL, and the pipeline stage by stage."""

import pytest

from compare import connect, difference
from raydescent.llm.queries import ORACLES, QUERIES


@pytest.mark.parametrize("name", sorted(QUERIES))
def test_query(spark, data, name):
    df = QUERIES[name](spark, data)
    if name in ORACLES:
        assert difference(df, connect(data), ORACLES[name]) == ""
    else:
        assert df.count() >= (50 if name != "op8_histogram_packing" else 200)


def test_pipeline(spark, data):
    import corpus_pipeline as p
    from raydescent.llm.common import cut, table

    docs = table(spark, data, "documents")
    seen = [docs.count()]
    for name, stage in p.STAGES[:-1]:
        out = cut(stage(spark, docs, data), name)
        assert out.columns == docs.columns
        ids = {r.doc_id for r in docs.select("doc_id").collect()}
        assert {r.doc_id for r in out.select("doc_id").collect()} <= ids
        docs = out
        seen.append(docs.count())
    assert seen[1] == seen[0] and seen[1] > seen[2] >= seen[3] > 0.5 * seen[0]
    packed = p.STAGES[-1][1](spark, docs, data)
    assert packed.select("doc_id").distinct().count() == seen[3]
    assert p.run(spark, data).count() == packed.count()


def test_native_plans(spark, data):
    """The licence scan and the url rules stay in the JVM, and nothing is multiplied out."""
    for name in ("op1_host_reputation", "op6_license_votes"):
        plan = QUERIES[name](spark, data)._jdf.queryExecution().executedPlan().toString()
        assert "Python" not in plan and "InArrow" not in plan and "Cartesian" not in plan and "NestedLoop" not in plan, name


def test_hot_keys_are_spread(spark):
    """A key with nearly all rows goes by broadcast; the result is that of a plain join."""
    from pyspark.sql import functions as F

    from raydescent.llm.common import skew_safe_lookup

    rows = spark.range(20_000).select("id", F.when(F.col("id") % 10 > 0, "hot").when(F.col("id") % 100 == 0, None).otherwise(F.col("id").cast("string")).alias("key"))
    facts = rows.where("key IS NOT NULL").groupBy("key").agg(F.count("*").alias("n"), F.min("id").alias("low"))
    got = skew_safe_lookup(rows, facts, "key", "n", 20_000)
    want = rows.join(facts, "key", "left").select("id", "key", "n", "low")
    assert got.exceptAll(want).isEmpty() and want.exceptAll(got).isEmpty() and got.count() == 20_000


def test_hot_rows_go_by_their_own_values(spark):
    """No running number decides where a row goes, so that a task that is run again deals its rows as before; and
    helper columns give way to columns of rows."""
    from pyspark.sql import functions as F

    from raydescent.llm.common import skew_safe_lookup

    rows = spark.range(3000).select(F.lit("hot").alias("key"), "id", F.lit(1).alias("_hk"), F.lit(2).alias("_f"), F.create_map(F.lit("a"), "id").alias("m"))
    facts = spark.createDataFrame([("hot", 3000, 5)], "key string, n long, low long")
    got = skew_safe_lookup(rows, facts, "key", "n", 3000)
    assert "monotonically" not in got._jdf.queryExecution().toString().lower()
    assert got.columns == ["key", "id", "_hk", "_f", "m", "n", "low"] and got.where("_hk = 1 AND _f = 2 AND low = 5").count() == 3000


def test_owned_cuts_are_removed(spark):
    from raydescent.llm.common import cut, cuts, owned_cuts

    before = cuts(spark)
    with owned_cuts(spark):
        assert cut(spark.range(5), "mine").count() == 5 and len(cuts(spark)) == len(before) + 1
    assert cuts(spark) == before
