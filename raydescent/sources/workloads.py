"""The experiments' inputs on the given tables, as examples (row_key, part_id, split, x, y).

Most labels in these tables carry no signal, so that convergence runs plant labels; gradients are also taken on the real ones.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from raydescent.operators.codes import hash_step, parity_sign
from raydescent.sources.tables import examples_from, load_table

#: Centres and spreads that bring money and quantity columns near unit size.
LINE_SCALE = (("l_quantity", 25.0, 15.0), ("l_extendedprice", 53000.0, 30000.0), ("l_discount", 0.05, 0.03), ("l_tax", 0.04, 0.03))


def embedding_examples(spark: SparkSession, sf_dir: str, k: int, delta: float = 0.0) -> DataFrame:
    """Real vectors and labels; delta > 0 moves each vector by delta towards its label's centre, a row of the sign table."""
    df = load_table(spark, sf_dir, "embeddings", "vec_id", "embedding", "label")
    x = F.col("embedding").cast("array<double>")
    if delta:
        x = F.transform(x, lambda v, j: v + delta * parity_sign(F.col("label") + 1, j) / 8.0)
    return examples_from(df, "vec_id", x, F.col("label"), k)


def _line_keys(df: DataFrame) -> DataFrame:
    return df.withColumn("row_key", F.col("l_orderkey") * 8 + F.col("l_linenumber"))


def _line_x():
    scaled = [(F.col(c) - mid) / wide for c, mid, wide in LINE_SCALE]
    turn = F.month("l_shipdate") * (2 * math.pi / 12)
    return F.array(*scaled, F.sin(turn), F.cos(turn))


def lineitem_examples(spark: SparkSession, sf_dir: str, k: int, real: bool = False) -> DataFrame:
    """Six features of a line; planted class: quarter of a linear score with hashed noise. real: flag and status, six classes at most."""
    cols = ("l_orderkey", "l_linenumber", *(c for c, *_ in LINE_SCALE), "l_shipdate", *(("l_returnflag", "l_linestatus") if real else ()))
    df = _line_keys(load_table(spark, sf_dir, "lineitem", *cols)).withColumn("x", _line_x())
    if real:
        flag = F.when(F.col("l_returnflag") == "A", 0).when(F.col("l_returnflag") == "N", 1).otherwise(2)
        y = flag * 2 + F.when(F.col("l_linestatus") == "F", 0).otherwise(1)
    else:
        noise = (hash_step(hash_step(F.col("row_key") + 31)) % 1000) / 1000.0 - 0.5
        score = F.col("x")[0] + F.col("x")[1] - F.col("x")[2] + 0.5 * F.col("x")[3] + 0.5 * noise
        y = F.when(score < -1, 0).when(score < 0, 1).when(score < 1, 2).otherwise(3)
    return examples_from(df, "row_key", F.col("x"), y, k)


def regression_examples(spark: SparkSession, sf_dir: str, k: int) -> DataFrame:
    """lineitem with the retail price of its part: planted y linear in quantity, price and discount."""
    line = _line_keys(load_table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_partkey", "l_quantity", "l_discount"))
    part = load_table(spark, sf_dir, "part", "p_partkey", "p_retailprice")
    df = line.join(part, F.col("l_partkey") == F.col("p_partkey"))
    x = F.array((F.col("l_quantity") - 25) / 15, (F.col("p_retailprice") - 950) / 50, (F.col("l_discount") - 0.05) / 0.03)
    noise = (hash_step(F.col("row_key") + 31) % 1000) / 1000.0 - 0.5
    return examples_from(df, "row_key", x, 2 * x[0] - x[1] + 0.5 * x[2] + noise, k)


def priority_examples(spark: SparkSession, sf_dir: str, k: int) -> DataFrame:
    """orders with customer and nation: price, balance, month and region one-hot; class: order priority (5)."""
    orders = load_table(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_totalprice", "o_orderdate", "o_orderpriority")
    customer = load_table(spark, sf_dir, "customer", "c_custkey", "c_nationkey", "c_acctbal")
    nation = load_table(spark, sf_dir, "nation", "n_nationkey", "n_regionkey")
    df = orders.join(customer, F.col("o_custkey") == F.col("c_custkey")).join(nation, F.col("c_nationkey") == F.col("n_nationkey"))
    region = [(F.col("n_regionkey") == r).cast("double") for r in range(5)]
    x = F.array((F.col("o_totalprice") - 250000) / 144000, (F.col("c_acctbal") - 4500) / 3000, (F.month("o_orderdate") - 6.5) / 3.5, *region)
    return examples_from(df, "o_orderkey", x, F.substring("o_orderpriority", 1, 1).cast("int") - 1, k)


def text_number(text):
    """A number of 32 bits from a text's checksum, which SQL engines agree on."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long")


def hashed_counts(text, dims: int):
    """Square roots of hashed word counts, scaled to the text's length."""
    words = F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), "[^a-zà-ÿ0-9]+"), lambda w: w != "")
    slots = F.transform(words, lambda w: F.pmod(text_number(w), F.lit(dims)).cast("int"))
    return slots, F.greatest(F.size(words), F.lit(1))


def word_runs(text, run: int):
    """The different runs of so many words in a text."""
    words = F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), "[^a-zà-ÿ0-9]+"), lambda w: w != "")
    many = F.greatest(F.size(words) - run + 1, F.lit(0))
    beside = F.arrays_zip(*[F.slice(words, i + 1, many) for i in range(run)])  # the text beside itself, shifted word by word
    return F.array_distinct(F.transform(beside, lambda z: F.concat_ws(" ", *[z.getField(str(i)) for i in range(run)])))


def outside_benchmark(docs: DataFrame, benchmark: DataFrame, run: int = 8) -> DataFrame:
    """The rows of docs (doc_id, text, ...) that share no run of so many words with a text of benchmark."""
    asked = benchmark.select(F.explode(word_runs(F.col("text"), run)).alias("_run")).distinct()
    held = docs.select(F.col("doc_id").alias("_id"), F.explode(word_runs(F.col("text"), run)).alias("_run"))
    found = held.join(asked, "_run", "left_semi").select("_id").distinct()
    return docs.join(found, F.col("doc_id") == F.col("_id"), "left_anti")


def labelled_documents(spark: SparkSession, sf_dir: str, target: str) -> DataFrame:
    """doc_id, text and the target of labelled documents outside the benchmark."""
    docs = load_table(spark, sf_dir, "documents", "doc_id", "text")
    labels = load_table(spark, sf_dir, "labels", "doc_id", target)
    df = docs.join(labels, "doc_id").where(F.col(target).isNotNull())
    return outside_benchmark(df, load_table(spark, sf_dir, "benchmark", "text"))


def document_examples(spark: SparkSession, sf_dir: str, k: int, target: str = "quality", dims: int = 32) -> DataFrame:
    """Labelled documents as hashed word shares, without those that overlap the benchmark. A text's key is a checksum of it,
    so that its copies share shard and split."""
    df = labelled_documents(spark, sf_dir, target)
    key = text_number(F.coalesce("text", F.lit("")))
    slots, n = hashed_counts(F.col("text"), dims)
    counted = df.withColumns({"row_key": key, "_s": slots, "_n": n})
    counted = counted.select("doc_id", "row_key", target, "_n", F.explode_outer("_s").alias("_d")).groupBy("doc_id", "row_key", target, "_n", "_d").agg(F.count("_d").alias("_c"))
    cells = counted.groupBy("doc_id", "row_key", target, "_n").agg(F.map_from_entries(F.collect_list(F.struct(F.coalesce("_d", F.lit(-1)), "_c"))).alias("_m"))  # dims entries at most
    x = F.transform(F.sequence(F.lit(0), F.lit(dims - 1)), lambda j: F.sqrt(F.coalesce(F.try_element_at("_m", j), F.lit(0)) / F.col("_n")))
    return examples_from(cells, "row_key", x, F.col(target), k)


def conversation_examples(spark: SparkSession, sf_dir: str, k: int) -> DataFrame:
    """Role of a turn (3 classes) from length, question marks and word length."""
    df = load_table(spark, sf_dir, "conversations", "conv_id", "turn", "role", "text").where("role IN ('system', 'user', 'assistant')")
    text = F.coalesce("text", F.lit(""))
    marks = F.length(text) - F.length(F.regexp_replace(text, "[?]", ""))
    words = F.greatest(F.size(F.split(text, " ")), F.lit(1))
    x = F.array(F.log1p(F.length(text)) - 5, F.least(marks, F.lit(5)) / 5.0, F.length(text) / words / 10.0 - 0.5)
    y = F.when(F.col("role") == "system", 0).when(F.col("role") == "user", 1).otherwise(2)
    return examples_from(df.withColumn("row_key", F.col("conv_id") * 64 + F.col("turn")), "row_key", x, y, k)


def page_examples(spark: SparkSession, sf_dir: str, k: int) -> DataFrame:
    """Pages by counts of tags and links and length; planted class: quarter of the share of text outside tags."""
    df = load_table(spark, sf_dir, "pages", "page_id", "html")
    html = F.coalesce("html", F.lit(""))
    size = F.greatest(F.length(html), F.lit(1))
    bare = F.length(F.regexp_replace(html, "<[^>]*>", ""))
    tags, links = F.regexp_count(html, F.lit("<[a-z]")), F.regexp_count(html, F.lit("<a "))
    share = bare / size
    y = F.when(share < 0.4, 0).when(share < 0.6, 1).when(share < 0.8, 2).otherwise(3)
    return examples_from(df, "page_id", F.array(F.log1p(tags) - 3, F.log1p(links) - 1.5, F.log(size) - 7), y, k)


def event_examples(df: DataFrame, k: int, *carried: str) -> DataFrame:
    """Events (batch or stream): value, hour of day and the number in props; planted class: quarter of value and number.
    Columns carried on stand after the others."""
    number = F.coalesce(F.from_json("props", "k int")["k"], F.lit(0))
    turn = F.hour("ts") * (2 * math.pi / 24)
    score = F.col("value") / 50 + number / 50
    y = F.when(score < 0.75, 0).when(score < 1.5, 1).when(score < 2.5, 2).otherwise(3)
    return examples_from(df, "event_id", F.array(F.col("value") / 50 - 1, F.sin(turn), F.cos(turn), number / 50 - 1), y, k, *carried)
