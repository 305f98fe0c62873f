"""Run registered queries and their SQL side by side: python tests/compare.py [sf_dir] [name...]"""

from __future__ import annotations

import os
import sys
import time
from collections import Counter
from decimal import Decimal

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir: str):
    import duckdb

    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for t in TABLES:
        path = f"{sf_dir}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{path}{'/*' if os.path.isdir(path) else ''}')")
    return con


def plain(v):
    if isinstance(v, Decimal):
        v = float(v) if v % 1 else int(v)
    if isinstance(v, float) and v == 0:
        return 0.0
    return v


def rows_of(names: list[str], rows) -> Counter:
    order = sorted(range(len(names)), key=lambda i: names[i])
    return Counter(tuple(plain(r[i]) for i in order) for r in rows)


def difference(df, con, sql: str) -> str:
    """Empty if the rows are the same."""
    names = df.columns
    got = rows_of(names, [tuple(r) for r in df.collect()])
    made = con.execute(sql)
    others = [d[0] for d in made.description]
    want = rows_of(others, made.fetchall())
    if sorted(names) != sorted(others):
        return f"columns {sorted(names)} and {sorted(others)}"
    if got == want:
        return ""
    a, b = list((got - want).elements()), list((want - got).elements())
    return f"{sum(got.values())} and {sum(want.values())} rows; {len(a)} differ, e.g. {sorted(map(str, a))[:3]} for {sorted(map(str, b))[:3]}"


def main(args: list[str]) -> int:
    sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    from pyspark.sql import SparkSession

    import __spark_entry__ as entry

    sf_dir = args[0] if args else "/root/testdata/sf0.01"
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    con, sql, bad = connect(sf_dir), entry.oracle_sql(), 0
    for name, f in entry.queries().items():
        if len(args) > 1 and name not in args[1:]:
            continue
        t = time.time()
        try:
            df = f(spark, sf_dir)
            said = difference(df, con, sql[name]) if name in sql else f"no SQL; {df.count()} rows"
        except Exception as e:  # noqa: BLE001  the report goes on
            said = f"{type(e).__name__}: {str(e)[:600]}"
        ok = not said or said.startswith("no SQL")
        bad += not ok
        print(f"{'ok  ' if ok else 'BAD '} {time.time() - t:6.1f} s  {name}  {said}", flush=True)
    return bad


if __name__ == "__main__":
    sys.exit(main(sys.argv[1:]))
