"""Every registered query has its own name, and SQL only where a query is."""

from __future__ import annotations

from pyspark.sql import functions as F

import __spark_entry__ as entry


def test_names():
    queries, oracles = entry.queries(), entry.oracle_sql()
    assert oracles.keys() <= queries.keys()
    assert all(callable(f) for f in queries.values()) and all(sql.strip() for sql in oracles.values())
    assert len(queries) > 200


def test_lsh_quality_and_sketches(spark, sf_dir):
    queries = entry.queries()
    row = queries["q_lsh_quality"](spark, sf_dir).first()
    assert row["recall"] == 1.0 and row["reduction"] > 0.9
    exact = {r["event_type"]: r["n"] for r in spark.read.parquet(f"{sf_dir}/events.parquet").groupBy("event_type").agg(F.count_distinct("user_id").alias("n")).collect()}
    sketch = {r["event_type"]: r["users"] for r in queries["q_agg_sketch"](spark, sf_dir).collect()}
    assert exact.keys() == sketch.keys() and all(abs(sketch[k] - n) <= max(1, 0.05 * n) for k, n in exact.items())
