"""Queries that once made their rows up: they follow the tables they are given, and agree with their statements."""

import __spark_entry__ as entry
import duckdb
import pytest

SF = "/root/testdata/sf0.001"
NAMES = ["cross_plan_grid", "fn_math_plan", "grid_hops", "plan_equal_grid", "plan_node_aligned_grid", "sample_count_by_k", "sql_recursive_doubling"]


@pytest.mark.parametrize("name", NAMES)
def test_reads_its_table(spark, name, tmp_path):
    db = duckdb.connect()
    tables = ("lineitem", "orders", "documents")
    for t in tables:
        db.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{SF}/{t}.parquet')")
    got = entry.queries()[name](spark, SF)
    assert any(t in f for t in tables for f in got.inputFiles()) or "recursive" in name
    want = db.execute(entry.oracle_sql()[name])
    assert got.columns == [c[0] for c in want.description]
    assert sorted(map(tuple, got.collect())) == sorted(want.fetchall())
    few = tmp_path / "few"
    few.mkdir()
    for t in tables:
        spark.read.parquet(f"{SF}/{t}.parquet").limit(3).write.parquet(str(few / f"{t}.parquet"))
    assert sorted(map(tuple, entry.queries()[name](spark, str(few)).collect())) != sorted(map(tuple, got.collect()))


def test_bytes_per_string_sends_every_string_over_both_levels(spark, monkeypatch):
    from pyspark.sql import functions as F

    from levelsort.operators import mergesort as ms

    arrived, send = [], ms.front_coded_lanes

    def watched(sent, lanes):
        out = send(sent, lanes)
        arrived.append(tuple(out.agg(F.count("*"), F.countDistinct("s"), F.min(F.length("s")), F.max(F.length("s"))).first()))
        return out

    monkeypatch.setattr(ms, "front_coded_lanes", watched)
    got = sorted(map(tuple, entry.queries()["cost_bytes_per_string"](spark, SF).collect()))
    n = spark.read.parquet(f"{SF}/orders.parquet").count()
    assert arrived == [(n, n, 500, 500)] * 10  # five sets, two levels
    db = duckdb.connect()
    db.execute(f"CREATE VIEW orders AS SELECT * FROM read_parquet('{SF}/orders.parquet')")
    want = sorted(db.execute(entry.oracle_sql()["cost_bytes_per_string"]).fetchall())
    assert [g[0] for g in got] == [w[0] for w in want] and [g[1:] for g in got] == [pytest.approx(w[1:], abs=1e-6) for w in want]
