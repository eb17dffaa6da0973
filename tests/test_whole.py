"""The queries on more, and on all, of what they are to count."""

import duckdb
import numpy as np
import pytest
from pyspark.errors import AnalysisException
from pyspark.sql import functions as F

from distinct_bounds.functions.special import hp
from distinct_bounds.operators import estimate, simulate
from distinct_bounds.plans import workloads

SF = "/root/testdata/sf0.001"


def test_inverse_by_table_above_its_end(spark):
    want = [0, 1, 137, 4_999, 5_000, 5_001, 15_000, 2_345_678]
    level = [0.01] + [float(a + b) / 2 for a, b in zip(hp(np.array(want[1:], float), 1 / 16), hp(np.array(want[1:], float) + 1, 1 / 16), strict=True)]
    aimed = spark.createDataFrame(list(zip(want, level, strict=True)), "want long, level double")
    got = estimate.inverse_by_table(aimed, estimate.hp_table(spark, 5000, 1 / 16), "level", "n", 1 / 16).collect()
    assert sorted(r["n"] for r in got) == want and all(r["n"] == r["want"] for r in got)


def test_inverse_by_table_of_large_groups(spark, tmp_path):
    spark.range(40_000).select(F.col("id").alias("user_id"), F.when(F.col("id") < 20_000, "a").otherwise("b").alias("event_type")).write.parquet(f"{tmp_path}/events.parquet")
    got = {r["event_type"]: r["estimate_int"] for r in workloads.inverse_by_table(spark, str(tmp_path)).collect()}
    plain = {r["event_type"]: r["estimate_int"] for r in workloads.point_by_groups(spark, str(tmp_path)).collect()}
    assert got == plain and min(got.values()) > 10_000


def test_twins_reach_as_far_as_the_data(spark, tmp_path):
    spark.range(200_000).select(F.col("id").alias("l_orderkey")).write.parquet(f"{tmp_path}/lineitem.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW lineitem AS SELECT * FROM '{tmp_path}/lineitem.parquet/*.parquet'")
    got = tuple(workloads.QUERIES["chebyshev_interval"](spark, str(tmp_path)).select("estimate_int", "lower_floor", "upper_floor").first())
    assert con.execute(f"SELECT estimate_int, lower_floor, upper_floor FROM ({workloads.SQL['chebyshev_interval']})").fetchall() == [got]
    assert got[1] > 60_000


def test_interval_methods_meet_every_stream(spark):
    got = {(r["stream"], r["method"]) for f in ("interval_methods_compare", "interval_methods_compare_more") for r in workloads.QUERIES[f](spark, SF).collect()}
    want = {*workloads.STREAMS, "user_type", "texts", "urls", "hosts", "props", "brands", "event_types", "regions", "flags"}
    assert got == {(n, m) for n in want for m in workloads.HALVES}


def test_first_month_and_both_order_keys_are_queries(spark):
    days = [r["slice"] for r in workloads.QUERIES["evolution_first_month"](spark, SF).collect()]
    assert len(days) > 5
    assert max(days) <= "1995-01-31" and {f"fit_{x}_orders" for x in ("row_uniform", "z_uniform", "x_geometric")} <= set(workloads.SQL)


def test_simulations_draw_as_many_trials_as_the_operators(spark):
    assert simulate.truncation_gap(spark).first()["trials"] == 1000
    assert {r["trials"] for r in workloads.mc_coverage(spark, SF).collect()} == {2000}


@pytest.mark.parametrize("name", ["bit_budgets", "finite_tails", "forward_levels", "gamma_products", "h_exponents", "hp_table", "log_shortest", "mc_coverage", "mc_coverage_claims", "mc_tail_constant", "mc_tail_fit", "mc_truncation"])
def test_reads_its_table(spark, tmp_path, name):
    with pytest.raises(AnalysisException):
        workloads.QUERIES[name](spark, str(tmp_path)).collect()
