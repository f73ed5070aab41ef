"""A part of the catalogue against DuckDB on the smallest tables (the driver runs all of it)."""

import math

import duckdb
import pytest

from coverdistinct.plans import catalogue, workloads
from coverdistinct.sources import streams

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
CHECKED = ["s1_bernoulli_count", "s5_stratified", "c1_exact", "c2_hll_m200", "c2_hll_m10_smallrange", "c5_bottom_m", "g1_spectrum", "g3_good_turing", "g5_unseen_truth", "r1_probe_in_sub", "r2_probe_in_sample",
           "r3_probe_value_hash", "r3_probe_grouped", "m1_sampled", "m1_grouped", "m1_counters", "m1_empty", "m1_all_singletons", "m1_null_policy", "m2_sampled", "m2_grouped", "b6_skew_aware", "v_moments",
           "v_th2", "k1_best_split", "w1_naive_vs_coverage", "w10_flows_per_day", "x_rollup_registers", "x_running_registers", "x_asof_estimate", "x_outer_truth", "x_sql_functions", "t_window_sampled", "t_window_probe", "t_running", "t_sliding", "t_session",
           "r6_reservoir", "m2_counters", "v_moments_exponential", "v_expected_subsampled", "k3_split_sampled", "w6_best_split", "x_cube_registers", "x_register_arrays", "x_set_ops_all", "x_window_ranks", "x_percentiles", "x_sql_planner", "x_pareto_grid", "t_rate_source", "x_udtf_grid"]


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return c


def rows(found, columns):
    def plain(v):
        v = v.item() if hasattr(v, "item") else v
        return None if isinstance(v, float) and math.isnan(v) else round(v, 6) + 0.0 if isinstance(v, float) else v
    return sorted((tuple(plain(r[c]) for c in sorted(columns)) for r in found), key=lambda r: tuple(map(str, r)))


@pytest.mark.parametrize("name", CHECKED)
def test_against_duckdb(spark, sf, con, name):
    df = catalogue.QUERIES[name](spark, sf)
    cur = con.execute(catalogue.ORACLES[name])
    columns = [c[0] for c in cur.description]
    assert sorted(columns) == sorted(df.columns)
    assert rows((dict(zip(columns, r)) for r in cur.fetchall()), columns) == rows(df.collect(), columns)


def test_entry_imports_and_names():
    import __spark_entry__ as e
    assert set(e.oracle_sql()) <= set(e.queries())
    assert "m1_sampled" in e.queries()


def test_the_planner_of_each_rate_measures_what_it_predicts(spark, sf):
    got = catalogue.QUERIES["w6_storage_best"](spark, sf).collect()
    assert len(got) == 9 and all(r["m"] + r["u"] == r["budget"] for r in got)


def test_model_tables_have_published_values_beside(spark, sf):
    got = catalogue.QUERIES["w2_model"](spark, sf).collect()
    assert len(got) == 6 and all(r["published_simulation"] is not None and r["analysis"] > 0 for r in got)


def test_counts_of_runs_give_the_probe_of_occurrences_from_one_shuffle(spark, sf):
    rates, us = [0.3, 0.1], [7, 60, 1_000_000]
    x = streams.load(spark, sf, "user")
    samples, values = workloads.sampled_runs(x, rates, 3), workloads.counted_runs(x, rates, 3)
    assert rows([r.asDict() for r in workloads._per_value(samples).collect()], ["rate", "run", "element", "k"]) == rows([r.asDict() for r in values.collect()], ["rate", "run", "element", "k"])
    want = rows([r.asDict() for r in workloads.probe_runs(samples, us, "value_hash").collect()], ["rate", "run", "u", "p0"])
    assert len(want) == 18 and want == rows([r.asDict() for r in workloads.probe_counted(values, us).collect()], ["rate", "run", "u", "p0"])
    both = catalogue._sub_runs(spark, sf, "user", rates, [(20, 7)], "value_hash", 3)
    both.collect()
    assert "ReusedExchange" in both._jdf.queryExecution().executedPlan().toString().split("== Initial Plan ==")[0]


def test_the_planned_splits_of_all_rates_come_from_one_sampling(spark, sf):
    plan = catalogue.QUERIES["w6_storage_best"](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Range (0, 20,") == 2  # registers and probe, which share a shuffle; two for each rate before


def test_the_empty_sample_is_one_of_a_table(spark, sf):
    df = catalogue.QUERIES["m1_empty"](spark, sf)
    assert "lineitem.parquet" in df._jdf.queryExecution().executedPlan().toString()
    assert [(r["l"], r["status"]) for r in df.collect()] == [(0, "empty_sample")]


def test_the_stream_in_batches_holds_all_events(spark, sf):
    assert catalogue.QUERIES["t_rate_source"](spark, sf).first()["l"] == streams.load(spark, sf, "user").count()


def test_the_grid_of_splits_is_one_of_tables(spark, sf):
    got = catalogue.QUERIES["x_udtf_grid"](spark, sf)
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "lineitem.parquet" in plan and "orders.parquet" in plan
    assert got.groupBy("stream", "rate").count().where("count = 198").count() == 6
