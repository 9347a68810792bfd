import pytest

import __spark_entry__ as entry
from driftks import registry
from driftks.operators import workloads
from driftks.sources import load

from .conftest import SF, same_rows

#: One query of each family; the driver runs them all.
SOME = ["exact_ks_price", "exact_ks_refine", "exact_statement", "approx_limit_quantity", "approx_limit_acctbal", "approx_limit_mid", "approx_limit_gamma_self", "third_table_exact", "replicate_exact_gamma_unif", "full_size_exact_gauss_shift", "histogram_ks", "sampled_ks", "adaptive_ks", "interp_violation", "traces_exact", "top_gaps", "sql_functions", "critical_distance_table", "precision_table", "unit_slope_table", "one_sample_uniform", "one_sample_normal", "holm_adjusted", "drift_by_group", "drift_rollup", "drift_cube", "without_each", "pairwise_groups", "incremental", "asof_eval", "range_join_eval", "interval_events", "session_features", "rank_sketch", "stream_weekly_knots", "stream_incremental", "stream_two"]


@pytest.mark.parametrize("name", SOME)
def test_query_equals_its_sql(spark, duck, name):
    same_rows(registry.queries()[name](spark, SF), duck, registry.oracle_sql()[name])


def values_of(duck, name, side):
    import numpy as np

    return np.array([v for (v,) in duck.execute(registry.PAIRS[name][side]).fetchall()], float)


def gap(x, y):
    import numpy as np

    points = np.union1d(x, y)
    return np.abs(np.searchsorted(np.sort(x), points, "right") / len(x) - np.searchsorted(np.sort(y), points, "right") / len(y)).max()


@pytest.mark.parametrize("name", ["price", "quantity", "discount_tax", "acctbal", "textlen", "w3", "w4"])
def test_approximate_queries_keep_their_bound(spark, duck, name):
    """The distance that a query named after the method returns, against the exact one from numpy."""
    label = {"w3": "gauss_null", "w4": "gamma_unif"}.get(name, name)
    x, y = (values_of(duck, name, side) for side in (0, 1))
    r = registry.queries()[f"approx_ks_{label}"](spark, SF).first()
    d = gap(x, y)
    assert (r["n"], r["m"]) == (len(x), len(y)) and abs(r["d_hat"] - d) <= r["d_bound"] + 1e-12
    assert r["p_lo"] <= r["p_value"] <= r["p_hi"] and r["decision"] in ("reject", "accept", "undecided")


def test_published_settings_and_behaviour(spark):
    """Twenty replications at the published sizes and precisions: knots, errors inside twice the bound of a function, decisions."""
    q = registry.queries()
    rows = q["full_size_gauss_null"](spark, SF).collect()
    assert len(rows) == 20 and all(abs(r["a_x"] - 7083) <= 3 and r["inside"] and r["agrees"] for r in rows)
    assert max(r["error"] for r in rows) <= 0.0004 and sum(r["reject"] for r in rows) <= 4
    rows = q["cdf_convergence"](spark, SF).collect()
    assert len(rows) == 9 and all(r["inside"] for r in rows)
    worst = {(r["a"], r["eps"]): r["max_error"] for r in rows}
    assert worst[11, 0.1] > worst[51, 0.1] > worst[51, 0.01] > worst[501, 0.001]
    r = q["compare_gauss_var"](spark, SF).first()
    assert r["points_planned"] == 2 * 1416 and r["points_planned"] > r["points_sketch"] and r["cdf_inside"] and r["sketch_inside"]


def test_exact_statement_joins_by_key(spark, tmp_path):
    """No pairing of every order with every customer; orders without a customer, price or balance, and customers that repeat, as in its SQL."""
    import duckdb

    assert "ExistenceJoin" not in registry.queries()["exact_statement"](spark, SF)._jdf.queryExecution().toString()
    orders = [(i, i % 7 if i % 11 else None, None if i % 13 == 0 else float("nan") if i % 17 == 0 else i * 777.0) for i in range(200)]
    customers = [(k % 6, None if k == 3 else k * 2_000.0) for k in range(8)] + [(None, 9_000.0)]
    spark.createDataFrame(orders, "o_orderkey long, o_custkey long, o_totalprice double").write.parquet(f"{tmp_path}/orders.parquet")
    spark.createDataFrame(customers, "c_custkey long, c_acctbal double").write.parquet(f"{tmp_path}/customer.parquet")
    con = duckdb.connect()
    for t in ("orders", "customer"):
        con.execute(f"create view {t} as select * from '{tmp_path}/{t}.parquet/*.parquet'")
    same_rows(registry.queries()["exact_statement"](spark, str(tmp_path)), con, registry.oracle_sql()["exact_statement"])


def test_experiments_read_given_tables(spark):
    """The experiments and the critical distances come from the tables, at the published sizes."""
    for label in ("gauss_shift", "gauss_var", "gauss_null", "gamma_unif", "gamma_self"):
        rows = workloads.resampled({"gauss_shift": "w1", "gauss_var": "w2", "gauss_null": "w3", "gamma_unif": "w4", "gamma_self": "w5"}[label], spark, SF, 1, (50, 20))
        assert [(r["is_x"], r["count"]) for r in rows.groupBy("is_x").count().orderBy("is_x").collect()] == [(False, 20), (True, 50)]
    own = {r[0] for r in workloads.gauss(spark, SF).select("z").collect()}
    rows = workloads.resampled("w3", spark, SF, 1, (300, 300)).collect()
    assert {r["value"] for r in rows} <= own and len({r["value"] for r in rows}) > 500
    sizes = dict(load(spark, SF, "lineitem").groupBy("l_returnflag").count().collect())
    assert {(r["flag_x"], r["n"], r["m"]) for r in registry.queries()["critical_distance_table"](spark, SF).collect()} == {(a, sizes[a], sizes[b]) for a in sizes for b in sizes if a < b}


def test_entry(spark):
    df = entry.entry(spark)
    assert df.count() == 1 and df.schema == entry.entry(spark).schema


def test_registry_is_consistent():
    names = entry.queries()
    assert set(entry.oracle_sql()) <= set(names) and len(names) > 100
