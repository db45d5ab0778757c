"""A spread of registered queries against their DuckDB oracles on the small tables."""

import math
import os

import duckdb
import pytest
from pyspark.sql import functions as F

from cubecast import workloads

NAMES = [
    "m_bin_survey", "m_cic", "m_kdf_6", "m_kd2", "m_rect_30", "m_rect_persp", "m_slab", "m_exec_sql_30", "m_exec_arr_60", "m_exec_obj_90", "m_tf_a", "m_cmp_fill", "m_color", "m_compr_runs",
    "b_prev", "b_splat", "b_shear", "c_med", "c_p75", "c_crit", "c_nm", "c_waste", "q_mom", "q_peak", "q_clip", "w7", "e_join_asof", "e_win_rle", "e_json_variant", "m_fsm", "s_cube_inc",
    "m_kd2_uneven", "m_skip_array", "m_planner", "m_int_t_array", "m_tf_a_array", "m_compr_bytes", "b_ooc", "b_shear_error", "b_shader", "w1", "w2", "w3_ratio", "w8_vec", "w10_topology", "w11", "c_cov", "e_sql_rec", "e_join_lateral", "s_late",
]


def plain(x):
    return float(f"{x:.6g}") if isinstance(x, float) and not math.isnan(x) else tuple(map(plain, x)) if isinstance(x, (list, tuple)) else x


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for f in os.listdir(sf):
        c.execute(f"create view {f[:-8]} as select * from '{sf}/{f}'")
    return c


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_oracle(spark, sf, con, name):
    df = workloads.QUERIES[name](spark, sf)
    cols = sorted(df.columns)
    got = sorted((tuple(plain(r[c]) for c in cols) for r in df.collect()), key=repr)
    cur = con.execute(workloads.ORACLES[name])
    heads = [d[0] for d in cur.description]
    want = sorted((tuple(plain(dict(zip(heads, r, strict=True))[c]) for c in cols) for r in cur.fetchall()), key=repr)
    assert sorted(heads) == cols and got == want


def test_entry_runs(spark, sf):
    assert workloads.flagship(spark, sf).count() > 0


def test_registry_is_consistent():
    assert set(workloads.ORACLES) <= set(workloads.QUERIES)


def test_appended_rows_do_not_stay_at_the_driver(spark, sf):
    before = spark.conf.get("spark.sql.streaming.stateStore.providerClass", None)
    out = workloads.QUERIES["s_dedup"](spark, sf)
    assert "Scan parquet" in out._jdf.queryExecution().executedPlan().toString() and "LocalTableScan" not in out._jdf.queryExecution().executedPlan().toString()
    assert spark.conf.get("spark.sql.streaming.stateStore.providerClass", None) == before
    assert sorted(map(tuple, out.collect())) == sorted(map(tuple, spark.read.parquet(f"{sf}/events.parquet").groupBy("event_type").count().collect()))


def same_as_sql(spark, folder, name):
    df = workloads.QUERIES[name](spark, str(folder))
    cols = sorted(df.columns)
    c = duckdb.connect()
    for f in os.listdir(folder):
        c.execute(f"create view {f[:-8]} as select * from '{folder}/{f}{'/*.parquet' if os.path.isdir(f'{folder}/{f}') else ''}'")
    cur = c.execute(workloads.ORACLES[name])
    heads = [d[0] for d in cur.description]
    want = sorted((tuple(plain(dict(zip(heads, r, strict=True))[x]) for x in cols) for r in cur.fetchall()), key=repr)
    return sorted(heads) == cols and sorted((tuple(plain(r[x]) for x in cols) for r in df.collect()), key=repr) == want


def test_sessions_of_events_whose_times_start_again_with_later_ids(spark, sf, tmp_path):
    e = spark.read.parquet(f"{sf}/events.parquet")
    again = e.selectExpr(*[{"event_id": "event_id + 1000000 as event_id", "user_id": "user_id + 1000 as user_id"}.get(c, c) for c in e.columns])
    e.unionByName(again).write.parquet(str(tmp_path / "events.parquet"))
    assert same_as_sql(spark, tmp_path, "s_session")
    # closed sessions come as files, not through the driver
    assert "Scan parquet" in workloads.QUERIES["s_session"](spark, str(tmp_path))._jdf.queryExecution().executedPlan().toString()


@pytest.fixture(scope="module")
def dear(spark, sf, tmp_path_factory):
    """Prices so high that a pixel needs more than four bytes."""
    folder = tmp_path_factory.mktemp("dear")
    line = spark.read.parquet(f"{sf}/lineitem.parquet")
    line.withColumn("l_extendedprice", F.col("l_extendedprice") * 1e6).write.parquet(str(folder / "lineitem.parquet"))
    return folder


@pytest.mark.parametrize("name", ["m_compr_bytes", "m_cmp_clip", "m_compr_rle", "m_compr_sparse", "m_compr_zlib"])
def test_messages_of_large_values(spark, dear, name):
    assert same_as_sql(spark, dear, name)


def test_measures_of_messages_of_large_values(spark, dear):
    run = {n: workloads.QUERIES[n](spark, str(dear)) for n in ("m_compr_cost", "c_tr_measured", "c_stage_measured", "c_scale_measured")}
    assert {n: d.count() for n, d in run.items()} == {"m_compr_cost": 12, "c_tr_measured": 4, "c_stage_measured": 4, "c_scale_measured": 3}


@pytest.mark.parametrize("name", ["b_full", "b_slab", "c_bal_published", "c_bal_slab", "c_msg", "c_cov", "c_nm", "c_occ", "c_ovl", "c_ovl_total", "c_recta", "c_samp_0"])
def test_measures_of_plans_read_a_table(spark, sf, name):
    assert "FileScan parquet" in workloads.QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert same_as_sql(spark, sf, name)
