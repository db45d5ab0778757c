"""The engine surface around the methods: scans, joins, aggregates, windows, scalars, SQL, functions, sinks, streams."""

from __future__ import annotations

import time
import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import udfs
from ..operators import array_engine, composite, cube, partition, render, view
from ..plans import kd
from ..plans.spec import SURVEY, ViewSpec
from ..sources import cubebin, sinks, store
from ..streaming import serve
from . import sqltext as S
from .methods import A30, MESSAGE, NODEHIT, partials, scratch, tbl
from .registry import add, query

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
VOX = f"with {S.SURVEY}"


def shared_path(s) -> str:
    """The same as a plain path, for writers that use files; refused where the shared folder is an object store."""
    path = scratch(s).removeprefix("file://").removeprefix("file:")
    if "://" in path:
        raise ValueError("brick files and images need a shared folder that tasks can open as files")
    return path


def both(name: str, sql: str, spark_sql: str | None = None) -> None:
    """One ANSI text for both engines (or its Spark spelling); vox is the survey cube."""
    text = spark_sql or sql
    used = [t for t in TABLES if f" {t}" in text or f"({t}" in text]

    def run(s, sf):
        for t in used:
            tbl(s, sf, t).createOrReplaceTempView(t)
        if "vox" in text:
            cube.survey(s, sf).createOrReplaceTempView("vox")
        return s.sql(text)

    ddb = sql
    if "vox" in sql:
        ddb = f"{VOX}, {sql[5:]}" if sql.startswith("with ") and not sql.startswith("with recursive") else f"{VOX} {sql}"
    add(name, run, ddb)


def v(s, sf):
    return cube.survey(s, sf)


def nearest_centroid(vectors):
    """label, nearest, n: how many vectors of a label lie nearest to the mean of which label. Centroids are one row a label."""
    parts = vectors.select("label", F.posexplode("embedding").alias("i", "x"))
    mean = parts.groupBy("label", "i").agg(F.avg(F.col("x").cast("double")).alias("m"))
    centres = mean.groupBy(F.col("label").alias("centre")).agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "m"))), lambda p: p["m"]).alias("c"))
    gap = F.zip_with("embedding", "c", lambda x, m: (x.cast("double") - m) * (x.cast("double") - m))
    d = vectors.select("vec_id", "label", "embedding").crossJoin(F.broadcast(centres)).withColumn("d", F.round(F.aggregate(gap, F.lit(0.0), lambda a, x: a + x), 9))
    return d.groupBy("vec_id", "label").agg(F.min_by("centre", F.struct("d", "centre")).alias("nearest")).groupBy("label", "nearest").agg(F.count("*").alias("n"))


# Scans and filters
add("e_scan_prune", lambda s, sf: tbl(s, sf, "lineitem").where("l_shipdate >= timestamp_ntz'1998-01-01' and l_shipdate < timestamp_ntz'1998-02-01'").select("l_orderkey", "l_quantity", "l_shipdate"), "select l_orderkey, l_quantity, l_shipdate from lineitem where l_shipdate >= '1998-01-01' and l_shipdate < '1998-02-01'")
for fmt in ("csv", "json", "orc", "parquet"):

    def _round(s, sf, fmt=fmt):
        path = scratch(s)
        v(s, sf).write.format(fmt).save(path)
        return s.read.schema(store.VOXELS).format(fmt).load(path)

    add(f"e_scan_{fmt}", _round, f"{VOX} select x, y, z, v from vox")


@query("e_scan_cubebin", f"{VOX} select x, y, z, v from vox")
def _(s, sf):
    path = shared_path(s)
    cubebin.register(s)
    cubebin.write(array_engine.pack_bricks(v(s, sf), kd.kd(SURVEY.dims, 8)), path)
    return s.read.format("cubebin").option("path", path).load().select("x", "y", "z", "v")


@query("m_load", f"with {S.kd_tree(SURVEY.dims, 8)}, {S.SURVEY} select brick, count(*) as n, min(v) as lo, max(v) as hi from vox join leaf on x >= x0 and x < x1 and y >= y0 and y < y1 and z >= z0 and z < z1 where brick in (1, 6) group by brick")
def _(s, sf):
    """Two bricks read from the store, by pruned partitions."""
    path = scratch(s)
    plan = kd.kd(SURVEY.dims, 8)
    partition.assign(v(s, sf), plan).withColumn("brick_group", F.col("brick") % store.GROUPS).write.partitionBy("brick_group").parquet(path)
    return store.read_bricks(s, path, [1, 6]).groupBy("brick").agg(F.count("*").alias("n"), F.min("v").alias("lo"), F.max("v").alias("hi"))


both("e_filter_box", "select x, y, z, v from vox where x between 5 and 9 and y between 5 and 9 and z between 5 and 9")
both("e_filter_null", "select count(*) as n, sum(case when w is null then 1 else 0 end) as blank, cast(sum(w) as bigint) as total from (select nullif(v % 7, 3) as w from vox) t", "select count(*) as n, sum(case when w is null then 1 else 0 end) as blank, sum(w) as total from (select nullif(v % 7, 3) as w from vox) t")
both("e_filter_like", "select p_partkey, p_name from part where p_name like 'small%' or p_name like '%widget'")
both("e_filter_in", "select event_id, event_type from events where event_type in ('view', 'click') and user_id in (1, 2, 3, 5, 8, 13)")
both("e_project_case", "select x, y, z, case when v >= 30000000 then 'bright' when v >= 10000000 then 'middle' else 'faint' end as class from vox")
# Joins
add("e_join_bcast", lambda s, sf: partition.assign(v(s, sf), kd.kd(SURVEY.dims, 8)).join(F.broadcast(kd.kd(SURVEY.dims, 8).frame(s).select("brick", "node")), "brick").groupBy("node").agg(F.count("*").alias("n")), f"with {S.kd_tree(SURVEY.dims, 8)}, {S.SURVEY} select brick as node, count(*) as n from vox join leaf on x >= x0 and x < x1 and y >= y0 and y < y1 and z >= z0 and z < z1 group by brick")
LO = "select o_orderpriority, count(*) as n from lineitem join orders on l_orderkey = o_orderkey group by o_orderpriority"
for hint in ("shuffle_hash", "merge"):
    add("e_join_shj" if hint == "shuffle_hash" else "e_join_smj", lambda s, sf, h=hint: tbl(s, sf, "lineitem").select("l_orderkey").join(tbl(s, sf, "orders").hint(h), F.expr("l_orderkey = o_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n")), LO)
add(
    "e_join_nl_theta",
    lambda s, sf: s.range(64 * 64)
    .selectExpr("int(id % 64) u", "int(id div 64) v")
    .join(F.broadcast(view.rects(kd.kd(SURVEY.dims, 16).frame(s), A30, SURVEY)), F.expr("u >= u0 and u < u1 and v >= v0 and v < v1"))
    .groupBy("u", "v")
    .agg(F.count("*").alias("layers")),
    f"with {S.kd_tree(SURVEY.dims, 16)}, {S.rects(A30, 'survey')} select u, v, count(*) as layers from (select unnest(range(64))::int as u), (select unnest(range(64))::int as v), rect where u >= u0 and u < u1 and v >= v0 and v < v1 group by u, v",
)
add("e_join_range", lambda s, sf: tbl(s, sf, "events").select("event_id", "value", F.floor(F.col("value") / 10).alias("band")).join(F.broadcast(s.range(60).select(F.col("id").alias("band"), (F.col("id") * 10 + 2.0).alias("lo"), (F.col("id") * 10 + 7.0).alias("hi"))), "band").where("value >= lo and value < hi").groupBy("band").agg(F.count("*").alias("n")), "select floor(value / 10)::bigint as band, count(*) as n from events where value - floor(value / 10) * 10 >= 2 and value - floor(value / 10) * 10 < 7 and value < 600 group by 1")
both("e_join_interval", "select p.event_id as purchase, count(*) as clicks from events p join events c on p.user_id = c.user_id and c.ts <= p.ts and c.ts >= p.ts - interval '1' hour where p.event_type = 'purchase' and c.event_type = 'click' group by p.event_id")


@query("e_join_asof", "select p.event_id, max(w.event_id) as view_id from events p left join events w on w.user_id = p.user_id and w.event_type = 'view' and w.event_id <= p.event_id where p.event_type = 'purchase' group by p.event_id")
def _(s, sf):
    """Newest view at or before each purchase: one shuffle and a running last value, no pairs."""
    e = tbl(s, sf, "events").where("event_type in ('view', 'purchase')")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("view_id", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), True).over(w)).where("event_type = 'purchase'").select("event_id", "view_id")


add("e_join_semi", lambda s, sf: tbl(s, sf, "documents").select("doc_id", "lang").join(tbl(s, sf, "labels"), "doc_id", "left_semi").groupBy("lang").agg(F.count("*").alias("n")), "select lang, count(*) as n from documents where doc_id in (select doc_id from labels) group by lang")
add("e_join_anti", lambda s, sf: tbl(s, sf, "documents").select("doc_id", "lang").join(tbl(s, sf, "labels"), "doc_id", "left_anti").groupBy("lang").agg(F.count("*").alias("n")), "select lang, count(*) as n from documents where doc_id not in (select doc_id from labels) group by lang")
add("e_join_outer", lambda s, sf: render.axis_frame(v(s, sf), SURVEY, ViewSpec(0)).withColumnRenamed("val", "a").join(render.axis_frame(v(s, sf), SURVEY, ViewSpec(180)).withColumnRenamed("val", "b"), ["u", "v"], "full_outer").select("u", "v", F.coalesce("a", F.lit(0)).alias("a"), F.coalesce("b", F.lit(0)).alias("b")), f"with a as ({S.mip(ViewSpec(0), 'survey')}), b as ({S.mip(ViewSpec(180), 'survey')}) select coalesce(a.u, b.u) as u, coalesce(a.v, b.v) as v, coalesce(a.val, 0) as a, coalesce(b.val, 0) as b from a full join b on a.u = b.u and a.v = b.v")
both("e_join_self", "select a.y, max(a.m) as along_z, max(b.m) as along_x from (select x, y, max(v) as m from vox group by x, y) a join (select z, y, max(v) as m from vox group by z, y) b on a.y = b.y group by a.y")
add("e_join_cross", lambda s, sf: kd.kd(SURVEY.dims, 8).frame(s).select("brick").crossJoin(F.broadcast(s.range(24).select((F.col("id") * 15).alias("angle")))), "select brick::int as brick, angle * 15 as angle from (select unnest(range(8)) as brick), (select unnest(range(24)) as angle)")


@query(
    "e_join_lateral",
    f"with {S.kd_tree(SURVEY.dims, 8)}, {S.SURVEY}, own as (select vox.*, brick from vox join leaf on vox.x >= x0 and vox.x < x1 and vox.y >= y0 and vox.y < y1 and vox.z >= z0 and vox.z < z1) select b.brick, t.x, t.y, t.z, t.v from (select distinct brick from own) b, lateral (select x, y, z, v from own o where o.brick = b.brick order by v desc, x, y, z limit 2) t",
)
def _(s, sf):
    """The two brightest voxels of each brick."""
    partition.assign(v(s, sf), kd.kd(SURVEY.dims, 8)).createOrReplaceTempView("own")
    kd.kd(SURVEY.dims, 8).frame(s).createOrReplaceTempView("bricks")
    return s.sql("select b.brick, t.x, t.y, t.z, t.v from bricks b, lateral (select x, y, z, v from own o where o.brick = b.brick order by v desc, x, y, z limit 2) t")


both("e_join_star", "select r_name, p_brand, round(sum(l_extendedprice * (1 - l_discount)), 2) as revenue from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey join part on l_partkey = p_partkey group by r_name, p_brand")
# Aggregates
both("e_agg_two_stage", "select x, y, max(m) as m from (select x, y, z % 4 as node, max(v) as m from vox group by x, y, z % 4) t group by x, y")
both("e_agg_distinct", "select event_type, count(distinct user_id) as users, count(distinct floor(value)) as whole from events group by event_type")
add("e_agg_approx", lambda s, sf: tbl(s, sf, "events").groupBy("event_type").agg((F.abs(F.approx_count_distinct("user_id", 0.02) - F.countDistinct("user_id")) <= 0.1 * F.countDistinct("user_id")).alias("near")), "select distinct event_type, true as near from events")
both("e_agg_stats", "select event_type, round(avg(value), 6) as mean, round(stddev_samp(value), 6) as sd, round(corr(value, user_id), 6) as corr from events group by event_type")
add("e_agg_moments", lambda s, sf: tbl(s, sf, "events").agg(F.round(F.skewness("value"), 4).alias("skew"), F.round(F.kurtosis("value"), 4).alias("kurt")), "with m as (select avg(value) as a, count(*) as n from events), c as (select avg((value - a) ** 2) as m2, avg((value - a) ** 3) as m3, avg((value - a) ** 4) as m4 from events, m) select round(m3 / m2 ** 15e-1, 4) as skew, round(m4 / m2 ** 2 - 3, 4) as kurt from c")
add("e_agg_quant", lambda s, sf: tbl(s, sf, "events").groupBy("event_type").agg(F.round(F.median("value"), 6).alias("med"), F.round(F.percentile("value", F.lit(0.75)), 6).alias("p75")), "select event_type, round(median(value), 6) as med, round(quantile_cont(value, 0.75), 6) as p75 from events group by event_type")
add("e_agg_quant_approx", lambda s, sf: tbl(s, sf, "events").groupBy("event_type").agg((F.abs(F.percentile_approx("value", 0.5, 10000) - F.median("value")) < 1).alias("near")), "select distinct event_type, true as near from events")
add("e_agg_maxby", lambda s, sf: v(s, sf).groupBy("z").agg(F.max_by(F.struct("x", "y"), F.struct("v", "x", "y")).alias("p")).select("z", "p.x", "p.y"), f"{VOX} select z, x, y from vox qualify row_number() over (partition by z order by v desc, x desc, y desc) = 1")
add("e_agg_mode", lambda s, sf: tbl(s, sf, "lineitem").groupBy("l_returnflag").agg(F.mode("l_quantity", True).alias("q")), "select l_returnflag, l_quantity as q from (select l_returnflag, l_quantity, count(*) as n from lineitem group by 1, 2) qualify row_number() over (partition by l_returnflag order by n desc, l_quantity) = 1")
both("e_agg_bool", "select user_id, bool_or(event_type = 'purchase') as bought, bool_and(value > 1) as big from events group by user_id")
both("e_agg_filter", "select user_id, count(*) filter (where event_type = 'view') as views, count(*) filter (where value > 50) as big from events group by user_id")
both("e_agg_rollup", "select r_name, n_name, count(*) as n, grouping(n_name) as g from supplier join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by rollup (r_name, n_name)")
both("e_agg_cube", "select l_returnflag, l_linestatus, count(*) as n from lineitem group by cube (l_returnflag, l_linestatus)")
both("e_agg_gsets", "select l_returnflag, l_linestatus, count(*) as n, grouping(l_returnflag) as a, grouping(l_linestatus) as b from lineitem group by grouping sets ((l_returnflag), (l_linestatus), ())")
add("e_agg_pivot", lambda s, sf: v(s, sf).where("z < 3").groupBy("x").pivot("z", [0, 1, 2]).agg(F.max("v")).select("x", *[F.col(str(i)).alias(f"z{i}") for i in range(3)]), f"{VOX} select x, max(v) filter (z = 0) as z0, max(v) filter (z = 1) as z1, max(v) filter (z = 2) as z2 from vox where z < 3 group by x")
add("e_agg_unpivot", lambda s, sf: tbl(s, sf, "lineitem").groupBy("l_returnflag").agg(F.max("l_quantity").alias("q"), F.max("l_tax").alias("t")).unpivot("l_returnflag", ["q", "t"], "what", "value"), "with a as (select l_returnflag, max(l_quantity) as q, max(l_tax) as t from lineitem group by 1) select l_returnflag, 'q' as what, q as value from a union all select l_returnflag, 't', t from a")
both("e_agg_hist", "select v // 4500000 as bin, count(*) as n from vox group by 1", "select v div 4500000 as bin, count(*) as n from vox group by 1")
add("e_agg_sketch", lambda s, sf: tbl(s, sf, "events").agg(F.hll_sketch_estimate(F.hll_sketch_agg("user_id", 12)).alias("h"), F.countDistinct("user_id").alias("n")).select((F.abs(F.col("h") - F.col("n")) <= 0.1 * F.col("n")).alias("near")), "select true as near")
# a sketch of 2^12 items holds every value of a small group as it is: its quantile is then exact
add(
    "e_agg_kll",
    lambda s, sf: tbl(s, sf, "supplier").groupBy("s_nationkey").agg(F.kll_sketch_agg_double("s_acctbal", F.lit(4096)).alias("k"), F.count("*").alias("n")).select("s_nationkey", "n", F.kll_sketch_get_n_double("k").alias("seen"), F.kll_sketch_get_quantile_double("k", F.lit(0.0)).alias("least"), F.kll_sketch_get_quantile_double("k", F.lit(1.0)).alias("most")),
    "select s_nationkey, count(*) as n, count(*) as seen, min(s_acctbal) as least, max(s_acctbal) as most from supplier group by s_nationkey",
)
# Windows
both("e_win_rank", "select l_linenumber, q, rank() over (partition by l_linenumber order by q) as r, dense_rank() over (partition by l_linenumber order by q) as d, ntile(4) over (partition by l_linenumber order by q) as t, round(percent_rank() over (partition by l_linenumber order by q), 6) as p from (select distinct l_linenumber, l_quantity as q from lineitem) t")
both("e_win_lag", "select x, y, z, v - lag(v) over (partition by x, y order by z) as step, lead(z) over (partition by x, y order by z) as nxt from vox")
both("e_win_running_max", "select x, y, z, max(v) over (partition by x, y order by z rows between unbounded preceding and current row) as running from vox")
both("e_win_moving", "select x, y, z, cast(sum(v) over (partition by x, y order by z rows between 1 preceding and 1 following) as bigint) as total from vox")
both("e_win_range", "select x, y, z, cast(sum(v) over (partition by x, y order by z range between 1 preceding and 1 following) as bigint) as total from vox")
both("e_win_first_last", "select distinct x, y, first_value(z) over w as a, last_value(z) over w as b, nth_value(z, 2) over w as c from vox window w as (partition by x, y order by z rows between unbounded preceding and unbounded following)")
both("e_win_rle", "select y, z, min(x) as start, count(*) as length from (select x, y, z, x - row_number() over (partition by y, z order by x) as g from vox) t group by y, z, g")
# Order, sets
both("e_top_k", "select x, y, z, v from vox order by v desc, x, y, z limit 10")
both("e_limit_offset", "select x, y, z, v from vox order by v desc, x, y, z limit 10 offset 20")
both("e_top_k_group", "select z, x, y, v from (select *, row_number() over (partition by z order by v desc, x, y) as r from vox) t where r <= 3")
MORTON = " + ".join(f"((({c} >> {i}) & 1) << {3 * i + k})" for i in range(6) for k, c in enumerate("xyz"))
add("e_sort_morton", lambda s, sf: v(s, sf).select("x", "y", "z", udfs.morton(F.col("x"), F.col("y"), F.col("z")).alias("code")).orderBy("code"), f"{VOX} select x, y, z, {MORTON} as code from vox")
for name, op in (("union", "union"), ("intersect", "intersect"), ("except", "except"), ("all", "except all")):
    both(f"e_set_{name}", f"select x, y from vox where z < 9 {op} select x, y from vox where z >= 9 and v > 5000000")
# Scalars
both("e_str_core", "select p_partkey, upper(trim(p_name)) as n, lpad(cast(p_size as varchar), 4, '0') as size, split_part(p_brand, '#', 2) as brand, replace(p_type, 'E', 'e') as t, length(p_name) as len, concat_ws('-', p_brand, p_type) as c, instr(p_name, 'ring') as at, substring(p_name, 2, 3) as sub from part", "select p_partkey, upper(trim(p_name)) as n, lpad(string(p_size), 4, '0') as size, split_part(p_brand, '#', 2) as brand, replace(p_type, 'E', 'e') as t, length(p_name) as len, concat_ws('-', p_brand, p_type) as c, instr(p_name, 'ring') as at, substring(p_name, 2, 3) as sub from part")
both("e_str_regex", "select doc_id, len(regexp_extract_all(text, '[0-9]+')) as numbers, regexp_matches(text, '(?i)license') as licence from documents", "select doc_id, regexp_count(text, '[0-9]+') as numbers, text rlike '(?i)license' as licence from documents")
both("e_str_url", "select page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) as host, regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1) as path from pages")
both("e_html_text", r"select page_id, regexp_extract(html, '<title>([^<]*)</title>', 1) as title, length(regexp_replace(html, '<[^>]*>', ' ', 'g')) as n from pages", r"select page_id, regexp_extract(html, '<title>([^<]*)</title>', 1) as title, length(regexp_replace(html, '<[^>]*>', ' ')) as n from pages")
both(
    "e_str_lev",
    "select item_id, doc_id, levenshtein(a, b) as d from (select item_id, doc_id, regexp_replace(substr(k.text, 1, 24), '[^ -~]', '?', 'g') as a, regexp_replace(substr(d.text, 1, 24), '[^ -~]', '?', 'g') as b from benchmark k join documents d on d.doc_id = k.item_id) t",
    "select item_id, doc_id, levenshtein(a, b) as d from (select item_id, doc_id, regexp_replace(substr(k.text, 1, 24), '[^ -~]', '?') as a, regexp_replace(substr(d.text, 1, 24), '[^ -~]', '?') as b from benchmark k join documents d on d.doc_id = k.item_id) t",
)
add("e_date_core", lambda s, sf: tbl(s, sf, "orders").select("o_orderkey", F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).alias("day"), F.month("o_orderdate").alias("m"), F.dayofweek("o_orderdate").alias("dow"), F.date_format("o_orderdate", "yyyy-MM").alias("ym"), F.quarter("o_orderdate").alias("q")), "select o_orderkey, date_diff('day', date '1995-01-01', o_orderdate::date) as day, month(o_orderdate) as m, dayofweek(o_orderdate) + 1 as dow, strftime(o_orderdate, '%Y-%m') as ym, quarter(o_orderdate) as q from orders")
add("e_date_interval", lambda s, sf: tbl(s, sf, "events").withColumn("u", F.unix_micros(F.col("ts").cast("timestamp"))).select("event_id", (F.col("u") - F.lag("u").over(Window.partitionBy("user_id").orderBy("u", "event_id"))).alias("gap")), "select event_id, epoch_us(ts) - lag(epoch_us(ts)) over (partition by user_id order by ts, event_id) as gap from events")
both("e_math_core", "select event_id, floor(value) as f, ceil(value) as c, round(sqrt(value), 6) as s, round(power(value, 2), 4) as p, round(ln(value + 1), 6) as l, greatest(value, 10.0) as g, sign(value - 20) as sg, abs(value - 20) as a from events", "select event_id, floor(value) as f, ceil(value) as c, round(sqrt(value), 6) as s, round(power(value, 2), 4) as p, round(ln(value + 1), 6) as l, greatest(value, 10.0D) as g, sign(value - 20) as sg, abs(value - 20) as a from events")
both("e_math_bits", "select x, y, x & y as a, x | y as o, xor(x, y) as e, x << 3 as l, y >> 1 as r from vox where z = 3", "select x, y, x & y as a, x | y as o, x ^ y as e, shiftleft(x, 3) as l, shiftright(y, 1) as r from vox where z = 3")
add("e_arr_hof", lambda s, sf: tbl(s, sf, "embeddings").select("vec_id", F.round(F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda a, x: a + x), 5).alias("sq"), F.size(F.filter("embedding", lambda x: x > 0)).alias("pos"), F.array_max("embedding").cast("double").alias("top"), F.exists("embedding", lambda x: x > 0.3).alias("big")), "select vec_id, round(list_sum(list_transform(embedding, lambda x: x::double * x::double)), 5) as sq, len(list_filter(embedding, lambda x: x > 0))::int as pos, list_max(embedding)::double as top, len(list_filter(embedding, lambda x: x > 3e-1)) > 0 as big from embeddings")
add("e_arr_explode", lambda s, sf: tbl(s, sf, "embeddings").select("vec_id", F.posexplode("embedding").alias("i", "x")).where("i < 3").groupBy("vec_id").agg(F.round(F.sum(F.col("x").cast("double") * (F.col("i") + 1)), 6).alias("t")), "select vec_id, round(embedding[1]::double + embedding[2]::double * 2 + embedding[3]::double * 3, 6) as t from embeddings")
add("e_vec_norm", lambda s, sf: tbl(s, sf, "embeddings").select("label", F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x).alias("q")).groupBy("label").agg(F.count("*").alias("n"), F.round(F.avg(F.sqrt("q")), 4).alias("norm")), "select label, count(*) as n, round(avg(sqrt(list_sum(list_transform(embedding, lambda x: x::double * x::double)))), 4) as norm from embeddings group by label")
add(
    "e_vec_nearest",
    lambda s, sf: nearest_centroid(tbl(s, sf, "embeddings")),
    """with e as (select vec_id, label, unnest(embedding)::double as x, generate_subscripts(embedding, 1) as i from embeddings), c as (select label as centre, i, avg(x) as m from e group by 1, 2),
d as (select e.vec_id, e.label, centre, round(sum((x - m) * (x - m)), 9) as d from e join c on c.i = e.i group by 1, 2, 3), n as (select vec_id, label, arg_min(centre, (d, centre)) as nearest from d group by 1, 2) select label, nearest, count(*) as n from n group by 1, 2""",
)
add("e_map_core", lambda s, sf: tbl(s, sf, "events").groupBy("user_id").agg(F.map_from_entries(F.array_sort(F.collect_set(F.struct("event_type", F.lit(1))))).alias("m")).select("user_id", F.size(F.map_keys("m")).alias("kinds"), F.map_contains_key("m", "view").alias("viewed")), "select user_id, count(distinct event_type)::int as kinds, bool_or(event_type = 'view') as viewed from events group by user_id")
add("e_struct_core", lambda s, sf: kd.kd(SURVEY.dims, 8).frame(s).select("brick", F.struct(F.struct("x0", "y0", "z0").alias("lo"), F.struct("x1", "y1", "z1").alias("hi")).alias("box")).select("brick", F.col("box.lo.x0").alias("x0"), (F.col("box.hi.z1") - F.col("box.lo.z0")).alias("depth")), f"with {S.kd_tree(SURVEY.dims, 8)} select brick, x0, z1 - z0 as depth from leaf")
add("e_json_core", lambda s, sf: tbl(s, sf, "events").select("event_id", F.from_json("props", "k int").getField("k").alias("k"), F.to_json(F.struct(F.get_json_object("props", "$.k").cast("int").alias("k"))).alias("j")), """select event_id, (props->>'$.k')::int as k, '{"k":' || (props->>'$.k') || '}' as j from events""")
add("e_json_variant", lambda s, sf: tbl(s, sf, "events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "int").alias("k")), "select event_id, (props->>'$.k')::int as k from events")
# SQL
both("e_sql_cte", "with big as (select x, y, sum(v) as t from vox group by x, y), top as (select max(t) as m from big) select x, y from big, top where t * 2 > m")


@query("e_sql_rec", f"with {S.kd_tree(SURVEY.dims, 6)} select brick, x0, x1, y0, y1, z0, z1 from leaf")
def _(s, sf):
    """The k-d partition as a recursive query."""
    axis = "case when x1 - x0 >= y1 - y0 and x1 - x0 >= z1 - z0 then 0 when y1 - y0 >= z1 - z0 then 1 else 2 end"
    step = "select *, shiftleft(1, length(bin(n - 1)) - 1) lft, " + axis + " a from t where n > 1"
    cut = "select *, case a when 0 then x0 when 1 then y0 else z0 end + (2 * (case a when 0 then x1 - x0 when 1 then y1 - y0 else z1 - z0 end) * lft + n) div (2 * n) c from p"
    side = ", ".join(f"int(if(a = {i} and side = 1, c, {x}0)), int(if(a = {i} and side = 0, c, {x}1))" for i, x in enumerate("xyz"))
    return s.sql(
        f"""with recursive t(n, path, x0, x1, y0, y1, z0, z1) as (
          select 6, cast('' as string), 0, {SURVEY.dims[0]}, 0, {SURVEY.dims[1]}, 0, {SURVEY.dims[2]}
          union all
          select int(if(side = 0, lft, n - lft)), path || side, {side} from (with p as ({step}) {cut}) q cross join (select explode(array(0, 1)) side) sides)
        select int(row_number() over (order by path) - 1) brick, x0, x1, y0, y1, z0, z1 from t where n = 1"""
    )


both("e_sql_sub", "select c_custkey, (select count(*) from orders where o_custkey = c_custkey) as n from customer where c_acctbal > (select avg(c_acctbal) from customer)")
both("e_sql_exists", "select s_suppkey from supplier where exists (select 1 from lineitem where l_suppkey = s_suppkey and l_quantity > 49)")


@query("e_sql_udf", f"{VOX} select x, y, z, v * 2 + 1 as w from vox where z = 2")
def _(s, sf):
    s.sql("create or replace temporary function twice_plus(a bigint) returns bigint return a * 2 + 1")
    v(s, sf).createOrReplaceTempView("vox")
    return s.sql("select x, y, z, twice_plus(v) as w from vox where z = 2")


add("e_sql_values", lambda s, sf: s.sql("select a, b from values (1, 'x'), (2, 'y') t(a, b) where a >= :least", {"least": 2}), "select * from (values (1, 'x'), (2, 'y')) t(a, b) where a >= 2")
both("e_sample_hash", "select x, y, z, v from vox where (x * 73 + y * 19 + z * 31) % 4 = 0")
add(
    "e_sample_strat",
    lambda s, sf: (lambda e, rate: e.sampleBy("event_type", rate, 7).groupBy("event_type").agg(F.count("*").alias("n")).join(e.groupBy("event_type").agg(F.count("*").alias("all")), "event_type").select("event_type", (F.abs(F.col("n") / F.col("all") - F.when(F.col("event_type") == "view", 0.5).otherwise(0.1)) < 0.1).alias("near")))(tbl(s, sf, "events"), {"view": 0.5, "click": 0.1}),
    "select event_type, true as near from events where event_type in ('view', 'click') group by event_type",
)
# Functions
COD = f"{VOX} select x, y, z, {MORTON} as code from vox"
for name, f in (("py", udfs.morton_row), ("pandas", udfs.morton_pandas), ("arrow", udfs.morton_arrow)):
    add(f"e_udf_{name}", lambda s, sf, f=f: v(s, sf).select("x", "y", "z", f("x", "y", "z").alias("code")), COD)
add("e_udaf", lambda s, sf: v(s, sf).groupBy("x", "y").agg(udfs.mip_agg("v").alias("val")), f"{VOX} select x, y, max(v) as val from vox group by x, y")


@query("e_udtf", f"with {S.frame_pixels(A30, 'survey')}, grid as (select x, y, z, 0::bigint as v from (select unnest(range(40)) as x), (select unnest(range(40)) as y), (select unnest(range(18)) as z)), {S.hits(A30, 'grid').replace('select u, v,', 'select px.u, px.v,', 1)} select u, v, x, y, z from hit where v = 32")
def _(s, sf):
    udfs.register(s)
    r = view.rays(s.range(64).selectExpr("int(id) u", "32 v"), A30, SURVEY)
    r.createOrReplaceTempView("one_line")
    return s.sql("select u, v, bigint(t.x) x, bigint(t.y) y, bigint(t.z) z from one_line, lateral ray_voxels(ox, oy, oz, dx, dy, dz, 40, 40, 18) t")


@query("e_udtf_kd", f"with {S.kd_tree(SURVEY.dims, 6)} select brick, x0, x1, y0, y1, z0, z1 from leaf")
def _(s, sf):
    udfs.register(s)
    return s.sql("select * from kd_leaves(40, 40, 18, 6)")


add("e_grp_pandas", lambda s, sf: composite.pack(composite.node(partials(s, sf)), view.node_rects(view.rects(kd.two_level(SURVEY.dims, [2] * 4).frame(s), A30, SURVEY)), True).select("node", F.length("data").alias("bytes")), f"{MESSAGE} select node, (4 * count(*))::int as bytes from buf group by node")
add("e_map_arrow", lambda s, sf: partials(s, sf).groupBy("brick").agg(F.sum("samples").alias("samples")), f"{NODEHIT} select brick, count(*) as samples from nh group by brick")
add("e_cogroup", lambda s, sf: udfs.frame_diff(render.axis_frame(v(s, sf), SURVEY, ViewSpec(0)), render.axis_frame(v(s, sf), SURVEY, ViewSpec(180))), f"with a as ({S.mip(ViewSpec(0), 'survey')}), b as ({S.mip(ViewSpec(180), 'survey')}), j as (select coalesce(a.v, b.v) as v, coalesce(a.val, 0) as p, coalesce(b.val, 0) as q from a full join b on a.u = b.u and a.v = b.v) select v, count(*) filter (p <> q) as differ, max(abs(p - q)) as maxabs from j group by v")
# Serving
add("m_msg", lambda s, sf: serve.decode(tbl(s, sf, "events")).drop("ts"), "select event_id as frame, user_id as session, 15 * ((props->>'$.k')::int % 24) as angle, 1 + ((props->>'$.k')::int % 4) / 2 as zoom, event_type as cmap from events")
add("m_last", lambda s, sf: serve.latest(serve.decode(tbl(s, sf, "events"))).select("session", "frame"), "select user_id as session, max(event_id) as frame from events group by user_id")
add(
    "m_fsm",
    lambda s, sf: serve.validate(tbl(s, sf, "events")).groupBy("user_id").agg(F.count("*").alias("n"), F.count_if("ok").alias("allowed"), F.max_by("state", "event_id").alias("state")),
    """with recursive o as (select user_id, event_id, event_type, row_number() over (partition by user_id order by ts, event_id) as i from events),
r as (select user_id, 0::bigint as i, 'init' as state, 0::bigint as allowed, 0::bigint as event_id from (select distinct user_id from events)
  union all select o.user_id, o.i, case when r.state in ('init', 'closed') and event_type = 'signup' then 'open' when r.state = 'open' and event_type = 'error' then 'closed' else r.state end,
    r.allowed + case when (r.state in ('init', 'closed') and event_type = 'signup') or (r.state = 'open' and event_type in ('view', 'click', 'purchase', 'error')) then 1 else 0 end, o.event_id
  from r join o on o.user_id = r.user_id and o.i = r.i + 1)
select user_id, max(i) as n, max(allowed) as allowed, arg_max(state, i) as state from r group by user_id""",
)
add("m_fsm_dialogue", lambda s, sf: serve.alternation(tbl(s, sf, "conversations")), "select conv_id, turn, case when p is null then role in ('system', 'user') when role = 'user' then p in ('system', 'assistant') when role = 'assistant' then p = 'user' else false end as ok from (select *, lag(role) over (partition by conv_id order by turn) as p from conversations)")
# Sinks


@query("e_sink_part", f"{VOX} select z % 4 as part, count(*) as n from vox group by 1")
def _(s, sf):
    path = scratch(s)
    v(s, sf).withColumn("part", F.col("z") % 4).write.partitionBy("part").parquet(path)
    return s.read.parquet(path).groupBy(F.col("part").cast("long").alias("part")).agg(F.count("*").alias("n"))


@query("e_sink_bucket", f"with {S.kd_tree(SURVEY.dims, 8)}, {S.SURVEY} select brick, count(*) as n from vox join leaf on x >= x0 and x < x1 and y >= y0 and y < y1 and z >= z0 and z < z1 group by brick")
def _(s, sf):
    name = f"voxels_{uuid.uuid4().hex}"
    sinks.write_bucketed(partition.assign(v(s, sf), kd.kd(SURVEY.dims, 8)), name)
    return s.table(name).groupBy("brick").agg(F.count("*").alias("n"))


@query("e_sink_ppm", f"select count(distinct v) as lines, count(distinct v) * 64 as bytes from ({S.mip(A30, 'survey')})")
def _(s, sf):
    """Scan lines and pixel bytes of the image files; each has a text line before them."""
    path = shared_path(s)
    sinks.frame_pgm(composite.final(partials(s, sf)), 64, 64, path, 66_191_316)
    head = F.substring_index(F.decode(F.substring("content", 1, 24), "ISO-8859-1"), "\n", 1)
    files = s.read.format("binaryFile").load(path).select(F.split(head, " ")[2].cast("long").alias("lines"), (F.col("length") - F.length(head) - 1).alias("bytes"))
    return files.agg(F.sum("lines").alias("lines"), F.sum("bytes").alias("bytes"))


# Streams over files; each is run to its end and its result read back


def streamed(s, sf):
    src = tbl(s, sf, "events").schema
    folder = scratch(s)
    tbl(s, sf, "events").repartitionByRange(4, "event_id").write.parquet(folder)
    return serve.timed(s.readStream.schema(src).option("maxFilesPerTrigger", 2).parquet(folder))


STATE = "spark.sql.streaming.stateStore.providerClass"
SHUFFLE = "spark.sql.shuffle.partitions"
STORE_ROWS = 250_000
ON_DISK = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def drained(s, df, mode="complete", stores=None):
    """Runs a stream over all that is there and returns its last result. Appended rows grow with the input: they go to files, not to the driver, and their state to disk.
    ``stores``: partitions of the state, at most those of a shuffle; each costs the same small time in every batch, however little it holds."""
    name, sink = f"out_{uuid.uuid4().hex}", scratch(s)
    writer = df.writeStream.outputMode(mode).option("checkpointLocation", scratch(s)).trigger(availableNow=True)
    if mode != "append":
        writer.format("memory").queryName(name).start().awaitTermination()
        return s.table(name)
    held = {STATE: ON_DISK} | ({} if stores is None else {SHUFFLE: str(min(stores, int(s.conf.get(SHUFFLE))))})
    before = {k: s.conf.get(k, None) for k in held}
    for k, v in held.items():
        s.conf.set(k, v)
    try:
        writer.format("parquet").option("path", sink).start().awaitTermination()
    finally:
        for k, v in before.items():
            s.conf.unset(k) if v is None else s.conf.set(k, v)
    return s.read.schema(df.schema).parquet(sink)


add("s_tumbling", lambda s, sf: drained(s, streamed(s, sf).withWatermark("ts", "1 day").groupBy(F.window("ts", "6 hours"), "event_type").agg(F.count("*").alias("n"), F.max("value").alias("top"))).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "event_type", "n", "top"), "select time_bucket(interval '6 hours', ts) as start, event_type, count(*) as n, max(value) as top from events group by 1, 2")
add("s_sliding", lambda s, sf: drained(s, streamed(s, sf).groupBy(F.window("ts", "6 hours", "3 hours")).agg(F.count("*").alias("n"))).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n"), "select time_bucket(interval '3 hours', ts) - i * interval '3 hours' as start, count(*) as n from events, (select unnest([0, 1]) as i) group by 1")
def in_time_order(s, e, closing="4 days"):
    """A stream of events that arrive in the order of their time: four files written one after another, so that no event is late, and a last
    one whose only row, so much later, closes every session that is open at the end. That row has no user and its own session never closes."""
    folder = scratch(s)
    cuts = e.select(F.percentile_approx("ts", [0.25, 0.5, 0.75], 10_000).alias("cuts")).first()["cuts"] or []
    cuts = sorted(set(cuts))
    place = sum((F.when(F.col("ts") >= F.lit(c), 1).otherwise(0) for c in cuts), F.lit(0))
    for i in range(len(cuts) + 1):
        e.where(place == i).coalesce(1).write.mode("append").parquet(folder)
    last = e.agg(F.max("ts").alias("last")).where("last is not null")
    row = last.select(*[(F.expr(f"last + interval {closing}") if f.name == "ts" else F.lit(None)).cast(f.dataType).alias(f.name) for f in e.schema])
    row.write.mode("append").parquet(folder)
    return serve.timed(s.readStream.schema(e.schema).option("maxFilesPerTrigger", 2).parquet(folder))


SESSIONS = "select user_id, count(*) filter (gap is null or gap >= 7200000000) as sessions, count(*) as n from (select user_id, epoch_us(ts) - lag(epoch_us(ts)) over (partition by user_id order by ts) as gap from events) group by user_id"


@query("s_session", SESSIONS)
def _(s, sf):
    """Sessions go out when they close; what is kept meanwhile is on disk."""
    e = tbl(s, sf, "events")
    stream = in_time_order(s, e).withWatermark("ts", "1 day")
    closed = drained(s, stream.groupBy(F.session_window("ts", "2 hours"), "user_id").agg(F.count("*").alias("n")), "append", max(4, -(-e.count() // STORE_ROWS)))
    return closed.groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("n"))


def top_user(s, sf):
    return tbl(s, sf, "events").agg(F.max("user_id") + 1).first()[0]


add("s_cube_inc", lambda s, sf: drained(s, serve.cube_stream(streamed(s, sf), top_user(s, sf))), f"with {S.WIDE} select x, y, z, v from vox")
add("s_frame_inc", lambda s, sf: drained(s, serve.mip_stream(streamed(s, sf), top_user(s, sf))), "with m as (select max(user_id) + 1 as ux from events) select (user_id * 27) // ux as u, ((hour(ts) * 60 + minute(ts)) * 27) // 1440 as w, max(round(value * 1e2)::bigint)::bigint as val from events, m group by 1, 2")
add("s_fsm", lambda s, sf: drained(s, serve.session_states(streamed(s, sf).withWatermark("ts", "1 day")), "append").groupBy("user_id").agg(F.max("n").alias("n")), "select user_id, count(*) as n from events group by user_id")


@query("s_dedup", "select event_type, count(*) as n from events group by event_type")
def _(s, sf):
    """Every event twice; the second goes within the watermark."""
    e = tbl(s, sf, "events")
    folder = scratch(s)
    e.unionByName(e).repartitionByRange(4, "event_id").write.parquet(folder)
    stream = serve.timed(s.readStream.schema(e.schema).parquet(folder)).withWatermark("ts", "30 days")
    return drained(s, stream.dropDuplicatesWithinWatermark(["event_id"]), "append").groupBy("event_type").agg(F.count("*").alias("n"))


@query("s_late", "select count(*) as n from events where time_bucket(interval '1 day', ts) + interval '1 day' <= (select max(ts) from events) - interval '1 hour'")
def _(s, sf):
    """Every tenth event sent again twenty days earlier, after the watermark passed it, is dropped: closed days hold what came in time."""
    e = tbl(s, sf, "events")
    folder, sink, mark = scratch(s), scratch(s), scratch(s)
    for part in (e, e.where("event_id % 10 = 0").withColumn("ts", F.expr("ts - interval 20 days"))):
        part.coalesce(1).write.mode("append").parquet(folder)
        stream = serve.timed(s.readStream.schema(e.schema).parquet(folder)).withWatermark("ts", "1 hour")
        days = stream.groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n"))
        days.writeStream.format("parquet").option("path", sink).option("checkpointLocation", mark).trigger(availableNow=True).start().awaitTermination()
    return s.read.parquet(sink).agg(F.sum("n").alias("n"))


add("s_join_static", lambda s, sf: drained(s, streamed(s, sf).join(F.broadcast(s.createDataFrame([("view", 1), ("click", 2)], "event_type string, weight int")), "event_type").groupBy("event_type").agg(F.sum("weight").alias("total"))), "select event_type, sum(case event_type when 'view' then 1 else 2 end)::bigint as total from events where event_type in ('view', 'click') group by event_type")


@query("s_join_stream", "select count(*) as n from events a join events b on a.user_id = b.user_id and b.ts >= a.ts and b.ts <= a.ts + interval '1 hour' where a.event_type = 'view' and b.event_type = 'click'")
def _(s, sf):
    a = streamed(s, sf).where("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("ts").alias("at")).withWatermark("at", "2 hours")
    b = streamed(s, sf).where("event_type = 'click'").select("user_id", "ts").withWatermark("ts", "2 hours")
    return drained(s, a.join(b, F.expr("u = user_id and ts >= at and ts <= at + interval 1 hour")), "append").agg(F.count("*").alias("n"))


@query("s_foreach", "select user_id as session, max(event_id) as frame from events group by user_id")
def _(s, sf):
    """Each batch renders (here: lists) the newest request of a session; replays overwrite their own folder."""
    sink = scratch(s)
    serve.start(streamed(s, sf), lambda r: r.select("session", "frame"), sink, scratch(s)).awaitTermination()
    return s.read.parquet(sink).groupBy("session").agg(F.max("frame").alias("frame"))


@query("s_restart", "select event_type, count(*) as n from events group by event_type")
def _(s, sf):
    """A stream stopped after its first files goes on from its checkpoint."""
    e = tbl(s, sf, "events")
    folder, sink, mark = scratch(s), scratch(s), scratch(s)
    for part in (e.where("event_id % 2 = 0"), e.where("event_id % 2 = 1")):
        part.write.mode("append").parquet(folder)
        serve.timed(s.readStream.schema(e.schema).parquet(folder)).writeStream.format("parquet").option("path", sink).option("checkpointLocation", mark).trigger(availableNow=True).start().awaitTermination()
    return s.read.parquet(sink).groupBy("event_type").agg(F.count("*").alias("n"))


@query("m_async", f"select count(*) as pixels, true as together from ({S.mip(ViewSpec(0), 'survey')}) union all select count(*), true from ({S.mip(ViewSpec(30), 'survey')})")
def _(s, sf):
    """Two frames in flight: whether each began before the other was done."""

    def job(a):
        begin = time.time()
        n = render.frame(v(s, sf), SURVEY, ViewSpec(a)).count()
        return n, begin, time.time()

    out = serve.pipeline([lambda a=a: job(a) for a in (0, 30)], 2)
    together = max(x[1] for x in out) < min(x[2] for x in out)
    return s.createDataFrame([(n, together) for n, _, _ in out], "pixels long, together boolean")
