"""Registered queries of the rendering methods, each with its oracle."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import functions as F

from ..operators import array_engine, baseline, color, composite, cube, measure, partition, render, view
from ..plans import kd
from ..plans.spec import CUBES, PARTICLE, PUBLISHED, SURVEY, WIDE, ViewSpec
from ..sources import store
from . import sqltext as S
from .registry import add, query

LI = "lineitem"
BOXCOLS = "brick, x0, x1, y0, y1, z0, z1"


def tbl(s, sf, name):
    return s.read.parquet(f"{sf}/{name}.parquet")


def scratch(s) -> str:
    """A folder that all executors share; a local one only where none is set and all runs on this machine."""
    base = s.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not s.sparkContext.master.startswith("local") or s.sparkContext.master.startswith("local-"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = os.path.join(tempfile.gettempdir(), "cubecast-scratch")
    return f"{base}/{uuid.uuid4().hex}"


# Ingest

for name in ("survey", "wide", "particle", "survey_scaled"):
    add({"survey": "m_bin_survey", "wide": "m_bin_wide", "particle": "m_cic", "survey_scaled": "m_scale_i"}[name], lambda s, sf, n=name: cube.load(s, sf, n), f"with {S.CUBE[name]} select x, y, z, v from vox")
add("m_scale_r_nearest", lambda s, sf: cube.particle_scaled(s, sf), f"with {S.CUBE['particle_scaled']} select x, y, z, v from vox")


@query(
    "m_scale_r_trilinear",
    f"""with {S.WIDE},
g as (select i, k, greatest(0, least(n - 1, floor(((2 * i + 1) * n - m) / (2e0 * m))::bigint + k)) as s,
        case k when 1 then ((2 * i + 1) * n - m) - 2 * m * floor(((2 * i + 1) * n - m) / (2e0 * m))::bigint else 2 * m - (((2 * i + 1) * n - m) - 2 * m * floor(((2 * i + 1) * n - m) / (2e0 * m))::bigint) end as w, ax
      from (select unnest(range(40)) as i, 27 as n, 40 as m, 'x' as ax union all select unnest(range(40)), 27, 40, 'y' union all select unnest(range(24)), 16, 24, 'z'), (select unnest([0, 1]) as k))
select a.i as x, b.i as y, c.i as z, floor(sum((a.w * b.w * c.w)::decimal(38, 0) * v) / {8 * 40 * 40 * 24}e0 + 5e-1)::bigint as v
from vox join g a on a.ax = 'x' and a.s = vox.x join g b on b.ax = 'y' and b.s = vox.y join g c on c.ax = 'z' and c.s = vox.z
group by 1, 2, 3 having floor(sum((a.w * b.w * c.w)::decimal(38, 0) * v) / {8 * 40 * 40 * 24}e0 + 5e-1) <> 0""",
)
def _(s, sf):
    return cube.resample(cube.wide(s, sf), WIDE, (40, 40, 24), "trilinear")


@query("m_cic_wrap", f"with {S.cic('wrap')} select x, y, z, v from vox")
def _(s, sf):
    rows = tbl(s, sf, LI).select("l_quantity", "l_extendedprice", "l_shipdate")
    return cube.cloud(rows, cube.particle_coordinates(rows), PARTICLE, edge="wrap")


@query(
    "m_ngp",
    """select least(31, floor((l_quantity - 1e0) * 32e0 / 49e0))::bigint as x, least(31, floor(l_extendedprice * 32e0 / 105000e0))::bigint as y,
least(31, floor(date_diff('day', date '1995-01-01', l_shipdate::date)::double * 32e0 / 2520e0))::bigint as z, count(*) as v from lineitem group by 1, 2, 3""",
)
def _(s, sf):
    rows = tbl(s, sf, LI).select("l_quantity", "l_extendedprice", "l_shipdate")
    return cube.build(rows, *[F.least(F.lit(31), F.floor(c)) for c in cube.particle_coordinates(rows)], agg="count")


@query("m_synth", "select id % 30 as x, (id // 30) % 20 as y, id // 600 as z, (id % 30 * 73 + (id // 30) % 20 * 19 + id // 600 * 31) % 1009 + case when (id % 30 + (id // 30) % 20 + id // 600) % 17 = 0 then 1000 else 0 end as v from (select unnest(range(9000)) as id)")
def _(s, sf):
    return cube.synth(s, (30, 20, 15))


def assigned(s, sf, n=8, name="survey"):
    return partition.assign(cube.load(s, sf, name), kd.kd(CUBES[name].dims, n))


IN_LEAF = S.IN_LEAF


def leaf_vox(n, name="survey"):
    return f"with {S.kd_tree(CUBES[name].dims, n)}, {S.CUBE[name]}, own as (select vox.*, brick from vox join leaf on {IN_LEAF})"


add("m_minmax", lambda s, sf: cube.minmax(assigned(s, sf)), f"{leaf_vox(8)} select brick, min(v) as lo, max(v) as hi from own group by brick")
add(
    "b_slab",
    lambda s, sf: partition.loads(cube.survey(s, sf), kd.slab(SURVEY.dims, 6, 2)).select("brick", *view.BOX, "n"),
    f"with {S.kd_tree(SURVEY.dims, 6, 2)}, {S.SURVEY} select {BOXCOLS}, count(vox.x) as n from leaf left join vox on {IN_LEAF} group by all",
)
add("m_minmax_global", lambda s, sf: cube.global_range(cube.minmax(assigned(s, sf))), f"with {S.SURVEY} select min(v) as lo, max(v) as hi from vox")


@query("m_meta", "select 'survey' as name, 40 as nx, 40 as ny, 18 as nz, 28800 as voxels")
def _(s, sf):
    """Dimensions from the file beside a stored cube; no voxel is read."""
    path = scratch(s)
    store.write_spec(s, SURVEY, path)
    spec = store.read_spec(s, path)
    return s.createDataFrame([(spec.name, *spec.dims, spec.volume)], "name string, nx int, ny int, nz int, voxels int")


# Partition

for n in (1, 2, 3, 5, 6, 7, 8, 12, 64):
    add(f"m_kd_{n}" if n & (n - 1) == 0 else f"m_kdf_{n}", lambda s, sf, n=n: kd.kd(SURVEY.dims, n).frame(s).select("brick", *view.BOX), f"with {S.kd_tree(SURVEY.dims, n)} select {BOXCOLS} from leaf")
for key, (dims, _) in PUBLISHED.items():
    add(f"m_kd_published_{key}", lambda s, sf, dims=dims: kd.kd(dims, 64).frame(s).select("brick", *view.BOX), f"with {S.kd_tree(dims, 64)} select {BOXCOLS} from leaf")


@query(
    "m_kd2",
    f"with {S.kd_tree(SURVEY.dims, 8)} select brick, brick // 2 as node, brick % 2 as gpu, x0, x1, y0, y1, z0, z1 from leaf",
)
def _(s, sf):
    return kd.two_level(SURVEY.dims, [2, 2, 2, 2]).frame(s)


KD2_UNEVEN = """with recursive g as (select s_nationkey as nation, count(*)::bigint as c, row_number() over (order by s_nationkey) - 1 as i from supplier group by 1),
pre as (select list_prepend(0::bigint, list(t order by i)) as p, count(*)::bigint as k from (select i, sum(c) over (order by i)::bigint as t from g)),
t as (select 0::bigint as f, k as n, 0::bigint as x0, 4000::bigint as x1, 0::bigint as y0, 4000::bigint as y1, 0::bigint as z0, 1800::bigint as z1 from pre
  union all
  (with q as (select t.*, (1 << (length(bin(n - 1)) - 1))::bigint as l, case when x1 - x0 >= y1 - y0 and x1 - x0 >= z1 - z0 then 0 when y1 - y0 >= z1 - z0 then 1 else 2 end as a from t where n > 1),
   w as (select q.*, p[f + l + 1] - p[f + 1] as mine, p[f + n + 1] - p[f + 1] as every, case a when 0 then x1 - x0 when 1 then y1 - y0 else z1 - z0 end as e, case a when 0 then x0 when 1 then y0 else z0 end as lo from q, pre),
   c as (select *, lo + (2 * e * mine + every) // (2 * every) as cut from w)
   select f, l, x0, case when a = 0 then cut else x1 end, y0, case when a = 1 then cut else y1 end, z0, case when a = 2 then cut else z1 end from c
   union all select f + l, n - l, case when a = 0 then cut else x0 end, x1, case when a = 1 then cut else y0 end, y1, case when a = 2 then cut else z0 end, z1 from c))
select g.nation as node, c as gpus, x0, x1, y0, y1, z0, z1, (x1 - x0) * (y1 - y0) * (z1 - z0) as volume from t join g on g.i = t.f where t.n = 1"""


def topology(s, sf, dims):
    """A real topology: suppliers as GPUs of nations. The plan, and the nation of each node."""
    rows = tbl(s, sf, "supplier").groupBy("s_nationkey").count().orderBy("s_nationkey").collect()  # one row a node
    return kd.two_level(dims, [r["count"] for r in rows]), s.createDataFrame([(i, r["s_nationkey"]) for i, r in enumerate(rows)], "node int, nation int")


@query("m_kd2_uneven", KD2_UNEVEN)
def _(s, sf):
    """Bricks and box of each node of an uneven topology; the bricks of a node fill its box."""
    plan, names = topology(s, sf, (4000, 4000, 1800))
    volume = F.sum((F.col("x1") - F.col("x0")).cast("long") * (F.col("y1") - F.col("y0")) * (F.col("z1") - F.col("z0")))
    box = [f(c).cast("long").alias(c) for c in view.BOX for f in (F.min if c.endswith("0") else F.max,)]
    return plan.frame(s).join(names, "node").groupBy(F.col("nation").alias("node")).agg(F.count("*").alias("gpus"), *box, volume.alias("volume"))


@query(
    "m_fit",
    "select * from (values " + ", ".join(f"('{k}', {dims[0]}::bigint * {dims[1]} * {dims[2]} * 4)" for k, (dims, _) in PUBLISHED.items()) + ") t(cube, bytes), (select (bytes + 8589934591) // 8589934592 as nodes_4gb, (bytes + 12884901887) // 12884901888 as nodes_6gb)",
)
def _(s, sf):
    rows = [(k, kd.needed_bytes(dims), kd.min_nodes(dims, 2, 4 << 30, 32 << 30), kd.min_nodes(dims, 2, 6 << 30, 32 << 30)) for k, (dims, _) in PUBLISHED.items()]
    return s.createDataFrame(rows, "cube string, bytes long, nodes_4gb long, nodes_6gb long")


for n in (5, 8, 64, 100):
    add(f"m_asgn_{n}", lambda s, sf, n=n: assigned(s, sf, n).groupBy("brick").agg(F.count("*").alias("n"), F.sum("v").alias("total")), f"{leaf_vox(n)} select brick, count(*) as n, sum(v)::bigint as total from own group by brick")
add(
    "m_asgn_rj",
    lambda s, sf: partition.assign_range(cube.survey(s, sf), kd.kd(SURVEY.dims, 8).frame(s)).select("x", "y", "z", "v", "brick"),
    f"{leaf_vox(8)} select x, y, z, v, brick from own",
)
add(
    "m_halo",
    lambda s, sf: partition.halo(cube.survey(s, sf), kd.kd(SURVEY.dims, 8)).groupBy("brick", "ghost").agg(F.count("*").alias("n"), F.sum("v").alias("total")),
    f"""{leaf_vox(8)} select l.brick, o.brick <> l.brick as ghost, count(*) as n, sum(v)::bigint as total from own o, leaf l
where o.x >= l.x0 - 1 and o.x < l.x1 + 1 and o.y >= l.y0 - 1 and o.y < l.y1 + 1 and o.z >= l.z0 - 1 and o.z < l.z1 + 1 group by 1, 2""",
)
QUALITY = """select count(*) as bricks, min(vol)::bigint as least, max(vol)::bigint as most, round(max(vol) / min(vol)::double, 6) as balance, round(max(greatest(x1 - x0, y1 - y0, z1 - z0) / least(x1 - x0, y1 - y0, z1 - z0)::double), 6) as side_ratio
from (select *, (x1 - x0)::bigint * (y1 - y0) * (z1 - z0) as vol from leaf)"""
for n in (5, 6, 8, 64):
    add(f"m_bal_{n}", lambda s, sf, n=n: partition.quality(s, kd.kd(SURVEY.dims, n)), f"with {S.kd_tree(SURVEY.dims, n)} {QUALITY}")
LOADS = QUALITY.replace("vol) / min(vol)::double", "vol) / nullif(min(vol), 0)::double").split("from (select")[0] + f"from (select leaf.*, n as vol from leaf join (select brick, count(vox.x) as n from leaf left join vox on {IN_LEAF} group by brick) using (brick))"
add("c_bal_slab", lambda s, sf: partition.quality(s, kd.slab(SURVEY.dims, 6), cube.survey(s, sf)), f"with {S.kd_tree(SURVEY.dims, 6, 2)}, {S.SURVEY} {LOADS}")
LARGE = PUBLISHED["survey_scaled"][0]
add(
    "c_bal_published",
    lambda s, sf: partition.quality(s, kd.kd(LARGE, 128), cube.survey_points(s, sf, LARGE)),
    f"with {S.kd_tree(LARGE, 128)}, {S.survey_points(LARGE)} {LOADS}",
)

# Views, rectangles, rays

A30, A60, A0, A90 = (ViewSpec(a) for a in (30, 60, 0, 90))
ZOOMED = ViewSpec(30, zoom=2.5)
NEAR = ViewSpec(30, distance=0.9)
INSIDE = ViewSpec(30, distance=0.1)


def bricks(s, n=8, spec=SURVEY):
    return kd.kd(spec.dims, n).frame(s)


for key, v in (("30", A30), ("60", A60), ("90", A90), ("zoom", ZOOMED), ("persp", NEAR), ("behind", INSIDE)):
    add(f"m_rect_{key}", lambda s, sf, v=v: view.rects(bricks(s), v, SURVEY).drop("node"), f"with {S.kd_tree(SURVEY.dims, 8)}, {S.rects(v, 'survey')} select brick, u0, u1, v0, v1 from rect")
add(
    "m_rect_u",
    lambda s, sf: view.node_rects(view.rects(kd.two_level(SURVEY.dims, [2] * 4).frame(s), A30, SURVEY)),
    f"with {S.kd_tree(SURVEY.dims, 8)}, {S.rects(A30, 'survey', node='brick // 2')} select node, min(u0) as u0, max(u1) as u1, min(v0) as v0, max(v1) as v1 from rect group by node",
)
add(
    "m_rect_x",
    lambda s, sf: view.pixels(view.rects(bricks(s), A30, SURVEY)).groupBy("brick").agg(F.count("*").alias("rays")),
    f"with {S.kd_tree(SURVEY.dims, 8)}, {S.rects(A30, 'survey')} select brick, ((u1 - u0) * (v1 - v0))::bigint as rays from rect",
)
add(
    "m_rect_e",
    lambda s, sf: view.rects(bricks(s, 64), ViewSpec(30, zoom=6.0), SURVEY).agg(F.count("*").alias("seen")).withColumn("all", F.lit(64)),
    f"with {S.kd_tree(SURVEY.dims, 64)}, {S.rects(ViewSpec(30, zoom=6.0), 'survey')} select count(*) as seen, 64 as \"all\" from rect",
)
add(
    "m_map",
    lambda s, sf: view.rects(bricks(s), A30, SURVEY).join(view.rects(bricks(s), A60, SURVEY).select("brick", *[F.col(c).alias(f"next_{c}") for c in ("u0", "u1", "v0", "v1")]), "brick").drop("node"),
    f"with {S.kd_tree(SURVEY.dims, 8)}, {S.rects(A30, 'survey')}, b as (with {S.rects(A60, 'survey')} select * from rect) select r.brick, r.u0, r.u1, r.v0, r.v1, b.u0 as next_u0, b.u1 as next_u1, b.v0 as next_v0, b.v1 as next_v1 from rect r join b on r.brick = b.brick",
)
add(
    "m_ray_o",
    lambda s, sf: view.rays(s.range(64 * 64).selectExpr("int(id % 64) u", "int(id div 64) v"), A30, SURVEY).select("u", "v", *[F.round(c, 6).alias(c) for c in ("ox", "oy", "oz", "dx", "dy", "dz")]),
    f"with {S.frame_pixels(A30, 'survey')} select u, v, round(ox, 6) as ox, round(oy, 6) as oy, round(oz, 6) as oz, round({S.d(-A30.sin)}, 6) as dx, 0e0 as dy, round({S.d(A30.cos)}, 6) as dz from px",
)


def _persp_sql():
    eye = NEAR.eye(SURVEY)
    return f"with {S.frame_pixels(NEAR, 'survey')} select u, v, round(ox - {S.d(eye[0])}, 6) as dx, round(oy - {S.d(eye[1])}, 6) as dy, round(oz - {S.d(eye[2])}, 6) as dz from px"


add(
    "m_ray_p",
    lambda s, sf: view.rays(s.range(64 * 64).selectExpr("int(id % 64) u", "int(id div 64) v"), NEAR, SURVEY).select("u", "v", *[F.round(c, 6).alias(c) for c in ("dx", "dy", "dz")]),
    _persp_sql(),
)
RAYS = f"with {S.kd_tree(SURVEY.dims, 8)}, {S.frame_pixels(A30, 'survey')}, {S.box_hits(A30)}"
add(
    "m_slab",
    lambda s, sf: render.brick_rays(SURVEY, A30, kd.kd(SURVEY.dims, 8), s).select("brick", "u", "v", F.round("te", 6).alias("te"), F.round("tx", 6).alias("tx")),
    f"{RAYS} select brick, u, v, round(te, 6) as te, round(tx, 6) as tx from ray",
)
add(
    "m_miss",
    lambda s, sf: view.box_rays(bricks(s), A30, SURVEY)
    .groupBy("brick")
    .agg(F.count("*").alias("started"))
    .join(render.brick_rays(SURVEY, A30, kd.kd(SURVEY.dims, 8), s).groupBy("brick").agg(F.count("*").alias("hit")), "brick")
    .select("brick", "started", "hit", (F.col("started") - F.col("hit")).alias("missed")),
    f"{RAYS}, {S.rects(A30, 'survey')} select r.brick, ((u1 - u0) * (v1 - v0))::bigint as started, h.hit, (u1 - u0) * (v1 - v0) - h.hit as missed from rect r join (select brick, count(*) as hit from ray group by brick) h on h.brick = r.brick",
)

# Frames

for a in (0, 30, 60, 90, 135):
    add(f"m_exec_sql_{a}", lambda s, sf, a=a: render.frame(cube.survey(s, sf), SURVEY, ViewSpec(a)), S.mip(ViewSpec(a), "survey"))
add("m_exec_sql_wide_45", lambda s, sf: render.frame(cube.wide(s, sf), WIDE, ViewSpec(45), kd.kd(WIDE.dims, 5)), S.mip(ViewSpec(45), "wide"))
add("m_exec_sql_particle_15", lambda s, sf: render.frame(cube.particle(s, sf), PARTICLE, ViewSpec(15)), S.mip(ViewSpec(15), "particle"))


def survey_blocks(s, sf, n=8, **how):
    return array_engine.pack_bricks(cube.survey(s, sf), kd.kd(SURVEY.dims, n), **how)


def array_frame(s, sf, v, name="survey", n=8, stop=None):
    spec = CUBES[name]
    packed = array_engine.pack_bricks(cube.load(s, sf, name), kd.kd(spec.dims, n))
    return array_engine.cast(packed, spec, [v], stop)


for a in (0, 30, 60, 90):
    add(f"m_exec_arr_{a}", lambda s, sf, a=a: composite.final(array_frame(s, sf, ViewSpec(a))), S.mip(ViewSpec(a), "survey"))
SHIFT = 30_000_000
add(
    "m_exec_arr_negative",
    lambda s, sf: composite.final(array_engine.cast(array_engine.pack_bricks(cube.survey(s, sf).withColumn("v", F.col("v") - SHIFT), kd.kd(SURVEY.dims, 8)), SURVEY, [A30])),
    f"with {S.hit_cte(A30, 'survey')} select u, v, max(value)::bigint - {SHIFT} as val from hit group by u, v",
)
for a in (0, 90, 180, 270):
    add(f"m_exec_obj_{a}", lambda s, sf, a=a: render.axis_frame(cube.survey(s, sf), SURVEY, ViewSpec(a)), S.mip(ViewSpec(a), "survey"))


@query("m_end_max", S.mip(A30, "survey"))
def _(s, sf):
    v = cube.survey(s, sf)
    top = v.agg(F.max("v")).first()[0]  # the global range is known since the cube was loaded
    return render.terminated(v, SURVEY, A30, top)


@query("m_end_max_array", S.mip(A30, "survey"))
def _(s, sf):
    v = cube.survey(s, sf)
    top = v.agg(F.max("v")).first()[0]
    return composite.final(array_frame(s, sf, A30, stop=top))


add(
    "m_end_exit",
    lambda s, sf: render.exact_mids(render.brick_rays(SURVEY, A30, kd.kd(SURVEY.dims, 8), s)).select(F.size("mids").alias("n"), (F.array_max("mids") < F.col("tx")).alias("inside")).groupBy("inside").agg(F.sum("n").alias("samples")),
    f"with {S.frame_pixels(A30, 'survey')}, grid as (select x, y, z, 0::bigint as v from (select unnest(range(40)) as x), (select unnest(range(40)) as y), (select unnest(range(18)) as z)), {S.hits(A30, 'grid').replace('select u, v,', 'select px.u, px.v,', 1)} select true as inside, count(*) as samples from hit",
)
FAINT = 40_000_000
BRIGHT = f"with {S.SURVEY.replace('vox as', 'vox0 as')}, vox as (select * from vox0 where v > {FAINT})"
BRIGHT_HIT = f"{BRIGHT}, {S.hit_cte(A30, 'survey', 'one as (select 1)')}"
add("m_skip", lambda s, sf: render.skipping_frame(cube.survey(s, sf), SURVEY, A30, kd.kd(SURVEY.dims, 64), FAINT), f"{BRIGHT_HIT} select u, v, max(value)::bigint as val from hit group by u, v")


def stored_blocks(s, sf, block=4, dtype="<i8"):
    """Small blocks of the survey cube, written once and read back."""
    path = scratch(s)
    store.write_blocks(array_engine.pack_bricks(cube.survey(s, sf), kd.kd(SURVEY.dims, 8), dtype=dtype, block=block), path)
    return path


@query("m_skip_array", f"{BRIGHT_HIT} select u, v, max(value)::bigint as val from hit group by u, v")
def _(s, sf):
    """The same from stored blocks, of which the scan opens those that have something above the background."""
    blocks = array_engine.skip_empty(store.read_bricks(s, stored_blocks(s, sf)), FAINT)
    return composite.final(array_engine.cast(blocks, SURVEY, [A30])).where(F.col("val") > FAINT)


@query(
    "m_skip_saved",
    f"with {S.kd_tree(SURVEY.dims, 8)}, {S.SURVEY}, b as (select brick, vox.x // 4 as i, vox.y // 4 as j, vox.z // 4 as k, max(v) as hi from vox join leaf on {IN_LEAF} group by all) select count(*) as blocks, count(*) filter (hi > {FAINT}) as read from b",
)
def _(s, sf):
    """Blocks there are, and blocks a skipping frame reads."""
    blocks = store.read_bricks(s, stored_blocks(s, sf))
    return blocks.agg(F.count("*").alias("blocks")).crossJoin(array_engine.skip_empty(blocks, FAINT).agg(F.count("*").alias("read")))


CLOSE = ViewSpec(30, zoom=6.0)


@query("m_scan", S.mip(CLOSE, "survey"))
def _(s, sf):
    """A frame that opens only the bricks its view can see: they prune the partitions of the stored cube."""
    plan = kd.kd(SURVEY.dims, 64)
    path = scratch(s)
    store.write_blocks(array_engine.pack_bricks(cube.survey(s, sf), plan), path)
    return composite.final(array_engine.cast(store.read_bricks(s, path, array_engine.seen_bricks(plan, SURVEY, [CLOSE])), SURVEY, [CLOSE]))


@query("m_tex", S.mip(A30, "survey").replace("max(value)::bigint", "max(value::float)::double"))
def _(s, sf):
    """Blocks of four-byte reals, pinned in memory, from which frames are cast."""
    blocks = store.pin(store.read_bricks(s, stored_blocks(s, sf, 64, "<f4")))
    return composite.final(array_engine.cast(blocks, SURVEY, [A30])).withColumn("val", F.col("val").cast("double"))
add(
    "m_smp_x",
    lambda s, sf: render.samples(render.exact_mids(render.brick_rays(SURVEY, A30, kd.kd(SURVEY.dims, 8), s)), ("u", "v")).join(cube.survey(s, sf).select("x", "y", "z"), ["x", "y", "z"]).select("u", "v", "x", "y", "z"),
    f"with {S.hit_cte(A30, 'survey')} select u, v, x, y, z from hit",
)


def uniform_sql(v, n_expr, mid, cube_name="survey"):
    dx, dz = S.d(-v.sin), S.d(v.cos)
    return f"""with {S.kd_tree(CUBES[cube_name].dims, 1)}, {S.CUBE[cube_name]}, {S.frame_pixels(v, cube_name)}, {S.box_hits(v)},
nn as (select px.*, te, tx, {n_expr.format(dx=dx, dz=dz)} as n from ray join px on px.u = ray.u and px.v = ray.v),
smp as (select u, v, floor(ox + t * {dx})::bigint as x, floor(oy)::bigint as y, floor(oz + t * {dz})::bigint as z from (select *, {mid} as t from nn) q)
select smp.u, smp.v, max(vox.v)::bigint as val from smp join vox on vox.x = smp.x and vox.y = smp.y and vox.z = smp.z group by 1, 2"""


L1 = "(abs(floor(ox + (tx - 1e-9) * {dx}) - floor(ox + (te + 1e-9) * {dx})) + abs(floor(oz + (tx - 1e-9) * {dz}) - floor(oz + (te + 1e-9) * {dz})) + 1)::bigint"
LINF = "(greatest(abs(floor(ox + (tx - 1e-9) * {dx}) - floor(ox + (te + 1e-9) * {dx})), abs(floor(oz + (tx - 1e-9) * {dz}) - floor(oz + (te + 1e-9) * {dz}))) + 1)::bigint"
UNIT = "greatest(1, ceil(sqrt(0e0 + ((tx - te) * abs({dx})) * ((tx - te) * abs({dx})) + 0e0 + ((tx - te) * abs({dz})) * ((tx - te) * abs({dz})))))::bigint"
HALF = UNIT.replace("ceil(sqrt(", "ceil(2e0 * sqrt(")
EVEN = "te + (unnest(range(n)) + 5e-1) * ((tx - te) / n)"
for rule, n in (("l1", L1), ("linf", LINF), ("unit", UNIT), ("half", HALF)):
    add(f"m_smp_u_{rule}", lambda s, sf, rule=rule: render.frame(cube.survey(s, sf), SURVEY, A30, kd.kd(SURVEY.dims, 1), "uniform", rule=rule), uniform_sql(A30, n, EVEN))
    add(f"m_smp_u_{rule}_array", lambda s, sf, rule=rule: composite.final(array_engine.cast(survey_blocks(s, sf), SURVEY, [A30], mode="uniform", rule=rule)), uniform_sql(A30, n, EVEN))
FIXED = "unnest(range(ceil(te / 1e0)::bigint, ceil(tx / 1e0)::bigint)) * 1e0"
add("m_smp_f", lambda s, sf: render.frame(cube.survey(s, sf), SURVEY, A30, kd.kd(SURVEY.dims, 8), "fixed", dt=1.0), uniform_sql(A30, "1", FIXED))
add("m_smp_f_array", lambda s, sf: composite.final(array_engine.cast(survey_blocks(s, sf), SURVEY, [A30], mode="fixed", dt=1.0)), uniform_sql(A30, "1", FIXED))
#: own(u, v, value, brick): fixed-step samples that see a voxel, by the brick (leaf) the voxel lies in.
LEAF_FIXED = f"""whole as (select 0 as brick, 0 as x0, 40 as x1, 0 as y0, 40 as y1, 0 as z0, 18 as z1), {S.box_hits(A30, "whole")}, smp as (select u, v, floor(ox + t * {S.d(-A30.sin)})::bigint as x, floor(oy)::bigint as y, floor(oz + t * {S.d(A30.cos)})::bigint as z
  from (select *, {FIXED} as t from (select px.*, te, tx from ray join px on px.u = ray.u and px.v = ray.v) nn) q),
own as (select smp.u, smp.v, vox.v as value, leaf.brick from smp join vox on vox.x = smp.x and vox.y = smp.y and vox.z = smp.z join leaf on {IN_LEAF})"""
add("b_fixed", lambda s, sf: render.frame(cube.survey(s, sf), SURVEY, A60, kd.kd(SURVEY.dims, 5), "fixed", dt=1.0), uniform_sql(A60, "1", FIXED))


# Transfer functions


def survey_samples(s, sf, v=A30, n=8, keep=("u", "v")):
    return render.nearest(render.samples(render.exact_mids(render.brick_rays(SURVEY, v, kd.kd(SURVEY.dims, n), s)), keep), cube.survey(s, sf))


HIT30 = f"with {S.hit_cte(A30, 'survey')}"
for key, f, sql in (
    ("mip", "max(value)", "max(value)::bigint"),
    ("min", "min(value)", "min(value)::bigint"),
    ("sum", "sum(value)", "sum(value)::bigint"),
    ("avg", "sum(value) div count(*)", "(sum(value) // count(*))::bigint"),
):
    add(f"m_tf_{key}", lambda s, sf, f=f: survey_samples(s, sf).groupBy("u", "v").agg(F.expr(f).alias("val")), f"{HIT30} select u, v, {sql} as val from hit group by u, v")


for key, t, f, sql in (("min", "min", "min(val)", "min(value)::bigint"), ("sum", "sum", "sum(val)", "sum(value)::bigint"), ("avg", "sum", "sum(val) div sum(samples)", "(sum(value) // count(*))::bigint")):
    add(f"m_tf_{key}_array", lambda s, sf, t=t, f=f: array_engine.cast(survey_blocks(s, sf), SURVEY, [A30], transfer=t).groupBy("u", "v").agg(F.expr(f).alias("val")), f"{HIT30} select u, v, {sql} as val from hit group by u, v")


def shaded(s, sf, n=8, keep=("u", "v")):
    return render.table_values(survey_samples(s, sf, n=n, keep=keep), 0, 70_000_000)


add(
    "m_tf_tab",
    lambda s, sf: shaded(s, sf).groupBy("u", "v").agg(F.round(F.max("c"), 6).alias("c"), F.round(F.max("a"), 6).alias("a")),
    f"{HIT30} select u, v, round(max(least(15, value * 16 // 70000000)) / 15e0, 6) as c, round(max(least(15, value * 16 // 70000000) * least(15, value * 16 // 70000000)) / 900e0, 6) as a from hit group by u, v",
)
ALPHA_SQL = f"""{HIT30}, smp as (select u, v, list(struct_pack(t := te, c := b / 15e0, a := b * b / 900e0) order by te) as l from (select *, least(15, value * 16 // 70000000) as b from hit) group by u, v)
select u, v, round(r.c, 6) as c, round(r.a, 6) as a from (select u, v, list_reduce(list_prepend(struct_pack(t := 0e0, c := 0e0, a := 0e0), l), lambda p, x: struct_pack(t := 0e0, c := p.c + (1e0 - p.a) * x.a * x.c, a := p.a + (1e0 - p.a) * x.a)) as r from smp)"""
add("m_tf_a", lambda s, sf: render.alpha(shaded(s, sf)).select("u", "v", F.round("c", 6).alias("c"), F.round("a", 6).alias("a")), ALPHA_SQL)
add(
    "m_tf_a_array",
    lambda s, sf: render.merge_alpha(array_engine.cast(survey_blocks(s, sf), SURVEY, [A30], transfer="alpha", table=(0, 70_000_000))).select("u", "v", F.round("c", 6).alias("c"), F.round("a", 6).alias("a")),
    ALPHA_SQL,
)
add(
    "m_cmp_ord",
    lambda s, sf: render.merge_alpha(render.alpha(shaded(s, sf, keep=("brick", "u", "v")), ("brick", "u", "v"))).select("u", "v", F.round("c", 6).alias("c"), F.round("a", 6).alias("a")),
    ALPHA_SQL,
)


@query("m_end_op", f"{HIT30} select count(*) as pixels, true as within from (select distinct u, v from hit)")
def _(s, sf):
    """Opacity termination: error against the full blend stays under what was left."""
    full = render.alpha(shaded(s, sf)).select("u", "v", F.col("c").alias("full"))
    cut = render.alpha(shaded(s, sf), limit=0.999).select("u", "v", "c")
    return full.join(cut, ["u", "v"]).agg(F.count("*").alias("pixels"), (F.max(F.abs(F.col("full") - F.col("c"))) <= 1e-3).alias("within"))


add(
    "m_tf_n",
    lambda s, sf: (lambda v: v.crossJoin(F.broadcast(v.agg((F.avg("v") + 3 * F.stddev_pop("v")).alias("cut")))).where("v > cut").select("x", "y", "z", "v"))(cube.survey(s, sf)),
    f"with {S.SURVEY} select x, y, z, v from vox, (select avg(v) + 3 * stddev_pop(v) as cut from vox) where v > cut",
)
TRILINEAR = f"""with {S.kd_tree(SURVEY.dims, 1)}, {S.SURVEY}, {S.frame_pixels(A30, 'survey')}, {S.box_hits(A30)},
nn as (select px.*, te, tx, {UNIT.format(dx=S.d(-A30.sin), dz=S.d(A30.cos))} as n from ray join px on px.u = ray.u and px.v = ray.v),
smp as (select u, v, t, ox + t * {S.d(-A30.sin)} - 5e-1 as qx, oy - 5e-1 as qy, oz + t * {S.d(A30.cos)} - 5e-1 as qz from (select *, {EVEN} as t from nn) q),
e as (select u, v, t, i, qx - floor(qx) as fx, qy - floor(qy) as fy, qz - floor(qz) as fz, greatest(0, least(39, floor(qx) + (i & 1)))::bigint as x, greatest(0, least(39, floor(qy) + (i >> 1 & 1)))::bigint as y, greatest(0, least(17, floor(qz) + (i >> 2 & 1)))::bigint as z
      from smp, (select unnest(range(8)) as i)),
w as (select e.u, e.v, t, fx, fy, fz, {', '.join(f'coalesce(max(case when i = {i} then vox.v end), 0)::double as c{i}' for i in range(8))} from e left join vox on vox.x = e.x and vox.y = e.y and vox.z = e.z group by all)
select u, v, round(max((1 - fz) * ((1 - fy) * ((1 - fx) * c0 + fx * c1) + fy * ((1 - fx) * c2 + fx * c3)) + fz * ((1 - fy) * ((1 - fx) * c4 + fx * c5) + fy * ((1 - fx) * c6 + fx * c7))), 3) as val from w group by u, v"""
add(
    "m_int_t",
    lambda s, sf: render.trilinear(render.uniform_mids(render.brick_rays(SURVEY, A30, kd.kd(SURVEY.dims, 1), s), "unit"), cube.survey(s, sf), SURVEY).groupBy("u", "v").agg(F.round(F.max("value"), 3).alias("val")),
    TRILINEAR,
)
add(
    "m_int_t_array",
    lambda s, sf: array_engine.cast(survey_blocks(s, sf, ghost=1, block=16), SURVEY, [A30], mode="uniform", rule="unit", interpolate=True).groupBy("u", "v").agg(F.round(F.max("val"), 3).alias("val")),
    TRILINEAR,
)
add("m_int_n", lambda s, sf: survey_samples(s, sf, A60).groupBy("u", "v").agg(F.count("*").alias("n"), F.sum("value").alias("total")), f"with {S.hit_cte(A60, 'survey')} select u, v, count(*) as n, sum(value)::bigint as total from hit group by u, v")

# Composition


def partials(s, sf, v=A30, gpus=(2, 2, 2, 2)):
    plan = kd.two_level(SURVEY.dims, list(gpus))
    return array_engine.cast(array_engine.pack_bricks(cube.survey(s, sf), plan), SURVEY, [v])


def two_level_rects(s, v=A30):
    return view.rects(kd.two_level(SURVEY.dims, [2] * 4).frame(s), v, SURVEY)


NODEHIT = f"with {S.kd_tree(SURVEY.dims, 8)}, {S.hit_cte(A30, 'survey')}, nh as (select hit.*, brick // 2 as node, brick from hit join leaf on hit.x >= x0 and hit.x < x1 and hit.y >= y0 and hit.y < y1 and hit.z >= z0 and hit.z < z1)"
add("m_cmp_1", lambda s, sf: composite.node(partials(s, sf)), f"{NODEHIT} select node, u, v, max(value)::bigint as val from nh group by 1, 2, 3")
add("m_cmp_2", lambda s, sf: composite.final(composite.node(partials(s, sf))), S.mip(A30, "survey"))
add("m_cmp_any", lambda s, sf: composite.final(partials(s, sf).orderBy(F.rand(3))), S.mip(A30, "survey"))
add(
    "m_cmp_clip",
    lambda s, sf: composite.pack(composite.node(partials(s, sf)), view.node_rects(two_level_rects(s)), True).select("node", "u0", "u1", "v0", "v1", F.length("data").cast("long").alias("bytes")),
    f"with {S.kd_tree(SURVEY.dims, 8)}, {S.rects(A30, 'survey', node='brick // 2')} select node, min(u0) as u0, max(u1) as u1, min(v0) as v0, max(v1) as v1, 4 * (max(u1) - min(u0))::bigint * (max(v1) - min(v0)) as bytes from rect group by node",
)
add("m_cmp_fill", lambda s, sf: composite.fill(composite.final(partials(s, sf)), A30), f"with {S.hit_cte(A30, 'survey')} select px.u, px.v, coalesce(max(value), 0)::bigint as val from px left join hit on hit.u = px.u and hit.v = px.v group by 1, 2")
add("m_direct", lambda s, sf: composite.final(composite.unpack(composite.pack(composite.node(partials(s, sf)), view.node_rects(two_level_rects(s)), True))), S.mip(A30, "survey"))
for f in (2, 4):
    add(f"m_multi_{f}", lambda s, sf, f=f: composite.tree(composite.node(partials(s, sf)), 4, f), S.mip(A30, "survey"))
add("m_dedic", lambda s, sf: composite.tiles(composite.node(partials(s, sf)), A30), S.mip(A30, "survey"))
for kind in ("rle", "sparse", "zlib"):
    add(
        f"m_compr_{kind}",
        lambda s, sf, kind=kind: composite.final(composite.unpack(composite.decoded(composite.encoded(composite.pack(composite.node(partials(s, sf)), view.node_rects(two_level_rects(s)), True), kind), kind))),
        S.mip(A30, "survey"),
    )
FILLED = f"with {S.hit_cte(A30, 'survey')}, fl as (select px.u, px.v, coalesce(max(value), 0)::bigint as val from px left join hit on hit.u = px.u and hit.v = px.v group by 1, 2)"
add(
    "m_compr_runs",
    lambda s, sf: composite.runs(composite.fill(composite.final(partials(s, sf)), A30)),
    f"{FILLED} select v, min(u) as start, count(*) as length, val from (select *, sum(chg) over (partition by v order by u) as g from (select *, case when val = lag(val) over (partition by v order by u) then 0 else 1 end as chg from fl)) group by v, g, val",
)
COLOR_SQL = """{frame}, lim as (select min(v) as lo, max(v) as hi from vox), b as (select fr.*, {bucket} as bucket from fr, lim)
select u, v, val, bucket, (255 * bucket // 15)::int as r, (160 * bucket // 15)::int as g, 0 as b from b"""
FR = f"with {S.hit_cte(A30, 'survey')}, fr as (select u, v, max(value)::bigint as val from hit group by u, v)"


def limits(s, sf):
    return cube.survey(s, sf).agg(F.min("v").alias("lo"), F.max("v").alias("hi"))


for stretch, b in (
    ("linear", "greatest(0, least(15, (val - lo) * 16 // (hi - lo)))::int"),
    ("sqrt", "greatest(0, least(15, floor(round(sqrt((val - lo)::double) * 16 / sqrt((hi - lo)::double), 9))))::int"),
    ("log", "greatest(0, least(15, floor(round(ln((val - lo)::double + 1) * 16 / ln((hi - lo)::double + 1), 9))))::int"),
):
    add("m_color" if stretch == "linear" else f"m_color_v_{stretch}", lambda s, sf, k=stretch: color.apply(composite.final(partials(s, sf)), limits(s, sf), "heat", 16, k), COLOR_SQL.format(frame=FR, bucket=b))

add(
    "m_color_v_percentile",
    lambda s, sf: color.apply_ranks(composite.final(partials(s, sf))),
    f"""{FR}, e as (select quantile_cont(val::double, [{', '.join(f'{i / 16}' for i in range(1, 16))}]) as edges from fr), b as (select fr.*, len(list_filter(edges, lambda x: x <= val))::int as bucket from fr, e)
select u, v, val, bucket, (255 * bucket // 15)::int as r, (160 * bucket // 15)::int as g, 0 as b from b""",
)
MESSAGE = f"""{NODEHIT}, {S.rects(A30, 'survey', node='brick // 2')}, nr as (select node, min(u0) as u0, max(u1) as u1, min(v0) as v0, max(v1) as v1 from rect group by node),
ni as (select node, u, v, max(value)::bigint as val from nh group by 1, 2, 3),
cell as (select nr.node, u, v, row_number() over (partition by nr.node order by u, v) as i from nr, (select unnest(range(64)) as u), (select unnest(range(64)) as v) where u >= u0 and u < u1 and v >= v0 and v < v1),
buf as (select cell.node, i, ni.val from cell left join ni on ni.node = cell.node and ni.u = cell.u and ni.v = cell.v)"""


def messages(s, sf):
    return composite.pack(composite.node(partials(s, sf)), view.node_rects(two_level_rects(s)), True)


add(
    "m_compr_bytes",
    lambda s, sf: composite.encoding_cost(messages(s, sf), ("rle", "sparse"), 1).select("node", "kind", "raw", "bytes"),
    f"""{MESSAGE} select node, 'sparse' as kind, 4 * count(*) as raw, 4 + 8 * count(val) as bytes from buf group by node
union all select node, 'rle', 4 * count(*), 4 + 8 * count(*) filter (i = 1 or val is distinct from before) from (select *, lag(val) over (partition by node order by i) as before from buf) group by node""",
)
add("m_compr_cost", lambda s, sf: composite.encoding_cost(messages(s, sf)))

# Baselines

add(
    "b_full",
    lambda s, sf: composite.message_bytes(view.node_rects(view.rects(partition.held(cube.survey(s, sf), kd.two_level(SURVEY.dims, [2] * 4)), A30, SURVEY)), A30, "full"),
    f"with {S.held(SURVEY.dims, 8, 'survey')}, {S.rects(A30, 'survey', boxes='box', node='brick // 2')} select count(distinct node) as nodes, count(distinct node) * 4 * 64 * 64 as bytes from rect",
)
add("b_1stage", lambda s, sf: baseline.one_stage(partials(s, sf)), S.mip(A30, "survey"))
add("b_norect", lambda s, sf: render.frame(cube.survey(s, sf), SURVEY, A30, rectangles=False), S.mip(A30, "survey"))
add("b_mr", lambda s, sf: baseline.map_reduce(cube.survey(s, sf), SURVEY, A30, kd.kd(SURVEY.dims, 8)), S.mip(A30, "survey"))
add("b_prev", lambda s, sf: baseline.previous(cube.survey(s, sf), SURVEY, A30), uniform_sql(A30, "1", FIXED))
add(
    "b_near",
    lambda s, sf: measure.image_error(
        array_engine.cast(survey_blocks(s, sf, ghost=1), SURVEY, [A30], mode="uniform", rule="unit", interpolate=True).groupBy("u", "v").agg(F.round(F.max("val"), 3).alias("val")),
        composite.final(array_engine.cast(survey_blocks(s, sf), SURVEY, [A30], mode="uniform", rule="unit")),
    ).select("differ", F.round("mae", 2).alias("mae"), F.round("maxabs", 2).alias("maxabs")),
    f"""with a as ({TRILINEAR}), b as ({uniform_sql(A30, UNIT, EVEN)}), j as (select coalesce(a.val, 0) as a, coalesce(b.val, 0) as b from a full join b on a.u = b.u and a.v = b.v)
select count(*) filter (a <> b) as differ, round(avg(abs(a - b)), 2) as mae, round(max(abs(a - b)), 2) as maxabs from j""",
)
add(
    "b_2d",
    lambda s, sf: baseline.slices(cube.survey(s, sf), "z", 0, 70_000_000),
    f"with {S.SURVEY} select z as k, x as u, y as w, least(7, v * 8 // 70000000)::int as bucket from vox",
)
add(
    "b_iso",
    lambda s, sf: baseline.iso(cube.survey(s, sf), SURVEY, A30, 30_000_000, kd.kd(SURVEY.dims, 8)).drop("t"),
    f"{HIT30} select u, v, min_by(value, te)::bigint as val from hit where value >= 30000000 group by u, v",
)
for agg, sql in (("mean", "sum(v) // 64"), ("max", "max(v)")):
    add(f"b_mres_{agg}", lambda s, sf, agg=agg: baseline.pyramid(cube.survey(s, sf), 2, agg), f"with {S.SURVEY} select x // 4 as x, y // 4 as y, z // 4 as z, ({sql})::bigint as v from vox group by 1, 2, 3")
for level in (1, 2, 3):
    f = 2**level
    add(
        f"b_mres_error_{level}",
        lambda s, sf, level=level: baseline.pyramid_error(cube.survey(s, sf), level),
        f"""with {S.SURVEY}, c as (select x // {f} as x, y // {f} as y, z // {f} as z, sum(v) // {f**3} as v from vox group by 1, 2, 3), mm as (select x, y, max(v) as coarse from c group by x, y), g as (select x // {f} as x, y // {f} as y, max(v) as fine from vox group by 1, 2)
select count(*) as pixels, count(*) filter (coarse * 2 < fine) as faded, round(avg(fine - coarse), 4) as mae, max(fine - coarse)::bigint as maxabs from g join mm on g.x = mm.x and g.y = mm.y""",
    )
add(
    "b_splat",
    lambda s, sf: baseline.splat(cube.survey(s, sf), SURVEY, A30),
    (lambda m: f"""with {S.SURVEY}, p as (select v, {S.d(m[0])} * x + {S.d(m[1])} * y + {S.d(m[2])} * z + {S.d(m[3])} as u0, {S.d(m[5])} * y + {S.d(m[7])} as v0 from vox),
b as (select v as val, least(u0, u0 + {S.d(m[0])}) + least(0e0, {S.d(m[2])}) as ul, greatest(u0, u0 + {S.d(m[0])}) + greatest(0e0, {S.d(m[2])}) as uh, v0 as vl, v0 + {S.d(m[5])} as vh from p)
select u, v, max(val)::bigint as val from (select unnest(range(64))::int as u), (select unnest(range(64))::int as v), b where u + 5e-1 >= ul and u + 5e-1 < uh and v + 5e-1 >= vl and v + 5e-1 < vh group by u, v""")(A30.matrix(SURVEY)),
)
add(
    "b_shear",
    lambda s, sf: baseline.shear(cube.survey(s, sf), SURVEY, A30),
    f"with {S.SURVEY} select x + floor((z + 5e-1) * {S.d(A30.sin / A30.cos)} + 5e-1)::bigint as a, y, max(v)::bigint as val from vox group by 1, 2",
)
SHEAR30 = f"sh as (select x + floor((z + 5e-1) * {S.d(A30.sin / A30.cos)} + 5e-1)::bigint as a, y, max(v)::bigint as val from vox group by 1, 2)"
K30 = A30.scale(SURVEY)
WARP30 = f"""with {S.SURVEY}, {SHEAR30}, pix as (select u, v, floor(((u + 5e-1 - 32e0) / {S.d(K30)} + {S.d(20.0 * A30.cos + 9.0 * A30.sin)}) / {S.d(A30.cos)})::bigint as a, floor(20e0 + (v + 5e-1 - 32e0) / {S.d(K30)})::bigint as y
from (select unnest(range(64))::int as u), (select unnest(range(64))::int as v)) select u, v, val from pix join sh on sh.a = pix.a and sh.y = pix.y"""
add("b_shear_warp", lambda s, sf: baseline.shear_warp(cube.survey(s, sf), SURVEY, A30), WARP30)
add(
    "b_shear_error",
    lambda s, sf: measure.image_error(render.frame(cube.survey(s, sf), SURVEY, A30), baseline.shear_warp(cube.survey(s, sf), SURVEY, A30)).select("differ", "mae", "maxabs"),
    f"with a as ({S.mip(A30, 'survey')}), b as ({WARP30}), j as (select coalesce(a.val, 0) as a, coalesce(b.val, 0) as b from a full join b on a.u = b.u and a.v = b.v) select count(*) filter (a <> b) as differ, round(avg(abs(a - b)), 4) as mae, max(abs(a - b))::bigint as maxabs from j",
)
