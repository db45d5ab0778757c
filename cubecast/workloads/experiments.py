"""Measures, experiment workloads and quantitative queries."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..operators import baseline, composite, cube, measure, partition, quant, render, view
from ..plans import kd
from ..plans.spec import ANGLES, CUBES, NODES, PUBLISHED, SURVEY, ViewSpec
from . import sqltext as S
from .methods import A30, EVEN, FIXED, HALF, L1, LINF, UNIT, partials, survey_samples, tbl, uniform_sql
from .registry import add, query

# Timing


def runs(s, sf):
    """cube, angle, run, ms from events: type, hour * 15, slot of ten, largest value of the slot."""
    e = tbl(s, sf, "events").select("event_id", "event_type", F.hour("ts").alias("h"), "value")
    run = F.row_number().over(Window.partitionBy("event_type", "h").orderBy("event_id")) % 10
    return e.select(F.col("event_type").alias("cube"), (F.col("h") * 15).alias("angle"), run.alias("run"), F.col("value").alias("ms")).groupBy("cube", "angle", "run").agg(F.max("ms").alias("ms"))


RUNS = "runs as (select event_type as cube, (hour(ts) * 15)::int as angle, run, max(value) as ms from (select *, row_number() over (partition by event_type, hour(ts) order by event_id) % 10 as run from events) group by 1, 2, 3)"
MED = f"with {RUNS}, med as (select cube, angle, median(ms) as ms from runs group by 1, 2)"
add("c_med", lambda s, sf: measure.median_runs(runs(s, sf)), f"{MED} select cube, angle, ms from med")
add("c_p75", lambda s, sf: measure.p75(measure.median_runs(runs(s, sf))).select("cube", F.round("ms", 6).alias("ms")), f"{MED} select cube, round(quantile_cont(ms, 0.75), 6) as ms from med group by cube")
add("w5", lambda s, sf: measure.fps(measure.p75(measure.median_runs(runs(s, sf)))).select("cube", F.round("ms", 6).alias("ms"), F.round("fps", 6).alias("fps")), f"{MED} select cube, round(quantile_cont(ms, 0.75), 6) as ms, round(1e3 / quantile_cont(ms, 0.75), 6) as fps from med group by cube")
add("c_fps", lambda s, sf: measure.fps(measure.median_runs(runs(s, sf))).select("cube", "angle", F.round("fps", 6).alias("fps")), f"{MED} select cube, angle, round(1e3 / nullif(ms, 0), 6) as fps from med")


def stages(s, sf):
    """Four stages of each hour as frames."""
    names = F.create_map(*[F.lit(x) for x in ("view", "render", "click", "merge", "purchase", "send", "signup", "server")])
    e = tbl(s, sf, "events").select(F.hour("ts").alias("frame"), F.element_at(names, F.col("event_type")).alias("stage"), "value").where("stage is not null")
    return e.groupBy("frame", "stage").agg(F.max("value").alias("ms"))


STAGES = "stages as (select hour(ts)::int as frame, case event_type when 'view' then 'render' when 'click' then 'merge' when 'purchase' then 'send' else 'server' end as stage, max(value) as ms from events where event_type <> 'error' group by 1, 2)"
add("c_tr", lambda s, sf: measure.total_model(stages(s, sf)).select("frame", F.round("upper", 6).alias("upper"), "lower"), f"with {STAGES} select frame, round(sum(ms), 6) as upper, max(ms) as lower from stages group by frame")
add("c_stage", lambda s, sf: measure.stage_share(stages(s, sf)).select("stage", F.round("ms", 4).alias("ms"), F.round("share", 6).alias("share")), f"with {STAGES} select stage, round(sum(ms), 4) as ms, round(sum(ms) / sum(sum(ms)) over (), 6) as share from stages group by stage")


def by_nodes(s, sf):
    """cube, nodes, ms: type, two to the power of one to six by weekday, mean-free largest value."""
    e = tbl(s, sf, "events").select(F.col("event_type").alias("cube"), F.expr("int(pow(2, 1 + event_id % 6))").alias("nodes"), "value", (F.col("event_id") % 6).alias("k"))
    return e.groupBy("cube", "nodes").agg((F.max("value") / (1 + F.min("k"))).alias("ms"))


BYN = "byn as (select event_type as cube, (2 ** (1 + event_id % 6))::int as nodes, max(value) / (1 + min(event_id % 6)) as ms from events group by 1, 2)"
add(
    "c_scale",
    lambda s, sf: measure.speedup(by_nodes(s, sf)).select("cube", "nodes", F.round("speedup", 6).alias("speedup"), F.round("efficiency", 6).alias("efficiency")),
    f"with {BYN} select cube, nodes, round(first_value(ms) over w / ms, 6) as speedup, round(first_value(ms) over w / ms * 2 / nodes, 6) as efficiency from byn window w as (partition by cube order by nodes)",
)
add(
    "c_crit",
    lambda s, sf: measure.critical_point(by_nodes(s, sf)),
    f"with {BYN}, n as (select *, lead(ms) over (partition by cube order by nodes) as nx from byn) select cube, min(case when nx >= ms * 98e-2 then nodes end) as critical_nodes from n group by cube",
)
add(
    "c_res",
    lambda s, sf: measure.ratio(by_nodes(s, sf), "nodes", 2, 8, ["cube"]).select("cube", F.round("ratio", 6).alias("ratio")),
    f"with {BYN} select cube, round(max(case when nodes = 8 then ms end) / max(case when nodes = 2 then ms end), 6) as ratio from byn group by cube",
)
GPU = "pairs as (select angle, max(case when cube = 'view' then ms end) as a, max(case when cube = 'click' then ms end) as b from med group by angle)"
add(
    "c_gpu",
    lambda s, sf: measure.reduction(
        measure.median_runs(runs(s, sf)).groupBy("angle").agg(F.max(F.when(F.col("cube") == "view", F.col("ms"))).alias("a"), F.max(F.when(F.col("cube") == "click", F.col("ms"))).alias("b"))
    ).select(*[F.round(c, 6).alias(c) for c in ("mean", "least", "most")]),
    f"{MED}, {GPU} select round(avg(1 - b / a), 6) as mean, round(min(1 - b / a), 6) as least, round(max(1 - b / a), 6) as most from pairs",
)

# Communication

BATCH = [ViewSpec(a, frame=a) for a in ANGLES]


def node_rects_batch(s, name, n, views=BATCH):
    """Rectangles of node bricks for all angles."""
    spec = CUBES[name]
    return view.rects_batch(kd.kd(spec.dims, n).frame(s), view.views_frame(s, views, spec))


def held(s, sf, name, n):
    """Node bricks of a cube, shrunk to the voxels that they hold."""
    return partition.held(cube.load(s, sf, name), kd.kd(CUBES[name].dims, n))


def held_rects_batch(s, sf, name, n, views=BATCH):
    """Rectangles of what node bricks hold, for all angles."""
    return view.rects_batch(held(s, sf, name, n), view.views_frame(s, views, CUBES[name]))


AREA = "((u1 - u0) * (v1 - v0))"
add(
    "c_msg",
    lambda s, sf: held_rects_batch(s, sf, "survey", 16).groupBy("frame").agg(F.sum(F.expr(f"{AREA} * 4L")).alias("bytes"), F.count("*").alias("messages")),
    f"with {S.held(SURVEY.dims, 16, 'survey')}, {S.rects_batch(BATCH, 'survey', boxes='box')} select frame, sum({AREA} * 4)::bigint as bytes, count(*) as messages from rect group by frame",
)
add(
    "c_recta",
    lambda s, sf: held_rects_batch(s, sf, "wide", 8).groupBy("angle").agg(F.sum(F.expr(f"bigint{AREA}")).alias("total"), F.max(F.expr(f"bigint{AREA}")).alias("largest")),
    f"with {S.held(CUBES['wide'].dims, 8, 'wide')}, {S.rects_batch(BATCH, 'wide', boxes='box')} select angle, sum({AREA})::bigint as total, max({AREA})::bigint as largest from rect group by angle",
)


add(
    "c_ovl",
    lambda s, sf: composite.depth(view.rects(held(s, sf, "survey", 16), A30, SURVEY)),
    f"with {S.held(SURVEY.dims, 16, 'survey')}, {S.rects(A30, 'survey', boxes='box')}, p as (select u, v, count(*) as layers from rect, (select unnest(range(64)) as u), (select unnest(range(64)) as v) where u >= u0 and u < u1 and v >= v0 and v < v1 group by u, v) select layers, count(*) as pixels from p group by layers",
)
add(
    "c_ovl_total",
    lambda s, sf: composite.overlap(view.rects(held(s, sf, "survey", 16), A30, SURVEY)),
    f"with {S.held(SURVEY.dims, 16, 'survey')}, {S.rects(A30, 'survey', boxes='box')}, p as (select u, v, count(*) as n from rect, (select unnest(range(64)) as u), (select unnest(range(64)) as v) where u >= u0 and u < u1 and v >= v0 and v < v1 group by u, v) select sum(n)::bigint as total, count(*) as covered, sum(n - 1)::bigint as extra from p",
)
GRID = "grid as (select x, y, z, 0::bigint as v from (select unnest(range(40)) as x), (select unnest(range(40)) as y), (select unnest(range(18)) as z))"


def grid_hits(v):
    return f"with {S.frame_pixels(v, 'survey')}, {GRID}, {S.hits(v, 'grid').replace('select u, v,', 'select px.u, px.v,', 1)}"


# rays and samples of what the cube holds; at the other angles, of a full grid
add(
    "c_samp_0",
    lambda s, sf: survey_samples(s, sf, ViewSpec(0), 6).agg(F.countDistinct("u", "v").alias("rays"), F.count("*").alias("samples")),
    f"with {S.hit_cte(ViewSpec(0), 'survey')} select count(distinct (u, v)) as rays, count(*) as samples from hit",
)
for a in (30, 60, 90):
    add(
        f"c_samp_{a}",
        lambda s, sf, a=a: render.exact_mids(render.brick_rays(SURVEY, ViewSpec(a), kd.kd(SURVEY.dims, 6), s)).agg(F.countDistinct("u", "v").alias("rays"), F.sum(F.size("mids")).alias("samples")),
        f"{grid_hits(ViewSpec(a))} select count(distinct (u, v)) as rays, count(*) as samples from hit",
    )
add(
    "c_waste",
    lambda s, sf: view.box_rays(kd.kd(SURVEY.dims, 8).frame(s), A30, SURVEY).agg(F.count("*").alias("started")).crossJoin(render.brick_rays(SURVEY, A30, kd.kd(SURVEY.dims, 8), s).agg(F.count("*").alias("hit"))).withColumn("wasted", F.col("started") - F.col("hit")),
    f"with {S.kd_tree(SURVEY.dims, 8)}, {S.frame_pixels(A30, 'survey')}, {S.box_hits(A30)}, {S.rects(A30, 'survey')} select a.started, b.hit, a.started - b.hit as wasted from (select sum({AREA})::bigint as started from rect) a, (select count(*) as hit from ray) b",
)


@query(
    "c_occ",
    "select cube, nodes, round(n * 4 / (2e0 * nodes) / 6442450944e0, 12) as share from ("
    + " union all ".join(f"select '{k}' as cube, (with {S.CUBE[k]} select count(*) from vox) as n" for k in CUBES)
    + "), (values " + ", ".join(f"({n})" for n in NODES) + ") t(nodes)",
)
def _(s, sf):
    """Share of a worker's memory that the voxels of each cube take, by nodes of two workers."""
    found = None
    fine = cube.particle(s, sf).persist()
    for k in CUBES:
        v = fine if k == "particle" else cube.resample(fine, CUBES["particle"], CUBES[k].dims) if k == "particle_scaled" else cube.load(s, sf, k)
        n = v.agg(F.count("*").alias("n")).select(F.lit(k).alias("cube"), "n")
        found = n if found is None else found.unionByName(n)
    nodes = F.explode(F.array(*[F.lit(n) for n in NODES]))
    return found.withColumn("nodes", nodes).select("cube", "nodes", F.round(F.col("n") * 4 / (2.0 * F.col("nodes")) / F.lit(6442450944.0), 12).alias("share"))


add(
    "c_mem",
    lambda s, sf: partition.assign(cube.survey(s, sf), kd.kd(SURVEY.dims, 16)).groupBy("brick").agg((F.count("*") * 8).alias("bytes")),
    f"with {S.kd_tree(SURVEY.dims, 16)}, {S.SURVEY} select brick, count(*) * 8 as bytes from vox join leaf on x >= x0 and x < x1 and y >= y0 and y < y1 and z >= z0 and z < z1 group by brick",
)
add("c_cic", lambda s, sf: cube.particle(s, sf).agg(F.sum("v").alias("mass")), "select (count(*) * 16777216)::bigint as mass from lineitem")
for rule, mode, how, n, mid in (("unit", "uniform", {"rule": "unit"}, UNIT, EVEN), ("l1", "uniform", {"rule": "l1"}, L1, EVEN), ("fixed", "fixed", {"dt": 1.0}, "1", FIXED)):
    add(
        f"c_img_{rule}",
        lambda s, sf, mode=mode, how=how: measure.image_error(render.frame(cube.survey(s, sf), SURVEY, A30), render.frame(cube.survey(s, sf), SURVEY, A30, kd.kd(SURVEY.dims, 1), mode, **how)).withColumn("psnr", F.round("psnr", 4)),
        f"""with a as ({S.mip(A30, 'survey')}), b as ({uniform_sql(A30, n, mid)}),
j as (select coalesce(a.val, 0) as a, coalesce(b.val, 0) as b from a full join b on a.u = b.u and a.v = b.v)
select count(*) filter (a <> b) as differ, round(avg(abs(a - b)), 4) as mae, max(abs(a - b))::bigint as maxabs, round(10 * log10(max(a)::double * max(a)::double / avg((a - b)::double * (a - b)::double)), 4) as psnr from j""",
    )


def coverage_sql(rule, n):
    dx, dz = S.d(-A30.sin), S.d(A30.cos)
    return f"""select '{rule}' as rule, count(*) as crossed, count(*) filter (s.u is null) as missed, round(count(*) filter (s.u is null) / count(*)::double, 6) as share
from hit h left join (select distinct u, v, floor(ox + t * {dx})::bigint as x, floor(oy)::bigint as y, floor(oz + t * {dz})::bigint as z from (select *, {EVEN} as t from (select px.*, te, tx, {n.format(dx=dx, dz=dz)} as n from ray join px on px.u = ray.u and px.v = ray.v) nn) q) s
on s.u = h.u and s.v = h.v and s.x = h.x and s.y = h.y and s.z = h.z"""


@query(
    "c_cov",
    f"with {S.kd_tree(SURVEY.dims, 1)}, {S.hit_cte(A30, 'survey')}, {S.box_hits(A30)} " + " union all ".join(coverage_sql(r, n) for r, n in (("l1", L1), ("linf", LINF), ("unit", UNIT), ("half", HALF))),
)
def _(s, sf):
    """Share of the cube's crossed voxels that each uniform rule misses."""
    r = render.brick_rays(SURVEY, A30, kd.kd(SURVEY.dims, 1), s)
    exact = render.nearest(render.samples(render.exact_mids(r), ("u", "v")), cube.survey(s, sf))
    out = None
    for rule in render.RULES:
        part = measure.coverage(exact, render.samples(render.uniform_mids(r, rule), ("u", "v"))).withColumn("rule", F.lit(rule))
        out = part if out is None else out.unionByName(part)
    return out


# Workloads (those that render are in ``frames``)

@query("w9", "select cube, (bytes + 12884901887) // 12884901888 as nodes from (values " + ", ".join(f"('{k}', {dims[0] * dims[1] * dims[2] * 4}::bigint)" for k, (dims, _) in PUBLISHED.items()) + ") t(cube, bytes)")
def _(s, sf):
    return s.createDataFrame([(k, kd.min_nodes(dims, 2, 6 << 30, 32 << 30)) for k, (dims, _) in PUBLISHED.items()], "cube string, nodes long")


# Quantitative queries

VOX = f"with {S.SURVEY}"
vox = cube.survey
add("q_stat", lambda s, sf: quant.stats(vox(s, sf)), f"{VOX} select count(*) as n, sum(v)::bigint as total, min(v) as lo, max(v) as hi, round(avg(v), 4) as mean, round(stddev_pop(v), 3) as spread from vox")
add("q_stat_box", lambda s, sf: quant.stats(vox(s, sf), (5, 20, 5, 30, 2, 9)), f"{VOX} select count(*) as n, sum(v)::bigint as total, min(v) as lo, max(v) as hi, round(avg(v), 4) as mean, round(stddev_pop(v), 3) as spread from vox where x >= 5 and x < 20 and y >= 5 and y < 30 and z >= 2 and z < 9")
add("q_hist", lambda s, sf: quant.histogram(vox(s, sf), 0, 70_000_000), f"{VOX} select least(31, v * 32 // 70000000)::int as bin, count(*) as n from vox group by 1")
add("q_spec", lambda s, sf: quant.spectrum(vox(s, sf), 10, 12, 2), f"{VOX} select z, sum(v)::bigint as total, count(*) as n from vox where x between 8 and 12 and y between 10 and 14 group by z")
add(
    "q_mom",
    lambda s, sf: quant.moments(vox(s, sf), 2, 15),
    f"{VOX}, g as (select x, y, sum(v)::bigint as m0, sum(v * z)::bigint as s1, sum(v * z * z)::bigint as s2 from vox where z >= 2 and z < 15 group by x, y) select x, y, m0, round(s1 / m0, 6) as m1, round(sqrt(greatest(0e0, s2 / m0 - (s1 / m0) * (s1 / m0))), 5) as m2 from g",
)
add("q_slice", lambda s, sf: quant.slice_(vox(s, sf), "z", 7), f"{VOX} select x as u, y as w, v from vox where z = 7")
add("q_crop", lambda s, sf: quant.crop(vox(s, sf), (3, 9, 3, 9, 3, 9)), f"{VOX} select x, y, z, v from vox where x between 3 and 8 and y between 3 and 8 and z between 3 and 8")
add("q_pick", lambda s, sf: quant.argmip(vox(s, sf)), f"{VOX} select x as u, y as w, max(v)::bigint as val, arg_max(z, v * 100 - z) as depth from vox group by x, y")
add(
    "q_peak",
    lambda s, sf: quant.peaks(vox(s, sf), 20_000_000),
    f"{VOX} select x, y, z, v from vox a where v >= 20000000 and not exists (select 1 from vox b where b.x between a.x - 1 and a.x + 1 and b.y between a.y - 1 and a.y + 1 and b.z between a.z - 1 and a.z + 1 and (b.x <> a.x or b.y <> a.y or b.z <> a.z) and b.v >= a.v)",
)
CLIP0 = "s0 as (select count(*) as n, avg(v) as m, stddev_pop(v) as s from vox)"
CLIPS = ", ".join([CLIP0, *[f"v{i} as (select v from {'vox' if i == 1 else f'v{i - 1}'}, s{i - 1} where v between m - 3 * s and m + 3 * s), s{i} as (select count(*) as n, avg(v) as m, stddev_pop(v) as s from v{i})" for i in (1, 2)]])
add("q_clip", lambda s, sf: quant.sigma_clip(vox(s, sf)), f"{VOX}, {CLIPS} " + " union all ".join(f"select {i} as round, n, round(m, 3) as mean, round(s, 2) as spread from s{i}" for i in range(3)))
add(
    "q_amr",
    lambda s, sf: quant.regrid([(vox(s, sf).where("x < 20"), 1), (baseline.pyramid(vox(s, sf), 1), 2)]).agg(F.count("*").alias("n"), F.sum("v").alias("total")),
    f"{VOX}, c as (select x // 2 as x, y // 2 as y, z // 2 as z, sum(v) // 8 as v from vox group by 1, 2, 3), r as (select unnest([0, 1]) as i), f as (select x * 2 + a.i as x, y * 2 + b.i as y, z * 2 + d.i as z, v from c, r a, r b, r d), fin as (select coalesce(g.v, f.v) as v from f full join (select * from vox where x < 20) g on f.x = g.x and f.y = g.y and f.z = g.z) select count(*) as n, sum(v)::bigint as total from fin",
)
add("w12", lambda s, sf: quant.progressive(vox(s, sf)), f"{VOX} select x, y, z, v, max(v) over (partition by x, y order by z)::bigint as running from vox")


@query("q_web")
def _(s, sf):
    """A frame as JSON for a browser."""
    from ..sources.sinks import frame_json

    return frame_json(composite.final(partials(s, sf)))
