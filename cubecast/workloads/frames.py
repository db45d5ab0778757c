"""Experiment workloads that render frames: by angle, nodes, size, system, topology and session; measured runs and rival executors."""

from __future__ import annotations

import time

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..operators import array_engine, baseline, composite, cube, measure, partition, render, view
from ..plans import kd, planner
from ..plans.spec import CUBES, NODES, SURVEY, SURVEY_SCALED, ViewSpec, spec_of
from ..sources import store
from ..streaming import serve
from . import sqltext as S
from .experiments import AREA, BATCH, node_rects_batch
from .methods import A30, IN_LEAF, LEAF_FIXED, NODEHIT, partials, scratch, survey_blocks, tbl, topology
from .registry import add, query

LARGEST, WORKERS = "survey_scaled", 64


def blocks_of(s, sf, name, n=WORKERS):
    return array_engine.pack_bricks(cube.load(s, sf, name), kd.kd(CUBES[name].dims, n))


# Time against angle: the largest cube at the largest number of nodes


@query(
    "w1",
    f"""with {S.kd_tree(SURVEY_SCALED.dims, WORKERS)}, {S.CUBE[LARGEST]}, {S.hits_batch(BATCH, LARGEST)}, {S.rects_batch(BATCH, LARGEST)},
rr as (select frame, count(*) as messages, sum({AREA})::bigint as rays, sum({AREA} * 4)::bigint as bytes from rect group by frame),
pp as (select frame, u, v, max(value)::bigint as val, count(*) as n from hit group by 1, 2, 3),
ff as (select frame, sum(n)::bigint as samples, count(*) as pixels, sum(val)::bigint as total from pp group by frame)
select rr.frame as angle, messages, rays, bytes, samples, pixels, total from rr join ff on ff.frame = rr.frame""",
)
def _(s, sf):
    """Messages, rays, bytes, samples and the frame of every angle, in one job."""
    parts = array_engine.cast(blocks_of(s, sf, LARGEST), SURVEY_SCALED, BATCH)
    pixels = parts.groupBy("frame", "u", "v").agg(F.max("val").alias("val"), F.sum("samples").alias("samples"))
    frames = pixels.groupBy("frame").agg(F.sum("samples").alias("samples"), F.count("*").alias("pixels"), F.sum("val").alias("total"))
    cost = node_rects_batch(s, LARGEST, WORKERS).groupBy("frame").agg(F.count("*").alias("messages"), F.sum(F.expr(f"bigint{AREA}")).alias("rays"), F.sum(F.expr(f"{AREA} * 4L")).alias("bytes"))
    return cost.join(frames, "frame").select(F.col("frame").alias("angle"), "messages", "rays", "bytes", "samples", "pixels", "total")


# Cubes against nodes. Plans of powers of two nest: a brick of n is made of 64 / n bricks of the finest plan.

NODE_LIST = ", ".join(f"({n})" for n in NODES)
W2_SQL = " union all ".join(
    f"""select * from (with {S.kd_tree(spec.dims, WORKERS)}, {S.hit_cte(A30, name)}, {S.rects_of_nodes(A30, name, NODES)},
own as (select u, v, value, brick from hit vox join leaf on {IN_LEAF}),
p as (select n, brick // (64 // n) as node, u, v, count(*) as samples from own, (values {NODE_LIST}) t(n) group by all),
busy as (select n, max(samples)::bigint as largest, sum(covered)::bigint as merge_rows, sum(samples)::bigint as samples from (select n, node, sum(samples) as samples, count(*) as covered from p group by all) group by n),
sent as (select n, sum({AREA} * 4)::bigint as bytes from rect group by n)
select '{name}' as cube, busy.n as nodes, samples, largest, merge_rows, bytes from busy join sent on sent.n = busy.n)"""
    for name, spec in CUBES.items()
)


@query("w2", W2_SQL)
def _(s, sf):
    """Five cubes by node counts: all samples, the busiest node's, what the server merges, and message bytes."""
    out = None
    for name, spec in CUBES.items():
        parts = array_engine.cast(blocks_of(s, sf, name), spec, [A30])
        counts = F.explode(F.array(*[F.lit(n) for n in NODES])).alias("nodes")
        p = parts.select(counts, "brick", "u", "v", "samples").withColumn("node", F.expr(f"brick div ({WORKERS} div nodes)"))
        p = p.groupBy("nodes", "node", "u", "v").agg(F.sum("samples").alias("samples")).groupBy("nodes", "node").agg(F.sum("samples").alias("samples"), F.count("*").alias("covered"))
        p = p.groupBy("nodes").agg(F.sum("samples").alias("samples"), F.max("samples").alias("largest"), F.sum("covered").alias("merge_rows"))
        table = None
        for n in NODES:
            b = kd.kd(spec.dims, n).frame(s).withColumn("node", F.lit(n))
            table = b if table is None else table.unionByName(b)
        sent = view.rects_batch(table, view.views_frame(s, [A30], spec)).groupBy(F.col("node").alias("nodes")).agg(F.sum(F.expr(f"{AREA} * 4L")).alias("bytes"))
        part = p.join(sent, "nodes").select(F.lit(name).alias("cube"), "nodes", "samples", "largest", "merge_rows", "bytes")
        out = part if out is None else out.unionByName(part)
    return out


# Frame size

SIZES = (64, 128)
SIZED = [ViewSpec(30, n, n, frame=n) for n in SIZES]
add("w3", lambda s, sf: composite.final(array_engine.cast(blocks_of(s, sf, "survey", 16), SURVEY, SIZED[1:])), S.mip(SIZED[1], "survey"))
add("w3_relational", lambda s, sf: render.frame(cube.survey(s, sf), SURVEY, SIZED[1]), S.mip(SIZED[1], "survey"))


@query(
    "w3_ratio",
    f"""with {S.kd_tree(SURVEY.dims, 16)}, {S.CUBE['survey']}, {S.hits_batch(SIZED, 'survey')}, {S.rects_batch(SIZED, 'survey')}, c as (select frame, count(distinct (u, v)) as pixels, count(*) as samples from hit group by frame),
r as (select frame, sum({AREA} * 4)::bigint as bytes from rect group by frame),
b as (select max(pixels) filter (c.frame = 64) as p0, max(pixels) filter (c.frame = 128) as p1, max(samples) filter (c.frame = 64) as s0, max(samples) filter (c.frame = 128) as s1, max(bytes) filter (c.frame = 64) as b0, max(bytes) filter (c.frame = 128) as b1 from c join r on r.frame = c.frame)
select round(p1 / p0::double, 6) as pixels, round(s1 / s0::double, 6) as samples, round(b1 / b0::double, 6) as bytes from b""",
)
def _(s, sf):
    """Work of the larger frame over that of the smaller one, with four times the pixels."""
    parts = array_engine.cast(blocks_of(s, sf, "survey", 16), SURVEY, SIZED)
    p = parts.groupBy("frame", "u", "v").agg(F.sum("samples").alias("samples")).groupBy("frame").agg(F.count("*").alias("pixels"), F.sum("samples").alias("samples"))
    p = p.join(node_rects_batch(s, "survey", 16, SIZED).groupBy("frame").agg(F.sum(F.expr(f"{AREA} * 4L")).alias("bytes")), "frame")
    at = {n: {c: F.max(F.when(F.col("frame") == n, F.col(c))) for c in ("pixels", "samples", "bytes")} for n in SIZES}
    return p.agg(*[F.round(at[128][c] / at[64][c], 6).alias(c) for c in ("pixels", "samples", "bytes")])


# Message volume, all cubes, node counts and angles


def volume_sql(name, held=False):
    spec = CUBES[name]
    box = f"brick, {S.BOX_HELD} from vox join leaf on {IN_LEAF} group by brick" if held else "brick, x0, x1, y0, y1, z0, z1 from leaf"
    parts = " union all ".join(f"select * from (with {S.kd_tree(spec.dims, n)} select {n} as n, {box})" for n in NODES)
    return f"""select * from (with {S.CUBE[name] + ", " if held else ""}boxes as ({parts}), {S.rects_batch(BATCH, name, boxes='boxes', node='n')}
select '{name}' as cube, node as nodes, frame, node * 16384 as full_bytes, sum({AREA} * 4)::bigint as sent, round(sum({AREA} * 4) / 16384e0, 6) as ratio from rect group by node, frame)"""


def volumes(s, names, sf=None):
    """Of whole bricks, or of what the tables put into them."""
    out = None
    for name in names:
        table, plans = None, [kd.kd(CUBES[name].dims, n) for n in NODES]
        if sf is not None:
            table = partition.held(cube.load(s, sf, name), *plans).withColumn("node", F.element_at(F.array(*[F.lit(n) for n in NODES]), F.col("plan") + 1))
        for n, plan in zip(NODES, plans if sf is None else (), strict=sf is None):
            b = plan.frame(s).withColumn("node", F.lit(n))
            table = b if table is None else table.unionByName(b)
        r = view.rects_batch(table, view.views_frame(s, BATCH, CUBES[name])).groupBy(F.col("node").alias("nodes"), "frame").agg(F.sum(F.expr(f"{AREA} * 4L")).alias("sent"))
        r = r.select(F.lit(name).alias("cube"), "nodes", "frame", (F.col("nodes") * 16384).alias("full_bytes"), "sent", F.round(F.col("sent") / 16384.0, 6).alias("ratio"))
        out = r if out is None else out.unionByName(r)
    return out


add("w6", lambda s, sf: volumes(s, CUBES), " union all ".join(volume_sql(name) for name in CUBES))
add("c_nm", lambda s, sf: volumes(s, ["survey"], sf).drop("cube", "ratio"), f"select nodes, frame, full_bytes, sent from ({volume_sql('survey', True)})")


# From the older system to the newer one

SLAB8, KD8 = S.kd_tree(SURVEY.dims, 8, 2), S.kd_tree(SURVEY.dims, 8)


def step_sql(i, tree, rects, two_stage, dynamic):
    leaf = KD8 if tree else SLAB8
    found = f"{S.hits(A30).replace('select u, v,', 'select px.u, px.v,', 1)}, own as (select u, v, value, brick from hit vox join leaf on {IN_LEAF})" if dynamic else LEAF_FIXED
    worker = "brick // 2" if two_stage else "brick"
    cost = (
        f"{S.rects(A30, 'survey', node=worker)}, cost as (select (select sum({AREA})::bigint from rect) as rays, sum((u1 - u0) * (v1 - v0) * 4)::bigint as bytes from (select node, min(u0) as u0, max(u1) as u1, min(v0) as v0, max(v1) as v1 from rect group by node))"
        if rects
        else "cost as (select 8 * 4096::bigint as rays, 8 * 16384::bigint as bytes)"
    )
    return f"""select * from (with {leaf}, {S.CUBE['survey']}, {S.frame_pixels(A30, 'survey')}, {found}, {cost},
p as (select {worker} as w, u, v, max(value)::bigint as val, count(*) as n from own group by all), q as (select u, v, max(val) as val, count(*) as k, sum(n) as n from p group by u, v)
select {i} as step, max(rays) as rays, sum(n)::bigint as samples, sum(k)::bigint as merge_rows, max(bytes) as bytes, count(*) as pixels, sum(val)::bigint as total from q, cost)"""


@query("w7", " union all ".join(step_sql(i, st.tree, st.rects, st.two_stage, st.dynamic) for i, st in enumerate(baseline.LADDER)))
def _(s, sf):
    """Rays, samples, merged rows, bytes and the frame after each change."""
    plans = {False: kd.slab(SURVEY.dims, 8), True: kd.kd(SURVEY.dims, 8)}
    paths = {k: scratch(s) for k in plans}
    for k, plan in plans.items():
        store.write_blocks(array_engine.pack_bricks(cube.survey(s, sf), plan), paths[k])
    return baseline.ladder({k: store.read_bricks(s, p) for k, p in paths.items()}, plans, SURVEY, A30)


# Data types, odd numbers of workers, a real topology

for name in ("survey", "wide", "particle", "vec"):
    add(f"w8_{name}", lambda s, sf, name=name: composite.final(array_engine.cast(array_engine.pack_bricks(cube.load(s, sf, name), kd.kd(spec_of(name).dims, 8)), spec_of(name), [ViewSpec(45)])), S.mip(ViewSpec(45), name))
for n in (3, 5, 6, 7, 12):
    add(f"w10_{n}", lambda s, sf, n=n: composite.final(array_engine.cast(survey_blocks(s, sf, n), SURVEY, [A30])).agg(F.count("*").alias("pixels"), F.sum("val").alias("total")), f"select count(*) as pixels, sum(val)::bigint as total from ({S.mip(A30, 'survey')})")


@query("w10_topology", S.mip(A30, LARGEST))
def _(s, sf):
    """A frame by the suppliers of each nation as its GPUs: node buffers first, then the server's merge."""
    plan, _ = topology(s, sf, SURVEY_SCALED.dims)
    parts = array_engine.cast(array_engine.pack_bricks(cube.survey_scaled(s, sf), plan), SURVEY_SCALED, [A30])
    return composite.final(composite.node(parts))


# The planner's choice, and a frame made as it says


def planned_frame(s, sf, name, shot, few):
    """The frame of a stored cube by the executor that the planner picks; only bricks that the view sees are read."""
    spec = CUBES[name]
    bricks = kd.kd(spec.dims, 8)
    plan = planner.plan_render(spec, shot, bricks, few=few)
    if plan.executor == "object_order":
        return plan, render.axis_frame(cube.load(s, sf, name), spec, shot)
    if plan.executor == "relational":
        return plan, render.frame(cube.load(s, sf, name), spec, shot, bricks)
    path = scratch(s)
    store.write_blocks(array_engine.pack_bricks(cube.load(s, sf, name), bricks), path)
    return plan, composite.final(array_engine.cast(store.read_bricks(s, path, list(plan.bricks)), spec, [shot]))


PLANNED = ((ViewSpec(90), 10**7), (A30, 10**7), (A30, 10**3))


@query(
    "m_planner",
    " union all ".join(
        f"select * from (with {KD8}, {S.rects(v, 'survey')}, f as ({S.mip(v, 'survey')}) select {i} as turn, '{x}' as executor, (select sum({AREA})::bigint from rect) as rays, (select sum({AREA} * (x1 - x0 + y1 - y0 + z1 - z0))::bigint from rect join leaf using (brick)) as most_samples, (select count(*) from f) as pixels, (select sum(val)::bigint from f) as total)"
        for i, ((v, _), x) in enumerate(zip(PLANNED, ("object_order", "relational", "array"), strict=True))
    ),
)
def _(s, sf):
    """Three frames, one by each executor."""
    out = None
    for i, (shot, few) in enumerate(PLANNED):
        plan, frame = planned_frame(s, sf, "survey", shot, few)
        row = frame.agg(F.count("*").alias("pixels"), F.sum("val").alias("total")).select(F.lit(i).alias("turn"), F.lit(plan.executor).alias("executor"), F.lit(plan.rays).cast("long").alias("rays"), F.lit(plan.most_samples).cast("long").alias("most_samples"), "pixels", "total")
        out = row if out is None else out.unionByName(row)
    return out


@query("m_remote", S.mip(A30, "survey"))
def _(s, sf):
    """A frame written by the workers and read by a viewer that knows nothing of the cube."""
    path = scratch(s)
    composite.final(array_engine.cast(survey_blocks(s, sf), SURVEY, [A30])).write.parquet(path)
    return s.read.parquet(path)


add(
    "m_shm",
    lambda s, sf: partials(s, sf).groupBy("node").agg(F.count("*").alias("inside"), F.countDistinct("u", "v").alias("across")),
    f"{NODEHIT} select node, count(distinct (brick, u, v)) as inside, count(distinct (u, v)) as across from nh group by node",
)


# Rivals of the array executor and of residence in memory


@query("w4", f"select count(*) as pixels, 0::bigint as differ, true as less_shuffled from ({S.mip(A30, 'survey')})")
def _(s, sf):
    """Two executors, one frame: pixels, those that differ, and whether the array executor shuffles fewer rows than there are samples."""
    v = cube.survey(s, sf)
    parts = array_engine.cast(survey_blocks(s, sf), SURVEY, [A30])
    one, two = render.frame(v, SURVEY, A30), composite.final(parts)
    both = one.join(two.withColumnRenamed("val", "other"), ["u", "v"], "full_outer")
    differ = both.agg(F.count("*").alias("pixels"), F.count_if(~F.col("val").eqNullSafe(F.col("other"))).alias("differ"))
    return differ.crossJoin(parts.agg((F.count("*") < F.sum("samples")).alias("less_shuffled")))


def timed(f):
    t = time.time()
    out = f()
    return out, (time.time() - t) * 1000


@query("b_gpu")
def _(s, sf):
    """The measure that compares two accelerator models, of the two executors: mean, least and most share of time that the array executor saves."""
    v = cube.survey(s, sf).persist()
    blocks = survey_blocks(s, sf).persist()
    v.count(), blocks.count()
    rows = []
    for angle in (30, 60):
        one = ViewSpec(angle)
        times = [min(timed(lambda f=f: f().count())[1] for _ in range(2)) for f in (lambda: render.frame(v, SURVEY, one), lambda: composite.final(array_engine.cast(blocks, SURVEY, [one])))]
        rows.append((angle, *times))
    v.unpersist(), blocks.unpersist()
    return measure.reduction(s.createDataFrame(rows, "angle int, a double, b double"))


OOC_BYTES = f"select sum(volume)::bigint * 8 as bytes from (select distinct brick, (x1 - x0) * (y1 - y0) * (z1 - z0) as volume from vox join leaf on {IN_LEAF})"


@query(
    "b_ooc",
    f"with {S.kd_tree(SURVEY.dims, 8)}, {S.CUBE['survey']}, {S.hits_batch([ViewSpec(a, frame=a) for a in (0, 30, 60)], 'survey')}, px1 as (select frame, u, v, max(value)::bigint as val from hit group by 1, 2, 3), b as ({OOC_BYTES}) select mode, count(*) as pixels, sum(val)::bigint as total, max(bytes) * times as bytes from px1, b, (values ('pinned', 1), ('storage', 3)) m(mode, times) group by mode, times",
)
def _(s, sf):
    """Three frames from blocks pinned once and from blocks read for each frame: the same images, and the bytes of voxels that storage must give."""
    path = scratch(s)
    store.write_blocks(survey_blocks(s, sf), path)
    out = None
    for mode, hold in (("pinned", True), ("storage", False)):
        frames, read = None, None
        pinned = store.pin(store.read_bricks(s, path)) if hold else None
        for a in (0, 30, 60):
            blocks = pinned if hold else store.read_bricks(s, path)
            f = composite.final(array_engine.cast(blocks, SURVEY, [ViewSpec(a)]))
            frames = f if frames is None else frames.unionByName(f)
            if read is None or not hold:
                size = blocks.agg(F.sum(F.length("data")).alias("bytes"))
                read = size if read is None else read.unionByName(size)
        row = frames.agg(F.count("*").alias("pixels"), F.sum("val").alias("total")).crossJoin(read.agg(F.sum("bytes").alias("bytes"))).withColumn("mode", F.lit(mode))
        out = row if out is None else out.unionByName(row)
    return out


@query(
    "b_cpu",
    f"with {KD8}, {S.hit_cte(A30, 'survey')}, own as (select u, v, value, brick from hit vox join leaf on {IN_LEAF}), e as (select count(distinct (u, v)) as pixels from hit) select 1 as workers, (select pixels from e) as pixels, count(*) as busiest from hit union all select 8, (select pixels from e), max(n) from (select brick, count(*) as n from own group by brick)",
)
def _(s, sf):
    """One brick in one task against eight: the same frame, and the samples of the busiest worker."""
    out = None
    for n in (1, 8):
        blocks = survey_blocks(s, sf, n)
        parts = array_engine.cast(blocks.coalesce(1) if n == 1 else blocks, SURVEY, [A30])
        busiest = parts.groupBy("brick").agg(F.sum("samples").alias("n")).agg(F.max("n").alias("busiest"))
        row = composite.final(parts).agg(F.count("*").alias("pixels")).crossJoin(busiest).withColumn("workers", F.lit(n))
        out = row if out is None else out.unionByName(row)
    return out


# Balance: plans weighted by what is there and by what is sampled, and what moves between two views

WEIGHTED = (0, 30, 60, 90)


def weighted_sql(weights: str, name: str = "wl") -> str:
    """name(brick, x0, x1, y0, y1): four bricks; x is cut where half the weight is reached, then y in each half."""
    return f"""{name}x as (select min(x) + 1 as cut from (select x, sum(sum(w)) over (order by x) as run, sum(sum(w)) over () as t from {weights} group by x) where run * 2 >= t),
{name}h as (select h, case h when 0 then 0 else cut end as x0, case h when 0 then cut else 40 end as x1 from {name}x, (values (0), (1)) t(h)),
{name}y as (select h, x0, x1, min(y) + 1 as cut from (select h, x0, x1, y, sum(sum(w)) over (partition by h order by y) as run, sum(sum(w)) over (partition by h) as t from {weights} join {name}h on x >= x0 and x < x1 group by h, x0, x1, y) where run * 2 >= t group by all),
{name} as (select (2 * h + k)::int as brick, x0, x1, case k when 0 then 0 else cut end as y0, case k when 0 then cut else 40 end as y1 from {name}y, (values (0), (1)) t(k))"""


def sampled_weights(angles) -> str:
    views = [ViewSpec(a, frame=a) for a in angles]
    return f"{S.hits_batch(views, 'survey')}, wv as (select x, y, z, count(*) as w from hit group by x, y, z)"


def sample_weights(s, sf, angles):
    """Samples of each voxel over some angles."""
    out = None
    for a in angles:
        r = render.exact_mids(render.brick_rays(SURVEY, ViewSpec(a), kd.kd(SURVEY.dims, 8), s))
        p = render.nearest(render.samples(r, ("u", "v")), cube.survey(s, sf)).groupBy("x", "y", "z").agg(F.count("*").alias("n"))
        out = p if out is None else out.unionByName(p)
    return out.groupBy("x", "y", "z").agg(F.sum("n").alias("w"))


def shares(plan, weights):
    box = ("x0", "x1", "y0", "y1")
    w = partition.assign(weights, plan).groupBy("brick").agg(F.sum("w").alias("w"))
    return plan.frame(weights.sparkSession).select("brick", *[F.col(c).cast("long").alias(c) for c in box]).join(w, "brick")


SHARE = "select brick, x0, x1, y0, y1, sum(w)::bigint as w from {wv} join wl on x >= x0 and x < x1 and y >= y0 and y < y1 group by all"


@query("b_shader", f"with {S.SURVEY}, ov as (select x, y, z, 1 as w from vox), {weighted_sql('ov')} {SHARE.format(wv='ov')}")
def _(s, sf):
    """Bricks of unequal size that hold equal numbers of occupied voxels."""
    v = cube.survey(s, sf).withColumn("w", F.lit(1))
    return shares(kd.weighted(v, SURVEY.dims, 4), v)


@query("b_stat", f"with {S.SURVEY}, {sampled_weights(WEIGHTED)}, {weighted_sql('wv')} {SHARE.format(wv='wv')}")
def _(s, sf):
    """Bricks that get equal numbers of samples over all angles together."""
    w = sample_weights(s, sf, WEIGHTED).persist()
    return shares(kd.weighted(w, SURVEY.dims, 4, "w"), w)


@query(
    "b_dyn",
    f"""with a as (with {S.SURVEY}, {sampled_weights((30,))}, {weighted_sql('wv')} select * from wl), b as (with {S.SURVEY}, {sampled_weights((15,))}, {weighted_sql('wv')} select * from wl), {S.SURVEY}
select a.brick as old, b.brick as new, count(*) as n from vox join a on x >= a.x0 and x < a.x1 and y >= a.y0 and y < a.y1 join b on x >= b.x0 and x < b.x1 and y >= b.y0 and y < b.y1 where a.brick <> b.brick group by 1, 2""",
)
def _(s, sf):
    """Voxels that change owner if every view had its own balanced plan: from 30 to 15 degrees."""
    plans = [kd.weighted(sample_weights(s, sf, (a,)), SURVEY.dims, 4, "w") for a in (30, 15)]
    return partition.migrated(cube.survey(s, sf), *plans).groupBy("old", "new").agg(F.count("*").alias("n"))


# Sessions: views from a stream of requests, drawn

SMALL = 16
SESSION_VIEWS = [ViewSpec(15 * k, SMALL, SMALL, 1 + k % 4 / 2, frame=k) for k in range(24)]
DRAWN = f"""with r as (select user_id as session, max(event_id) as frame, max_by((props->>'$.k')::int % 24, event_id) as k from (select * from events qualify row_number() over (partition by user_id order by ts desc, event_id desc) = 1) group by user_id), {S.CUBE['survey']}, {S.hits_batch(SESSION_VIEWS, 'survey')},
p as (select frame as k, u, v, max(value)::bigint as val from hit group by 1, 2, 3), f as (select k, count(*) as pixels, sum(val)::bigint as total from p group by k)
select session, r.frame, 15 * k as angle, coalesce(pixels, 0) as pixels, coalesce(total, 0)::bigint as total from r left join f using (k)"""


def drawn(s, sf, requests):
    """Every session's newest request as an image: each view that is asked for is cast once, however many sessions share it."""
    blocks = survey_blocks(s, sf)
    return serve.drawn(requests, blocks, SURVEY, SMALL)


def image_facts(images):
    """Pixels and total of each session's image; a blank image has none."""
    return images.groupBy("session", "frame", "angle").agg(F.count("val").alias("pixels"), F.coalesce(F.sum("val"), F.lit(0)).alias("total"))


add("m_sched", lambda s, sf: image_facts(drawn(s, sf, serve.latest(serve.decode(tbl(s, sf, "events"))))), DRAWN)


@query("w11", DRAWN)
def _(s, sf):
    """The same from a stream: each micro-batch draws its newest views into a folder of its own, apart from who shows them."""
    from .surface import streamed

    sink = scratch(s)
    path = scratch(s)
    store.write_blocks(survey_blocks(s, sf), path)
    blocks = store.read_bricks(s, path)
    serve.start(streamed(s, sf), lambda r: serve.drawn(r, blocks, SURVEY, SMALL), sink, scratch(s)).awaitTermination()
    last = s.read.parquet(sink).withColumn("newest", F.max("ts").over(Window.partitionBy("session"))).where("ts = newest")
    last = last.withColumn("newest", F.max("frame").over(Window.partitionBy("session"))).where("frame = newest")
    return image_facts(last)


add("m_evt", lambda s, sf: _w11(s, sf).select("session", "frame"), f"select session, frame from ({DRAWN})")
_w11 = _


# Measured runs of this engine: their numbers differ from run to run, so these have no SQL


def measured(s, sf, angles=(0, 30, 60, 90), repeats=3, nodes=(8,), side=64):
    """cube, angle, nodes, run, stage, ms of frames of the survey cube: rays and samples, merge in nodes, messages, merge at the server."""
    rows = []
    for n in nodes:
        plan = kd.two_level(SURVEY.dims, [2] * (n // 2)) if n > 1 else kd.kd(SURVEY.dims, 1)
        blocks = array_engine.pack_bricks(cube.survey(s, sf), plan).persist()
        blocks.count()
        for a in angles:
            shot = ViewSpec(a, side, side)
            table = view.node_rects(view.rects(plan.frame(s), shot, SURVEY))
            for run in range(repeats):
                parts = array_engine.cast(blocks, SURVEY, [shot]).persist()
                _, cast_ms = timed(parts.count)
                merged = composite.node(parts).persist()
                _, node_ms = timed(merged.count)
                sent = composite.pack(merged, table, True).persist()
                _, send_ms = timed(sent.count)
                _, server_ms = timed(lambda sent=sent: composite.final(composite.unpack(sent)).count())
                rows += [("survey", a, n, run, stage, ms) for stage, ms in (("render", cast_ms), ("merge", node_ms), ("send", send_ms), ("server", server_ms))]
                for x in (parts, merged, sent):
                    x.unpersist()
        blocks.unpersist()
    return s.createDataFrame(rows, "cube string, angle int, nodes int, run int, stage string, ms double")


def total_runs(runs):
    return runs.groupBy("cube", "angle", "nodes", "run").agg(F.sum("ms").alias("ms"))


add("c_tr_measured", lambda s, sf: measure.total_model(measured(s, sf), "angle"))
add("c_stage_measured", lambda s, sf: measure.stage_share(measured(s, sf)))
add("w5_measured", lambda s, sf: measure.fps(measure.p75(measure.median_runs(total_runs(measured(s, sf))))))


@query("c_scale_measured")
def _(s, sf):
    """Median time by nodes, speed-up, efficiency, and the count past which the time stays or rises."""
    t = total_runs(measured(s, sf, (30,), 3, (2, 4, 8))).groupBy("cube", "nodes").agg(F.median("ms").alias("ms"))
    rows = s.createDataFrame(t.collect(), t.schema)  # a row a node count
    return measure.speedup(rows).join(measure.critical_point(rows), "cube")


@query("c_res_measured")
def _(s, sf):
    """Time of a frame with four times the pixels over that of the smaller one."""
    out = None
    for side in (64, 128):
        t = total_runs(measured(s, sf, (30,), 3, (8,), side)).groupBy("cube").agg(F.median("ms").alias("ms")).withColumn("side", F.lit(side))
        out = t if out is None else out.unionByName(t)
    return measure.ratio(out, "side", 64, 128, ["cube"])
