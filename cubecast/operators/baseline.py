"""What the methods are compared with: other orders of traversal, other partitions, other message schemes."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.kd import KdPlan, slab
from ..plans.spec import CubeSpec, ViewSpec
from . import array_engine, composite, render
from .render import AXES
from .view import box_rays, clip, num
from .view import rects as rectangles_of


def previous(voxels: DataFrame, cube: CubeSpec, view: ViewSpec, n: int = 8, rects: bool = False, dynamic: bool = False, kd_plan: KdPlan | None = None) -> DataFrame:
    """The older system as the list of changes implies it: slabs, every pixel from every brick, a fixed step, one merge. Each switch adds one change."""
    plan = kd_plan or slab(cube.dims, n)
    r = clip(box_rays(plan.frame(voxels.sparkSession), view, cube, rects))
    r = render.mids(r, "exact") if dynamic else render.mids(r, "fixed", dt=1.0)
    return render.mip(render.nearest(render.samples(r, ("u", "v")), voxels))


@dataclass(frozen=True)
class Step:
    """One system on the way from the older to the newer one."""

    rects: bool = False
    tree: bool = False
    two_stage: bool = False
    dynamic: bool = False


#: Each step adds one change: rectangles, k-d bricks, the merge in two stages, the sample in each crossed voxel.
LADDER = (Step(), Step(True), Step(True, True), Step(True, True, True), Step(True, True, True, True))


def ladder(blocks: dict[bool, DataFrame], plans: dict[bool, KdPlan], cube: CubeSpec, view: ViewSpec, gpus: int = 2) -> DataFrame:
    """step, rays, samples, merge_rows, bytes, pixels, total of every step. blocks and plans: by whether they come from the k-d tree.

    merge_rows: what the server merges. bytes: messages to it, four a pixel; without rectangles each is a whole frame."""
    spark = blocks[True].sparkSession
    out = None
    for i, step in enumerate(LADDER):
        parts = array_engine.cast(blocks[step.tree], cube, [view], mode="exact" if step.dynamic else "fixed", rectangles=step.rects)
        worker = F.expr(f"int(brick div {gpus})") if step.two_stage else F.col("brick")
        sent = parts.groupBy(worker.alias("worker"), "u", "v").agg(F.max("val").alias("val"), F.sum("samples").alias("samples"))
        frame = sent.groupBy("u", "v").agg(F.max("val").alias("val"), F.count("*").alias("rows"), F.sum("samples").alias("samples"))
        facts = frame.agg(F.sum("samples").alias("samples"), F.sum("rows").alias("merge_rows"), F.count("*").alias("pixels"), F.sum("val").alias("total"))
        table = plans[step.tree].frame(spark)
        if step.rects:
            r = rectangles_of(table, view, cube)
            area = (F.col("u1") - F.col("u0")) * (F.col("v1") - F.col("v0"))
            mine = r.withColumn("node", worker).groupBy("node").agg(F.min("u0").alias("u0"), F.max("u1").alias("u1"), F.min("v0").alias("v0"), F.max("v1").alias("v1"))
            cost = r.agg(F.sum(area).alias("rays")).crossJoin(mine.agg((F.sum(area) * 4).alias("bytes")))
        else:
            pixels = view.width * view.height
            cost = table.agg((F.count("*") * pixels).alias("rays"), (F.count("*") * pixels * 4).alias("bytes"))
        row = facts.crossJoin(cost).select(F.lit(i).alias("step"), "rays", "samples", "merge_rows", "bytes", "pixels", "total")
        out = row if out is None else out.unionByName(row)
    return out


def slices(voxels: DataFrame, axis: str, lo: int, hi: int, levels: int = 8) -> DataFrame:
    """Frame-by-frame 2-D views, filled contours: k, u, w, bucket."""
    a, b = [c for c in AXES if c != axis]
    bucket = F.expr(f"least({levels - 1}, int((v - {lo}) * {levels} div {max(1, hi - lo)}))")
    return voxels.select(F.col(axis).alias("k"), F.col(a).alias("u"), F.col(b).alias("w"), bucket.alias("bucket"))


def iso(voxels: DataFrame, cube: CubeSpec, view: ViewSpec, level: int, plan: KdPlan) -> DataFrame:
    """u, v, t, val of the first sample at or above a level: a surface."""
    s = render.nearest(render.samples(render.mids(render.brick_rays(cube, view, plan, voxels.sparkSession)), ("u", "v")), voxels)
    g = s.where(F.col("value") >= level).groupBy("u", "v").agg(F.min(F.struct("t", "value")).alias("m"))
    return g.select("u", "v", F.round("m.t", 6).alias("t"), F.col("m.value").alias("val"))


def pyramid(voxels: DataFrame, k: int = 1, agg: str = "mean") -> DataFrame:
    """A cube of half the side, k times. mean counts absent voxels as background."""
    f = 1 << k
    g = voxels.groupBy(*[F.expr(f"{a} div {f}").alias(a) for a in AXES])
    return g.agg((F.expr(f"sum(v) div {f ** 3}") if agg == "mean" else F.max("v")).alias("v"))


def pyramid_error(voxels: DataFrame, k: int) -> DataFrame:
    """What the projection of a mean pyramid loses along z: pixels, those that fade to under half, mean and largest loss."""
    f = 1 << k
    fine = voxels.groupBy(F.expr(f"x div {f}").alias("x"), F.expr(f"y div {f}").alias("y")).agg(F.max("v").alias("fine"))
    coarse = pyramid(voxels, k).groupBy("x", "y").agg(F.max("v").alias("coarse"))
    d = F.col("fine") - F.col("coarse")
    return fine.join(coarse, ["x", "y"]).agg(F.count("*").alias("pixels"), F.count_if(F.col("coarse") * 2 < F.col("fine")).alias("faded"), F.round(F.avg(d), 4).alias("mae"), F.max(d).alias("maxabs"))


def splat(voxels: DataFrame, cube: CubeSpec, view: ViewSpec) -> DataFrame:
    """Object order: each voxel is drawn over the pixels whose centres lie in its projected box; max. A voxel's footprint is a few pixels."""
    from .view import projected

    corners = [(x, y, z) for x in (0, 1) for y in (0, 1) for z in (0, 1)]
    us, vs = [], []
    for x, y, z in corners:
        u, v, w = projected(view, cube, *[(F.col(a) + d).cast("double") for a, d in zip(AXES, (x, y, z), strict=True)])
        us.append(u / w)
        vs.append(v / w)
    p = voxels.select("v", F.least(*us).alias("ul"), F.greatest(*us).alias("uh"), F.least(*vs).alias("vl"), F.greatest(*vs).alias("vh"))
    p = p.select(F.col("v").alias("val"), *[e.cast("int").alias(n) for n, e in (("u0", F.ceil(F.col("ul") - 0.5)), ("u1", F.ceil(F.col("uh") - 0.5) - 1), ("v0", F.ceil(F.col("vl") - 0.5)), ("v1", F.ceil(F.col("vh") - 0.5) - 1))])
    p = p.where("u0 <= u1 and v0 <= v1").withColumn("u", F.explode(F.sequence("u0", "u1"))).withColumn("v", F.explode(F.sequence("v0", "v1")))
    return p.where(f"u >= 0 and u < {view.width} and v >= 0 and v < {view.height}").groupBy("u", "v").agg(F.max("val").alias("val"))


def shear(voxels: DataFrame, cube: CubeSpec, view: ViewSpec) -> DataFrame:
    """Shear-warp, first half: slices along the main axis move by a whole offset, then a maximum along that axis: intermediate image (a, y, val)."""
    along_z = abs(view.cos) >= abs(view.sin)
    main, other = ("z", "x") if along_z else ("x", "z")
    ratio = (view.sin / view.cos) if along_z else (view.cos / view.sin)
    offset = F.floor((F.col(main) + 0.5) * num(ratio) + 0.5).cast("long")
    return voxels.groupBy((F.col(other) + offset).alias("a"), "y").agg(F.max("v").alias("val"))


def shear_warp(voxels: DataFrame, cube: CubeSpec, view: ViewSpec) -> DataFrame:
    """Second half: the intermediate image scaled along a to the frame."""
    s, (cx, cy, cz) = view.scale(cube), cube.centre
    along_z = abs(view.cos) >= abs(view.sin)
    image = shear(voxels, cube, view)
    p = voxels.sparkSession.range(view.width * view.height).select((F.col("id") % view.width).cast("int").alias("u"), F.expr(f"int(id div {view.width})").alias("v"))
    right = (F.col("u") + num(0.5) - num(view.width / 2)) / num(s)
    up = (F.col("v") + num(0.5) - num(view.height / 2)) / num(s)
    # a ray keeps x cos + z sin; at main coordinate 0 it meets the other axis at:
    at = (right + num(cx * view.cos + cz * view.sin)) / num(view.cos if along_z else view.sin)
    p = p.select("u", "v", F.floor(at).cast("long").alias("a"), F.floor(num(cy) + up).cast("long").alias("y"))
    return p.join(image, ["a", "y"]).select("u", "v", "val")


def map_reduce(voxels: DataFrame, cube: CubeSpec, view: ViewSpec, plan: KdPlan) -> DataFrame:
    """Bricks emit pixel fragments, pixels reduce; rectangles are not used."""
    r = render.exact_mids(clip(box_rays(plan.frame(voxels.sparkSession), view, cube, False)))
    fragments = render.nearest(render.samples(r), voxels).select("u", "v", "value").repartition("u", "v")
    return fragments.groupBy("u", "v").agg(F.max("value").alias("val"))


def one_stage(partials: DataFrame) -> DataFrame:
    """Every worker's partial image straight to the server."""
    return composite.final(partials)
