"""Ray casting as relations: samples along rays, lookup, accumulation. The array executor is in ``array_engine``."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.kd import KdPlan, kd
from ..plans.spec import CubeSpec, ViewSpec
from .partition import assign
from .view import EPS, box_rays, clip, num

AXES = ("x", "y", "z")
RULES = ("l1", "linf", "unit", "half")


def crossings(a: str) -> Column:
    """Parameters at which the ray crosses inner planes of one axis between te and tx."""
    o, d = F.col(f"o{a}"), F.col(f"d{a}")
    pe, px = o + F.col("te") * d, o + F.col("tx") * d
    low, high = F.floor(F.least(pe, px)).cast("int"), F.ceil(F.greatest(pe, px)).cast("int")
    planes = F.when((d != 0) & (low <= high), F.sequence(low, high)).otherwise(F.array().cast("array<int>"))
    return F.filter(F.transform(planes, lambda k: (k - o) / d), lambda t: (t > F.col("te")) & (t < F.col("tx")))


def exact_mids(r: DataFrame) -> DataFrame:
    """mids: the middle of every stretch between crossings, so each crossed voxel gets one sample."""
    t = F.array_sort(F.concat(F.array("te"), *[crossings(a) for a in AXES], F.array("tx")))
    r = r.withColumn("t", t)
    n = F.size("t")
    pairs = F.zip_with(F.slice("t", F.lit(1), n - 1), F.slice("t", F.lit(2), n - 1), lambda a, b: F.when(b - a > EPS, (a + b) / 2.0))
    return r.withColumn("mids", F.filter(pairs, lambda m: m.isNotNull())).drop("t")


def steps(rule: str) -> Column:
    """Number of samples of a uniform step for a ray, from its entry and exit."""
    delta = {a: (F.col("tx") - F.col("te")) * F.abs(F.col(f"d{a}")) for a in AXES}
    moved = {a: F.abs(F.floor(F.col(f"o{a}") + (F.col("tx") - 1e-9) * F.col(f"d{a}")) - F.floor(F.col(f"o{a}") + (F.col("te") + 1e-9) * F.col(f"d{a}"))) for a in AXES}
    chord = F.sqrt(sum((delta[a] * delta[a] for a in AXES), F.lit(0.0)))
    n = {
        "l1": lambda: moved["x"] + moved["y"] + moved["z"] + 1,
        "linf": lambda: F.greatest(*moved.values()) + 1,
        "unit": lambda: F.ceil(chord),
        "half": lambda: F.ceil(chord * 2.0),
    }[rule]()
    return F.greatest(n, F.lit(1)).cast("int")


def uniform_mids(r: DataFrame, rule: str = "l1") -> DataFrame:
    """mids: equal steps in [te, tx], a sample in the middle of each."""
    r = r.withColumn("n", steps(rule))
    return r.withColumn("mids", F.transform(F.sequence(F.lit(0), F.col("n") - 1), lambda i: F.col("te") + (i + 0.5) * ((F.col("tx") - F.col("te")) / F.col("n")))).drop("n")


def fixed_mids(r: DataFrame, dt: float = 1.0) -> DataFrame:
    """mids: multiples of one global step, blind to entry and exit; the same for any bricks."""
    first, last = F.ceil(F.col("te") / dt).cast("int"), F.ceil(F.col("tx") / dt).cast("int") - 1
    return r.withColumn("mids", F.when(first <= last, F.transform(F.sequence(first, last), lambda i: i * num(dt))).otherwise(F.array().cast("array<double>")))


def mids(r: DataFrame, mode: str = "exact", **how) -> DataFrame:
    return {"exact": exact_mids, "uniform": uniform_mids, "fixed": fixed_mids}[mode](r, **how)


def samples(r: DataFrame, keep: tuple[str, ...] = ("brick", "u", "v")) -> DataFrame:
    """One row a sample: t and the voxel it lies in."""
    s = r.select(*keep, *[f"{k}{a}" for k in "od" for a in AXES], F.explode("mids").alias("t"))
    return s.select(*keep, "t", *[F.floor(F.col(f"o{a}") + F.col("t") * F.col(f"d{a}")).cast("long").alias(a) for a in AXES])


def nearest(s: DataFrame, voxels: DataFrame, how: str = "inner") -> DataFrame:
    """Value of the voxel of each sample; samples in absent voxels drop (or are 0 with how='left')."""
    out = s.join(voxels.select(*AXES, F.col("v").alias("value")), list(AXES), how)
    return out if how == "inner" else out.withColumn("value", F.coalesce("value", F.lit(0)))


def trilinear(r: DataFrame, voxels: DataFrame, cube: CubeSpec, keep: tuple[str, ...] = ("u", "v")) -> DataFrame:
    """Interpolated value at each sample point, from the eight cell centres around it; borders repeat. Fixed operand order."""
    s = r.select(*keep, *[f"{k}{a}" for k in "od" for a in AXES], F.explode("mids").alias("t"))
    for a, n in zip(AXES, cube.dims, strict=True):
        q = F.col(f"o{a}") + F.col("t") * F.col(f"d{a}") - 0.5
        s = s.withColumn(f"f{a}", q - F.floor(q)).withColumn(f"i{a}", F.floor(q).cast("long"))
    at = [F.struct(F.lit(c).alias("c"), *[F.greatest(F.lit(0), F.least(F.lit(n - 1), F.col(f"i{a}") + (c >> i & 1))).cast("long").alias(a) for i, (a, n) in enumerate(zip(AXES, cube.dims, strict=True))]) for c in range(8)]
    e = s.select(*keep, "t", "fx", "fy", "fz", F.explode(F.array(*at)).alias("p")).select(*keep, "t", "fx", "fy", "fz", "p.*")
    g = e.join(voxels.select(*AXES, F.col("v").alias("value")), list(AXES), "left").groupBy(*keep, "t", "fx", "fy", "fz")
    g = g.agg(*[F.max(F.when(F.col("c") == c, F.col("value"))).alias(f"c{c}") for c in range(8)])

    def lerp(a, b, f):
        return a + f * (b - a)

    c = [F.coalesce(F.col(f"c{i}"), F.lit(0)).cast("double") for i in range(8)]
    x = [lerp(c[2 * i], c[2 * i + 1], F.col("fx")) for i in range(4)]
    y = [lerp(x[0], x[1], F.col("fy")), lerp(x[2], x[3], F.col("fy"))]
    return g.select(*keep, "t", lerp(y[0], y[1], F.col("fz")).alias("value"))


def mip(s: DataFrame, keys: tuple[str, ...] = ("u", "v")) -> DataFrame:
    return s.groupBy(*keys).agg(F.max("value").alias("val"))


def brick_rays(cube: CubeSpec, view: ViewSpec, plan: KdPlan, spark, rectangles: bool = True) -> DataFrame:
    return clip(box_rays(plan.frame(spark), view, cube, rectangles))


def frame(voxels: DataFrame, cube: CubeSpec, view: ViewSpec, plan: KdPlan | None = None, mode: str = "exact", rectangles: bool = True, **how) -> DataFrame:
    """u, v, val of the maximum intensity projection by the relational executor; only pixels that see a voxel."""
    plan = plan or kd(cube.dims, 8)
    r = mids(brick_rays(cube, view, plan, voxels.sparkSession, rectangles), mode, **how)
    return mip(nearest(samples(r, ("u", "v")), voxels))


def axis_frame(voxels: DataFrame, cube: CubeSpec, view: ViewSpec) -> DataFrame:
    """Object-order short cut for right angles: project occupied voxels along an axis first, then look pixels up; no rays."""
    s, (cx, cy, cz) = view.scale(cube), cube.centre
    side = "x" if view.sin == 0 else "z"
    flat = voxels.groupBy(side, "y").agg(F.max("v").alias("val"))
    spark = voxels.sparkSession
    p = spark.range(view.width * view.height).select((F.col("id") % view.width).cast("int").alias("u"), F.expr(f"int(id div {view.width})").alias("v"))
    right = (F.col("u") + num(0.5) - num(view.width / 2)) / num(s)
    up = (F.col("v") + num(0.5) - num(view.height / 2)) / num(s)
    at = num(cx) + right * num(view.cos) if side == "x" else num(cz) + right * num(view.sin)
    p = p.select("u", "v", F.floor(at).cast("long").alias(side), F.floor(num(cy) + up).cast("long").alias("y"))
    return p.join(F.broadcast(flat) if cube.dims[0] * cube.dims[1] * cube.dims[2] < 10**7 else flat, [side, "y"]).select("u", "v", "val")


def terminated(voxels: DataFrame, cube: CubeSpec, view: ViewSpec, top: int, plan: KdPlan | None = None) -> DataFrame:
    """Two rounds by brick brightness: pixels that reach the global maximum in the first are not cast again."""
    spark = voxels.sparkSession
    plan = plan or kd(cube.dims, 8)
    local = assign(voxels, plan).groupBy("brick").agg(F.max("v").alias("hi"))
    bright = plan.frame(spark).join(F.broadcast(local), "brick")
    r = clip(box_rays(bright, view, cube))
    keep = ("brick", "u", "v")
    first = mip(nearest(samples(mids(r.where(F.col("hi") == top)), keep), voxels))
    done = first.where(F.col("val") == top).select("u", "v")
    rest = r.where(F.col("hi") < top).join(done, ["u", "v"], "left_anti")
    second = mip(nearest(samples(mids(rest), keep), voxels))
    return first.unionByName(second).groupBy("u", "v").agg(F.max("val").alias("val"))


def skip_empty(voxels: DataFrame, plan: KdPlan, background: int = 0) -> DataFrame:
    """Bricks with anything above the background."""
    busy = assign(voxels, plan).where(F.col("v") > background).select("brick").distinct()
    return plan.frame(voxels.sparkSession).join(busy, "brick", "left_semi")


def skipping_frame(voxels: DataFrame, cube: CubeSpec, view: ViewSpec, plan: KdPlan, background: int) -> DataFrame:
    """The projection of what lies above a background; rays start only in bricks that have any of it."""
    bright = voxels.where(F.col("v") > background)
    r = mids(clip(box_rays(skip_empty(voxels, plan, background), view, cube)))
    return mip(nearest(samples(r, ("u", "v")), bright))


# Emission and opacity


def table_values(s: DataFrame, lo: int, hi: int, buckets: int = 16) -> DataFrame:
    """Colour c and opacity a of each sample from a ramp table of 16 buckets."""
    b = F.least(F.lit(buckets - 1), F.expr(f"int((value - {lo}) * {buckets} div {max(1, hi - lo)})"))
    s = s.withColumn("b", b)
    return s.withColumn("c", F.col("b") / num(buckets - 1)).withColumn("a", F.col("b") * F.col("b") / num(4.0 * (buckets - 1) ** 2)).drop("b")


def over(ordered: Column, limit: float | None = None) -> Column:
    """Front-to-back blend of an array of (t, c, a) sorted by t: struct(c, a). limit: opacity at which the rest is left out."""
    start = F.struct(F.lit(0.0).alias("c"), F.lit(0.0).alias("a"))

    def step(acc, x):
        new = F.struct((acc["c"] + (1.0 - acc["a"]) * x["a"] * x["c"]).alias("c"), (acc["a"] + (1.0 - acc["a"]) * x["a"]).alias("a"))
        return new if limit is None else F.when(acc["a"] >= limit, acc).otherwise(new)

    return F.aggregate(ordered, start, step)


def alpha(s: DataFrame, keys: tuple[str, ...] = ("u", "v"), limit: float | None = None) -> DataFrame:
    """Ordered blend of all samples of a key: c, a and the entry t."""
    g = s.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("t", "c", "a"))).alias("l"))
    g = g.withColumn("o", over(F.col("l"), limit))
    return g.select(*keys, F.col("l")[0]["t"].alias("t"), F.col("o.c").alias("c"), F.col("o.a").alias("a"))


def merge_alpha(partials: DataFrame, keys: tuple[str, ...] = ("u", "v")) -> DataFrame:
    """Blend of partial results in the order of their entry; associative, so any contiguous grouping gives the same."""
    g = partials.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("t", "c", "a"))).alias("l"))
    start = F.struct(F.lit(0.0).alias("c"), F.lit(0.0).alias("a"))
    o = F.aggregate("l", start, lambda acc, x: F.struct((acc["c"] + (1.0 - acc["a"]) * x["c"]).alias("c"), (acc["a"] + (1.0 - acc["a"]) * x["a"]).alias("a")))
    return g.withColumn("o", o).select(*keys, F.col("l")[0]["t"].alias("t"), F.col("o.c").alias("c"), F.col("o.a").alias("a"))
