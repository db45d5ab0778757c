"""Views to rectangles, pixels and rays. A matrix is sixteen literals, so Catalyst folds the projection."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.spec import CubeSpec, ViewSpec

BOX = ("x0", "x1", "y0", "y1", "z0", "z1")


def num(x: float) -> Column:
    return F.lit(float(x))


def projected(view: ViewSpec, cube: CubeSpec, x: Column, y: Column, z: Column) -> tuple[Column, Column, Column]:
    """u w, v w and w of a point."""
    m = view.matrix(cube)

    def row(i):
        return num(m[4 * i]) * x + num(m[4 * i + 1]) * y + num(m[4 * i + 2]) * z + num(m[4 * i + 3])

    return row(0), row(1), row(3)


def rects(bricks: DataFrame, view: ViewSpec, cube: CubeSpec, clip: bool = True) -> DataFrame:
    """Rendering rectangle of each brick: bounds of its eight projected corners, clipped to the frame; bricks outside drop.
    A corner behind the eye makes it the whole frame."""
    corners = F.array(*[F.struct(*[F.col(f"{c}{i >> k & 1}").cast("double").alias(c) for k, c in enumerate("xyz")]) for i in range(8)])
    p = bricks.select("brick", "node", F.explode(corners).alias("p"))
    u, v, w = projected(view, cube, F.col("p.x"), F.col("p.y"), F.col("p.z"))
    p = p.select("brick", "node", u.alias("uw"), v.alias("vw"), w.alias("w"))
    good = F.col("w") > 0
    p = p.select("brick", "node", good.alias("good"), F.when(good, F.col("uw") / F.col("w")).alias("u"), F.when(good, F.col("vw") / F.col("w")).alias("v"))
    b = p.groupBy("brick", "node").agg(F.bool_and("good").alias("good"), *[f(c).alias(n) for f, c, n in ((F.min, "u", "ul"), (F.max, "u", "uh"), (F.min, "v", "vl"), (F.max, "v", "vh"))])

    def bound(low, high, size):
        a, z = F.floor(F.col(low)), F.ceil(F.col(high))
        if clip:
            a, z = F.greatest(a, F.lit(0)), F.least(z, F.lit(size))
        return F.when(F.col("good"), a).otherwise(0).cast("int"), F.when(F.col("good"), z).otherwise(size).cast("int")

    (u0, u1), (v0, v1) = bound("ul", "uh", view.width), bound("vl", "vh", view.height)
    return b.select("brick", "node", u0.alias("u0"), u1.alias("u1"), v0.alias("v0"), v1.alias("v1")).where("u0 < u1 and v0 < v1")


def node_rects(r: DataFrame) -> DataFrame:
    """Union box of the rectangles of each node."""
    return r.groupBy("node").agg(F.min("u0").alias("u0"), F.max("u1").alias("u1"), F.min("v0").alias("v0"), F.max("v1").alias("v1"))


def pixels(r: DataFrame) -> DataFrame:
    """One row a pixel of each rectangle; nothing outside is ever made."""
    u = r.withColumn("u", F.explode(F.sequence("u0", F.col("u1") - 1)))
    return u.withColumn("v", F.explode(F.sequence("v0", F.col("v1") - 1))).drop("u0", "u1", "v0", "v1")


def rays(p: DataFrame, view: ViewSpec, cube: CubeSpec) -> DataFrame:
    """Origin and direction through each pixel's centre."""
    s, (cx, cy, cz) = view.scale(cube), cube.centre
    right = (F.col("u") + num(0.5) - num(view.width / 2)) / num(s)
    up = (F.col("v") + num(0.5) - num(view.height / 2)) / num(s)
    on = (num(cx) + right * num(view.cos), num(cy) + up, num(cz) + right * num(view.sin))  # in the plane of the centre
    if view.distance is None:
        return p.select("*", *[c.alias(f"o{a}") for a, c in zip("xyz", on, strict=True)], num(-view.sin).alias("dx"), num(0.0).alias("dy"), num(view.cos).alias("dz"))
    eye = view.eye(cube)
    return p.select("*", *[num(e).alias(f"o{a}") for a, e in zip("xyz", eye, strict=True)], *[(c - num(e)).alias(f"d{a}") for a, c, e in zip("xyz", on, eye, strict=True)])


EPS = 1e-9


def clip(r: DataFrame) -> DataFrame:
    """Entry te and exit tx of each ray in its brick's box; rays that miss it drop. Needs x0..z1, ox..oz, dx..dz."""
    low, high = [], []
    inside = F.lit(True)
    for a in "xyz":
        o, d, b0, b1 = F.col(f"o{a}"), F.col(f"d{a}"), F.col(f"{a}0"), F.col(f"{a}1")
        safe = F.when(d != 0, d)
        ta, tb = (b0 - o) / safe, (b1 - o) / safe
        low.append(F.coalesce(F.least(ta, tb), F.lit(float("-inf"))))
        high.append(F.coalesce(F.greatest(ta, tb), F.lit(float("inf"))))
        inside = inside & ((d != 0) | ((o >= b0) & (o < b1)))
    te, tx = F.greatest(*low), F.least(*high)
    return r.where(inside).select("*", te.alias("te"), tx.alias("tx")).where(F.col("tx") - F.col("te") > EPS)


def box_rays(bricks: DataFrame, view: ViewSpec, cube: CubeSpec, rectangles: bool = True) -> DataFrame:
    """Rays of every brick before the box test. Without rectangles every brick starts every pixel."""
    if rectangles:
        p = pixels(rects(bricks, view, cube)).drop("node")
    else:
        p = bricks.select("brick", F.lit(0).alias("u0"), F.lit(view.width).alias("u1"), F.lit(0).alias("v0"), F.lit(view.height).alias("v1"))
        p = pixels(p)
    return rays(p.join(F.broadcast(bricks), "brick"), view, cube)


def views_frame(spark, views: list[ViewSpec], cube: CubeSpec) -> DataFrame:
    """frame, angle, w, h, m: a batch of views as rows, so that all their frames are one job."""
    rows = [(v.frame, float(v.angle), v.width, v.height, v.matrix(cube)) for v in views]
    return spark.createDataFrame(rows, "frame long, angle double, w int, h int, m array<double>")


def rects_batch(bricks: DataFrame, views: DataFrame) -> DataFrame:
    """frame, angle, brick, node and rectangle for every view of a batch; both sides are control tables, a few rows a worker or request."""
    corners = F.array(*[F.struct(*[F.col(f"{c}{i >> k & 1}").cast("double").alias(c) for k, c in enumerate("xyz")]) for i in range(8)])
    p = bricks.select("brick", "node", F.explode(corners).alias("p")).crossJoin(F.broadcast(views))

    def row(i):
        m = F.col("m")
        return m[4 * i] * F.col("p.x") + m[4 * i + 1] * F.col("p.y") + m[4 * i + 2] * F.col("p.z") + m[4 * i + 3]

    p = p.select("frame", "angle", "brick", "node", "w", "h", row(0).alias("a"), row(1).alias("b"), row(3).alias("k"))
    p = p.select("frame", "angle", "brick", "node", "w", "h", (F.col("k") > 0).alias("good"), F.when(F.col("k") > 0, F.col("a") / F.col("k")).alias("u"), F.when(F.col("k") > 0, F.col("b") / F.col("k")).alias("v"))
    g = p.groupBy("frame", "angle", "brick", "node", "w", "h").agg(F.bool_and("good").alias("good"), F.min("u").alias("ul"), F.max("u").alias("uh"), F.min("v").alias("vl"), F.max("v").alias("vh"))
    low = lambda c: F.when(F.col("good"), F.greatest(F.floor(c), F.lit(0))).otherwise(0).cast("int")
    high = lambda c, n: F.when(F.col("good"), F.least(F.ceil(c), F.col(n))).otherwise(F.col(n)).cast("int")
    out = g.select("frame", "angle", "brick", "node", low("ul").alias("u0"), high("uh", "w").alias("u1"), low("vl").alias("v0"), high("vh", "h").alias("v1"))
    return out.where("u0 < u1 and v0 < v1")
