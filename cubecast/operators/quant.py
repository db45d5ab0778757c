"""Quantitative queries where the data lies: statistics, spectra, moments, slices, peaks, noise."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

AXES = ("x", "y", "z")


def crop(voxels: DataFrame, box) -> DataFrame:
    x0, x1, y0, y1, z0, z1 = box
    return voxels.where(f"x >= {x0} and x < {x1} and y >= {y0} and y < {y1} and z >= {z0} and z < {z1}")


def stats(voxels: DataFrame, box=None) -> DataFrame:
    v = crop(voxels, box) if box else voxels
    return v.agg(F.count("*").alias("n"), F.sum("v").alias("total"), F.min("v").alias("lo"), F.max("v").alias("hi"), F.round(F.avg("v"), 4).alias("mean"), F.round(F.stddev_pop("v"), 3).alias("spread"))


def histogram(voxels: DataFrame, lo: int, hi: int, bins: int = 32) -> DataFrame:
    b = F.expr(f"least({bins - 1}, int((v - {lo}) * {bins} div {max(1, hi - lo)}))")
    return voxels.groupBy(b.alias("bin")).agg(F.count("*").alias("n"))


def spectrum(voxels: DataFrame, x: int, y: int, r: int = 0) -> DataFrame:
    """z, total, n in an aperture of side 2 r + 1."""
    return voxels.where(f"x between {x - r} and {x + r} and y between {y - r} and {y + r}").groupBy("z").agg(F.sum("v").alias("total"), F.count("*").alias("n"))


def moments(voxels: DataFrame, lo: int, hi: int) -> DataFrame:
    """Moment 0, 1 and 2 maps over [lo, hi) of z, from integer sums."""
    g = voxels.where(f"z >= {lo} and z < {hi}").groupBy("x", "y").agg(F.sum("v").alias("m0"), F.sum(F.col("v") * F.col("z")).alias("s1"), F.sum(F.col("v") * F.col("z") * F.col("z")).alias("s2"))
    mean = F.col("s1") / F.nullif("m0", F.lit(0))
    return g.select("x", "y", "m0", F.round(mean, 6).alias("m1"), F.round(F.sqrt(F.greatest(F.lit(0.0), F.col("s2") / F.nullif("m0", F.lit(0)) - mean * mean)), 5).alias("m2"))


def slice_(voxels: DataFrame, axis: str, k: int) -> DataFrame:
    a, b = [c for c in AXES if c != axis]
    return voxels.where(F.col(axis) == k).select(F.col(a).alias("u"), F.col(b).alias("w"), "v")


def argmip(voxels: DataFrame, axis: str = "z") -> DataFrame:
    """The voxel that makes each pixel of an axis-aligned projection; ties to the smallest depth."""
    a, b = [c for c in AXES if c != axis]
    return voxels.groupBy(F.col(a).alias("u"), F.col(b).alias("w")).agg(F.max("v").alias("val"), F.max_by(axis, F.struct("v", -F.col(axis))).alias("depth"))


def peaks(voxels: DataFrame, least: int) -> DataFrame:
    """Voxels of at least ``least`` above all of their 26 neighbours; absent neighbours are 0."""
    near = voxels
    for a in AXES:
        near = near.withColumn(a, F.explode(F.array(F.col(a) - 1, F.col(a), F.col(a) + 1)))
    best = near.groupBy(*AXES).agg(F.max("v").alias("top"), F.count("*").alias("n"))
    same = near.select(*AXES, F.col("v").alias("nv"))
    ties = voxels.join(same, list(AXES)).where("nv = v").groupBy(*AXES).agg(F.count("*").alias("ties"))
    return voxels.where(F.col("v") >= least).join(best, list(AXES)).where("v = top").join(ties, list(AXES)).where("ties = 1").select(*AXES, "v")


def sigma_clip(voxels: DataFrame, k: int = 3, rounds: int = 3) -> DataFrame:
    """Noise by iterated clipping, all rounds in one plan; each round's limits are one broadcast row. round, n, mean, spread."""
    out, now = None, voxels.select("v")
    for i in range(rounds):
        s = now.agg(F.count("*").alias("n"), F.avg("v").alias("mean"), F.stddev_pop("v").alias("spread"))
        row = s.select(F.lit(i).alias("round"), "n", F.round("mean", 3).alias("mean"), F.round("spread", 2).alias("spread"))
        out = row if out is None else out.unionByName(row)
        now = now.crossJoin(F.broadcast(s.select((F.col("mean") - k * F.col("spread")).alias("a"), (F.col("mean") + k * F.col("spread")).alias("b")))).where("v between a and b").select("v")
    return out


def regrid(levels: list[tuple[DataFrame, int]]) -> DataFrame:
    """One grid of the finest level from mixed resolutions: (voxels, factor to the finest); the finest wins."""
    from .cube import upscale

    parts = None
    for voxels, k in levels:
        p = upscale(voxels, k).withColumn("level", F.lit(-k))
        parts = p if parts is None else parts.unionByName(p)
    return parts.groupBy(*AXES).agg(F.max_by("v", "level").alias("v"))


def progressive(voxels: DataFrame) -> DataFrame:
    """Running maximum along z."""
    w = Window.partitionBy("x", "y").orderBy("z").rowsBetween(Window.unboundedPreceding, 0)
    return voxels.withColumn("running", F.max("v").over(w))
