"""Measures: timing, scaling, communication, accuracy."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def median_runs(runs: DataFrame) -> DataFrame:
    """Median over runs of each cube and angle."""
    return runs.groupBy("cube", "angle").agg(F.median("ms").alias("ms"))


def p75(medians: DataFrame) -> DataFrame:
    """Upper quartile over angles: the frame time of a cube."""
    return medians.groupBy("cube").agg(F.percentile("ms", F.lit(0.75)).alias("ms"))


def fps(times: DataFrame) -> DataFrame:
    return times.withColumn("fps", F.try_divide(F.lit(1000.0), F.col("ms")))


def total_model(stages: DataFrame, key: str = "frame") -> DataFrame:
    """Bounds of the total from stage times: no more than their sum, no less than the largest."""
    return stages.groupBy(key).agg(F.sum("ms").alias("upper"), F.max("ms").alias("lower"))


def stage_share(stages: DataFrame) -> DataFrame:
    total = F.sum(F.sum("ms")).over(Window.partitionBy())
    return stages.groupBy("stage").agg(F.sum("ms").alias("ms"), (F.sum("ms") / total).alias("share"))


def speedup(times: DataFrame) -> DataFrame:
    """cube, nodes, ms -> speed-up and efficiency against the fewest nodes."""
    w = Window.partitionBy("cube").orderBy("nodes")
    base, n0 = F.first("ms").over(w), F.first("nodes").over(w)
    s = base / F.col("ms")
    return times.select("cube", "nodes", "ms", s.alias("speedup"), (s * n0 / F.col("nodes")).alias("efficiency"))


def critical_point(times: DataFrame, tol: float = 0.02) -> DataFrame:
    """First node count past which the time stays or rises; null if it keeps falling."""
    w = Window.partitionBy("cube").orderBy("nodes")
    t = times.withColumn("next", F.lead("ms").over(w))
    return t.groupBy("cube").agg(F.min(F.when(F.col("next") >= F.col("ms") * F.lit(1 - tol), F.col("nodes"))).alias("critical_nodes"))


def ratio(times: DataFrame, by: str, small, large, keys: list[str]) -> DataFrame:
    """ms at ``large`` over ms at ``small``."""
    g = times.groupBy(*keys).agg(F.max(F.when(F.col(by) == large, F.col("ms"))).alias("b"), F.max(F.when(F.col(by) == small, F.col("ms"))).alias("a"))
    return g.select(*keys, (F.col("b") / F.col("a")).alias("ratio"))


def reduction(pairs: DataFrame) -> DataFrame:
    """Mean, least and most of 1 - b / a."""
    r = 1 - F.col("b") / F.nullif("a", F.lit(0.0))
    return pairs.agg(F.avg(r).alias("mean"), F.min(r).alias("least"), F.max(r).alias("most"))


def image_error(a: DataFrame, b: DataFrame, peak: Column | None = None) -> DataFrame:
    """Pixels that differ, mean and largest absolute error, PSNR; absent pixels are 0."""
    j = a.select("u", "v", F.col("val").alias("a")).join(b.select("u", "v", F.col("val").alias("b")), ["u", "v"], "full_outer").select(F.coalesce("a", F.lit(0)).alias("a"), F.coalesce("b", F.lit(0)).alias("b"))
    d = F.abs(F.col("a") - F.col("b"))
    g = j.agg(F.count_if(d > 0).alias("differ"), F.avg(d).alias("mae"), F.max(d).alias("maxabs"), F.avg(d.cast("double") * d.cast("double")).alias("mse"), F.max("a").alias("peak"))
    psnr = F.when(F.col("mse") > 0, 10 * F.log10(F.col("peak").cast("double") * F.col("peak") / F.col("mse")))
    return g.select("differ", F.round("mae", 4).alias("mae"), "maxabs", F.round(psnr, 6).alias("psnr"))


def coverage(exact: DataFrame, other: DataFrame) -> DataFrame:
    """Voxels crossed per ray, and how many of them another sampling misses."""
    keys = ["u", "v", "x", "y", "z"]
    a, b = exact.select(*keys).distinct(), other.select(*keys).distinct()
    missed = a.join(b, keys, "left_anti").agg(F.count("*").alias("missed"))
    return a.agg(F.count("*").alias("crossed")).crossJoin(missed).withColumn("share", F.round(F.col("missed") / F.nullif("crossed", F.lit(0)), 6))
