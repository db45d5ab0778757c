"""Colour mapping on the merged frame, with the cube's global range and a user's map."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Generated ramps: red, green and blue at both ends.
RAMPS = {"grey": ((0, 0, 0), (255, 255, 255)), "heat": ((0, 0, 0), (255, 160, 0)), "ice": ((0, 0, 40), (160, 220, 255))}


def table(spark: SparkSession, name: str = "heat", n: int = 16) -> DataFrame:
    (a, b), rows = RAMPS[name], []
    for i in range(n):
        rows.append((i, *(p + (q - p) * i // (n - 1) for p, q in zip(a, b, strict=True))))
    return spark.createDataFrame(rows, "bucket int, r int, g int, b int")


def bucket(value: Column, lo: Column, hi: Column, n: int, stretch: str = "linear") -> Column:
    """Bucket 0 if the range is empty; the last bucket holds the maximum."""
    if stretch == "linear":
        b = (value - lo) * n / F.nullif(hi - lo, F.lit(0))
        b = F.floor(b)
    else:
        f = {"sqrt": F.sqrt, "log": lambda x: F.log(x + 1)}[stretch]
        b = F.floor(F.round(f((value - lo).cast("double")) * n / F.nullif(f((hi - lo).cast("double")), F.lit(0.0)), 9))
    return F.coalesce(F.greatest(F.lit(0), F.least(F.lit(n - 1), b)), F.lit(0)).cast("int")


def ranks(frame: DataFrame, n: int = 16) -> DataFrame:
    """One row lo, hi, edges: the values at which n equal shares of the frame's pixels end; n - 1 numbers, whatever the frame."""
    shares = F.percentile("val", F.array(*[F.lit(i / n) for i in range(1, n)]))
    return frame.agg(F.min("val").alias("lo"), F.max("val").alias("hi"), shares.alias("edges"))


def apply_ranks(frame: DataFrame, cmap: str = "heat", n: int = 16) -> DataFrame:
    """u, v, val, bucket, r, g, b with the percentile stretch: a pixel's bucket is the number of shares that end at or below its value."""
    f = frame.crossJoin(F.broadcast(ranks(frame, n).select("edges")))
    f = f.withColumn("bucket", F.size(F.filter("edges", lambda e: e <= F.col("val")))).drop("edges")
    return f.join(F.broadcast(table(frame.sparkSession, cmap, n)), "bucket").select("u", "v", "val", "bucket", "r", "g", "b")


def apply(frame: DataFrame, limits: DataFrame, cmap: str = "heat", n: int = 16, stretch: str = "linear") -> DataFrame:
    """u, v, val, bucket, r, g, b. limits: one row lo, hi."""
    colours = table(frame.sparkSession, cmap, n)
    f = frame.crossJoin(F.broadcast(limits)).withColumn("bucket", bucket(F.col("val"), F.col("lo"), F.col("hi"), n, stretch)).drop("lo", "hi")
    return f.join(F.broadcast(colours), "bucket").select("u", "v", "val", "bucket", "r", "g", "b")
