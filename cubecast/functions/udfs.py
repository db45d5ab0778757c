"""Functions that Spark lacks: Morton order, interpolation weights, projection aggregates, ray and plan tables."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.kd import kd

LONG = T.LongType()


def morton(x: Column, y: Column, z: Column, bits: int = 10) -> Column:
    """Interleaved bits of three coordinates, in generated code."""
    out = F.lit(0).cast("long")
    for i in range(bits):
        for k, c in enumerate((x, y, z)):
            out = out.bitwiseOR(F.shiftleft(F.shiftright(c.cast("long"), i).bitwiseAND(F.lit(1).cast("long")), 3 * i + k))
    return out


def spread_bits(v: np.ndarray, bits: int = 10) -> np.ndarray:
    v = v.astype(np.int64)
    out = np.zeros_like(v)
    for i in range(bits):
        out |= (v >> i & 1) << (3 * i)
    return out


@F.udf(LONG)
def morton_row(x, y, z):
    """The same row by row: the slow form, kept to show and to test the difference."""
    out = 0
    for i in range(10):
        out |= (x >> i & 1) << (3 * i) | (y >> i & 1) << (3 * i + 1) | (z >> i & 1) << (3 * i + 2)
    return out


@F.pandas_udf(LONG)
def morton_pandas(x: pd.Series, y: pd.Series, z: pd.Series) -> pd.Series:
    return pd.Series(spread_bits(x.to_numpy()) | spread_bits(y.to_numpy()) << 1 | spread_bits(z.to_numpy()) << 2)


@F.arrow_udf(LONG)
def morton_arrow(x: pa.Array, y: pa.Array, z: pa.Array) -> pa.Array:
    return pa.array(spread_bits(x.to_numpy()) | spread_bits(y.to_numpy()) << 1 | spread_bits(z.to_numpy()) << 2)


@F.pandas_udf(LONG)
def mip_agg(v: pd.Series) -> int:
    """Projection as a grouped aggregate."""
    return int(v.max())


@F.udtf(returnType=T.StructType([*(T.StructField(c, T.IntegerType()) for c in "xyz"), T.StructField("t", T.DoubleType())]))
class RayVoxels:
    """Voxels that a ray crosses in a box [0, n), with the middle of each stretch."""

    def eval(self, ox: float, oy: float, oz: float, dx: float, dy: float, dz: float, nx: int, ny: int, nz: int):
        o, d, n = (ox, oy, oz), (dx, dy, dz), (nx, ny, nz)
        te, tx = -np.inf, np.inf
        for a in range(3):
            if d[a] == 0:
                if not 0 <= o[a] < n[a]:
                    return
                continue
            t = sorted(((0 - o[a]) / d[a], (n[a] - o[a]) / d[a]))
            te, tx = max(te, t[0]), min(tx, t[1])
        if not tx - te > 1e-9:
            return
        cuts = sorted({te, tx, *(t for a in range(3) if d[a] != 0 for t in ((k - o[a]) / d[a] for k in range(n[a] + 1)) if te < t < tx)})
        for a, b in zip(cuts[:-1], cuts[1:], strict=True):
            if b - a > 1e-9:
                m = (a + b) / 2
                yield (*(int(np.floor(o[i] + m * d[i])) for i in range(3)), float(m))


@F.udtf(returnType=T.StructType([T.StructField(c, T.IntegerType()) for c in ("brick", "x0", "x1", "y0", "y1", "z0", "z1")]))
class KdLeaves:
    def eval(self, nx: int, ny: int, nz: int, n: int):
        for b in kd((nx, ny, nz), n).bricks:
            yield (b.brick, *b.box)


def register(spark: SparkSession) -> None:
    """SQL names of the functions."""
    spark.udf.register("morton3", morton_row)
    spark.udtf.register("ray_voxels", RayVoxels)
    spark.udtf.register("kd_leaves", KdLeaves)


def frame_diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """Pixels of two frames side by side by cogrouped scan lines: v, differ, maxabs."""

    def line(key, left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        j = left.merge(right, on=["u", "v"], how="outer", suffixes=("_a", "_b")).fillna(0)
        d = (j["val_a"] - j["val_b"]).abs()
        return pd.DataFrame({"v": [key[0]], "differ": [int((d > 0).sum())], "maxabs": [int(d.max())]})

    return a.groupBy("v").cogroup(b.groupBy("v")).applyInPandas(line, "v int, differ long, maxabs long")
