"""Tables to voxels: deposits, scaling, synthetic cubes, ranges. Voxels are (x, y, z, v) in BIGINT; absent means 0."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.spec import VEC, CubeSpec

AXES = ("x", "y", "z")


def build(rows: DataFrame, x: Column, y: Column, z: Column, value: Column | None = None, agg: str = "sum") -> DataFrame:
    """Nearest-cell deposit: one partial and one final aggregation around a single exchange. agg: sum, count, max or min."""
    measure = {"sum": F.sum, "max": F.max, "min": F.min}[agg]("v") if agg != "count" else F.count("*")
    picked = rows.select(x.cast("long").alias("x"), y.cast("long").alias("y"), z.cast("long").alias("z"), *([value.alias("v")] if value is not None else []))
    return picked.groupBy(*AXES).agg(measure.cast("long").alias("v"))


def cents(column: str) -> Column:
    return F.round(F.col(column) * F.lit(100.0)).cast("long")


def cloud(rows: DataFrame, coordinates: list[Column], spec: CubeSpec, mass: Column | None = None, bits: int = 8, edge: str = "clamp") -> DataFrame:
    """Cloud-in-cell deposit. coordinates: grid units as DOUBLE. A particle spreads over the eight cells that a unit box around it
    overlaps; weights are fixed point, 2^bits an axis, so the eight products sum to exactly 2^(3 bits)."""
    one = 1 << bits
    picked = rows
    names = []
    for axis, (c, n) in enumerate(zip(coordinates, spec.dims, strict=True)):
        q = F.floor(c * F.lit(float(one)) + F.lit(0.5)).cast("long") - one // 2  # distance from the first cell centre, fixed point
        cell, part = F.floor(q / F.lit(one)).cast("long"), F.pmod(q, F.lit(one))
        low, high = (F.greatest(F.least(cell + k, F.lit(n - 1)), F.lit(0)) if edge == "clamp" else F.pmod(cell + k, F.lit(n)) for k in (0, 1))
        name = f"__a{axis}"
        names.append(name)
        picked = picked.withColumn(name, F.array(F.struct(low.alias("i"), (F.lit(one) - part).alias("w")), F.struct(high.alias("i"), part.alias("w"))))
    mass = mass if mass is not None else F.lit(1)
    corners = [F.struct(*[F.col(n)[c >> i & 1]["i"].alias(a) for i, (n, a) in enumerate(zip(names, AXES, strict=True))], (mass * F.col(names[0])[c & 1]["w"] * F.col(names[1])[c >> 1 & 1]["w"] * F.col(names[2])[c >> 2 & 1]["w"]).alias("w")) for c in range(8)]
    spread = picked.select(F.explode(F.array(*corners)).alias("p")).select("p.*").where("w <> 0")
    return spread.groupBy(*AXES).agg(F.sum("w").cast("long").alias("v"))


def upscale(voxels: DataFrame, k: int) -> DataFrame:
    """Each voxel k times along each axis."""
    out = voxels
    for a in AXES:
        out = out.withColumn(a, F.explode(F.sequence(F.col(a) * k, F.col(a) * k + k - 1)))
    return out.select(*AXES, "v")


def target_grid(spark: SparkSession, dims) -> DataFrame:
    nx, ny, nz = dims
    return spark.range(nx * ny * nz).select((F.col("id") % nx).alias("x"), (F.expr(f"id div {nx}") % ny).alias("y"), F.expr(f"id div {nx * ny}").alias("z"))


def resample(voxels: DataFrame, source: CubeSpec, dims, mode: str = "nearest") -> DataFrame:
    """A cube of other dimensions. nearest: the cell under the new centre. trilinear: the eight cells around it, borders repeated, rounded."""
    spark = voxels.sparkSession
    grid = target_grid(spark, dims)
    if mode == "nearest":
        at = [F.expr(f"((2 * {a} + 1) * {n}) div {2 * m}") for a, n, m in zip(AXES, source.dims, dims, strict=True)]
        g = grid.select(*AXES, *[c.alias(f"s{a}") for c, a in zip(at, AXES, strict=True)])
        v = voxels.select(*[F.col(a).alias(f"s{a}") for a in AXES], "v")
        return g.join(v, ["sx", "sy", "sz"]).select(*AXES, "v")
    # positions in 1 / (2 m) cells: (2 i + 1) n - m, exact integers
    g = grid
    for a, n, m in zip(AXES, source.dims, dims, strict=True):
        p = (2 * F.col(a) + 1) * n - m
        low = F.floor(p / F.lit(2 * m)).cast("long")
        g = g.withColumn(f"__{a}", F.array(*[F.struct(F.greatest(F.lit(0), F.least(F.lit(n - 1), low + k)).alias("i"), (F.pmod(p, F.lit(2 * m)) if k else 2 * m - F.pmod(p, F.lit(2 * m))).alias("w")) for k in (0, 1)]))
    corners = [F.struct(*[F.col(f"__{a}")[c >> i & 1]["i"].alias(f"s{a}") for i, a in enumerate(AXES)], (F.col("__x")[c & 1]["w"] * F.col("__y")[c >> 1 & 1]["w"] * F.col("__z")[c >> 2 & 1]["w"]).alias("w")) for c in range(8)]
    wide = g.select(*AXES, F.explode(F.array(*corners)).alias("p")).select(*AXES, "p.*")
    v = voxels.select(*[F.col(a).alias(f"s{a}") for a in AXES], "v")
    whole = 8 * dims[0] * dims[1] * dims[2]
    total = wide.join(v, ["sx", "sy", "sz"]).groupBy(*AXES).agg(F.sum(F.col("w").cast("decimal(20,0)") * F.col("v")).alias("t"))
    return total.select(*AXES, F.floor(F.col("t") / F.lit(whole) + F.lit(0.5).cast("decimal(2,1)")).cast("long").alias("v")).where("v <> 0")


def synth(spark: SparkSession, dims) -> DataFrame:
    """A procedural cube of any size, all in generated code: a hash-like integer pattern with ridges."""
    g = target_grid(spark, dims)
    return g.withColumn("v", (F.col("x") * 73 + F.col("y") * 19 + F.col("z") * 31) % 1009 + F.when((F.col("x") + F.col("y") + F.col("z")) % 17 == 0, 1000).otherwise(0))


def minmax(assigned: DataFrame) -> DataFrame:
    """Local range of each brick."""
    return assigned.groupBy("brick").agg(F.min("v").alias("lo"), F.max("v").alias("hi"))


def global_range(local: DataFrame) -> DataFrame:
    return local.agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"))


# The stand-in cubes


def placed(spark: SparkSession, sf_dir: str, dims) -> tuple[DataFrame, list[Column]]:
    """Line items, and their cells in a survey cube of some size: part, supplier, ship day."""
    rows = spark.read.parquet(f"{sf_dir}/lineitem.parquet").select("l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice")
    top = rows.agg((F.max("l_partkey") + 1).alias("px"), (F.max("l_suppkey") + 1).alias("sx"))
    day = F.datediff("l_shipdate", F.lit("1995-01-01").cast("date"))
    return rows.crossJoin(F.broadcast(top)), [F.expr(f"l_partkey * {dims[0]} div px"), F.expr(f"l_suppkey * {dims[1]} div sx"), F.floor(day * dims[2] / 2520)]


def survey(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, cell = placed(spark, sf_dir, (40, 40, 18))
    return build(rows, *cell, cents("l_extendedprice"))


def survey_points(spark: SparkSession, sf_dir: str, dims) -> DataFrame:
    """x, y, z of each line item in a survey cube of some size, for which voxels would be about as many as the line items."""
    rows, cell = placed(spark, sf_dir, dims)
    return rows.select(*[c.cast("long").alias(a) for a, c in zip(AXES, cell, strict=True)])


def wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = spark.read.parquet(f"{sf_dir}/events.parquet").select("user_id", "ts", "value")
    top = rows.agg((F.max("user_id") + 1).alias("ux"))
    minute = F.hour("ts") * 60 + F.minute("ts")
    return build(rows.crossJoin(F.broadcast(top)), F.expr("user_id * 27 div ux"), F.floor(minute * 27 / 1440), F.floor((F.dayofmonth("ts") - 1) * 16 / 30), cents("value"))


def particle_coordinates(rows: DataFrame, n: int = 32) -> list[Column]:
    """Quantity over [1, 50], price over [0, 105000], ship day over [0, 2520), in grid units."""
    day = F.datediff("l_shipdate", F.lit("1995-01-01").cast("date")).cast("double")
    return [(F.col("l_quantity") - 1.0) * float(n) / 49.0, F.col("l_extendedprice") * float(n) / 105000.0, day * float(n) / 2520.0]


def particle(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = spark.read.parquet(f"{sf_dir}/lineitem.parquet").select("l_quantity", "l_extendedprice", "l_shipdate")
    return cloud(rows, particle_coordinates(rows), CubeSpec("particle", (32, 32, 32)))


def survey_scaled(spark: SparkSession, sf_dir: str) -> DataFrame:
    return upscale(survey(spark, sf_dir), 2)


def particle_scaled(spark: SparkSession, sf_dir: str, mode: str = "nearest") -> DataFrame:
    return resample(particle(spark, sf_dir), CubeSpec("particle", (32, 32, 32)), (81, 81, 81), mode)


def vec(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vectors as particles: their first three components in grid units."""
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("embedding")
    return cloud(rows, [(F.col("embedding")[i].cast("double") + 1.0) * 16.0 for i in range(3)], VEC)


BUILDERS = {"vec": vec, "survey": survey, "wide": wide, "particle": particle, "survey_scaled": survey_scaled, "particle_scaled": particle_scaled}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return BUILDERS[name](spark, sf_dir)
