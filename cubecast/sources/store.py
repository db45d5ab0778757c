"""Cubes on storage: long and brick form, specifications beside the data."""

from __future__ import annotations

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.spec import CubeSpec

VOXELS = "x long, y long, z long, v long"
GROUPS = 16


def write_spec(spark: SparkSession, spec: CubeSpec, path: str) -> None:
    spark.createDataFrame([(spec.to_json(),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/_spec_json")


def read_spec(spark: SparkSession, path: str) -> CubeSpec:
    """Dimensions without touching voxels."""
    return CubeSpec.from_json(spark.read.text(f"{path}/_spec_json").first()[0])


def write_blocks(blocks: DataFrame, path: str) -> None:
    """Block rows by brick group, sorted by their largest value, so that a filter on it skips row groups and one on bricks skips folders."""
    dealt = blocks.withColumn("brick_group", F.col("brick") % GROUPS).repartition("brick_group").sortWithinPartitions("brick_group", "hi")
    dealt.write.mode("overwrite").partitionBy("brick_group").parquet(path)


def read_bricks(spark: SparkSession, path: str, bricks: list[int] | None = None, schema: str | None = None) -> DataFrame:
    """Brick rows; a list of bricks prunes partitions and row groups."""
    reader = spark.read.schema(schema) if schema else spark.read
    df = reader.parquet(path)
    if bricks is None:
        return df
    groups = sorted({b % GROUPS for b in bricks})
    return df.where(F.col("brick_group").isin(groups) & F.col("brick").isin(bricks))


def pin(df: DataFrame) -> DataFrame:
    """In-core residence that spills instead of failing."""
    return df.persist(StorageLevel.MEMORY_AND_DISK)
