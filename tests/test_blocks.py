"""Blocks of the array executor: odd values, borders, ghost layers, transfers, pruned scans, the planner."""

import math

import pytest
from pyspark.sql import functions as F

from cubecast.operators import array_engine, composite, cube, measure, partition, render
from cubecast.plans import planner
from cubecast.plans.kd import kd, two_level
from cubecast.plans.spec import SURVEY, CubeSpec, ViewSpec
from cubecast.sources import store

SPEC = CubeSpec("odd", (7, 6, 5))
SHOT = ViewSpec(30, 24, 24)


def rows(df):
    return sorted(tuple(r) for r in df.collect())


@pytest.fixture(scope="module")
def odd(spark):
    """Negative, zero, absent and null voxels."""
    grid = cube.target_grid(spark, SPEC.dims).withColumn("v", (F.col("x") * 31 + F.col("y") * 17 + F.col("z") * 7) % 23 - 11)
    v = grid.where("(x + y + z) % 4 <> 0").withColumn("v", F.when(F.col("x") == 3, F.lit(None)).otherwise(F.col("v"))).persist()
    yield v
    v.unpersist()


@pytest.mark.parametrize("block", [2, 64])
@pytest.mark.parametrize("dtype", ["<i8", "<i4", "<f4"])
def test_odd_values_equal_the_relational_executor(spark, odd, block, dtype):
    plan = kd(SPEC.dims, 3)
    want = rows(render.frame(odd.where("v is not null"), SPEC, SHOT, plan))
    got = array_engine.cast(array_engine.pack_bricks(odd, plan, dtype=dtype, block=block), SPEC, [SHOT])
    assert rows(composite.final(got).select("u", "v", F.col("val").cast("long"))) == want
    nodes = composite.node(got.withColumn("node", F.lit(0)))
    assert min(v for _, _, v in want) < 0 and nodes.count() == len(want)


@pytest.mark.parametrize("shot", [SHOT, ViewSpec(0, 16, 16), ViewSpec(210, 16, 16), ViewSpec(30, 24, 24, distance=0.9)])
def test_interpolation_needs_its_ghosts_and_equals_the_relational_one(spark, odd, shot):
    v = odd.where("v is not null")
    r = render.uniform_mids(render.brick_rays(SPEC, shot, kd(SPEC.dims, 1), spark), "unit")
    want = rows(render.trilinear(r, v, SPEC).groupBy("u", "v").agg(F.round(F.max("value"), 6)))
    for n, block in ((1, 64), (5, 2)):
        # blocks without a voxel of their own are not stored: fill them, as absent counts as zero here
        filled = cube.target_grid(spark, SPEC.dims).join(v, ["x", "y", "z"], "left").withColumn("v", F.coalesce("v", F.lit(0)))
        blocks = array_engine.pack_bricks(filled, kd(SPEC.dims, n), ghost=1, block=block)
        got = array_engine.cast(blocks, SPEC, [shot], mode="uniform", rule="unit", interpolate=True).groupBy("u", "v").agg(F.round(F.max("val"), 6))
        assert rows(got) == want
    with pytest.raises(Exception, match="ghost"):
        array_engine.cast(array_engine.pack_bricks(v, kd(SPEC.dims, 1)), SPEC, [shot], interpolate=True).count()


def test_alpha_segments_merge_in_any_cut(spark, odd):
    v = odd.where("v is not null")
    s = render.table_values(render.nearest(render.samples(render.exact_mids(render.brick_rays(SPEC, SHOT, kd(SPEC.dims, 1), spark))), v.withColumn("v", F.col("v") + 11)), 0, 22)
    want = render.alpha(s).select("u", "v", F.round("c", 9).alias("c"), F.round("a", 9).alias("a"))
    for n, block in ((1, 64), (4, 2)):
        parts = array_engine.cast(array_engine.pack_bricks(v.withColumn("v", F.col("v") + 11), kd(SPEC.dims, n), block=block), SPEC, [SHOT], transfer="alpha", table=(0, 22))
        got = render.merge_alpha(parts).select("u", "v", F.round("c", 9).alias("c"), F.round("a", 9).alias("a"))
        assert rows(got) == rows(want)


def test_values_and_bricks_that_do_not_fit_fail_before_wrong_pixels(spark):
    v = spark.createDataFrame([(0, 0, 0, 2**40)], "x long, y long, z long, v long")
    with pytest.raises(Exception, match="fit"):
        array_engine.pack_bricks(v, kd((2, 2, 2), 1), dtype="<i4").count()
    with pytest.raises(ValueError):
        array_engine.pack_bricks(v, kd((1024, 1024, 1024), 2), memory=1 << 30)
    parts = spark.createDataFrame([(0, 1, 1, 2**40)], "node int, u int, v int, val long")
    with pytest.raises(Exception, match="four bytes"):
        composite.pack(parts, spark.createDataFrame([(0, 0, 4, 0, 4)], "node int, u0 int, u1 int, v0 int, v1 int")).count()


def test_skipping_and_pruning_reach_the_scan(spark, sf, tmp_path):
    plan = kd(SURVEY.dims, 64)
    path = str(tmp_path / "blocks")
    store.write_blocks(array_engine.pack_bricks(cube.survey(spark, sf), plan), path)
    text = array_engine.skip_empty(store.read_bricks(spark, path), 5.0)._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThan(hi,5.0)" in text
    close = ViewSpec(30, zoom=6.0)
    seen = array_engine.seen_bricks(plan, SURVEY, [close])
    assert 0 < len(seen) < 64
    text = store.read_bricks(spark, path, seen)._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [brick_group" in text
    some = array_engine.cast(store.read_bricks(spark, path, seen), SURVEY, [close])
    assert rows(composite.final(some)) == rows(composite.final(array_engine.cast(store.read_bricks(spark, path), SURVEY, [close])))


def test_large_plans_keep_their_driver_table_small(spark):
    plan = two_level((5004, 5002, 2186), [5, 1, 9, 2] * 32)
    assert len(plan) > 64
    subtrees, _ = partition.crown(plan.tree, partition.INLINE_LEAVES)
    assert len(subtrees) <= partition.INLINE_LEAVES and sorted(b for t in subtrees for b in partition.leaves_of(t)) == list(range(len(plan)))
    v = spark.range(3000).selectExpr("id * 1667 % 5004 x", "id * 911 % 5002 y", "id * 577 % 2186 z", "id v")
    own = rows(partition.assign(v, plan).select("v", "brick"))
    assert own == rows(partition.assign_range(v, plan.frame(spark)).select("v", "brick"))


def test_planner_picks_and_explains():
    plan = kd(SURVEY.dims, 8)
    assert planner.plan_render(SURVEY, ViewSpec(90), plan).executor == "object_order"
    assert planner.plan_render(SURVEY, ViewSpec(30), plan).executor == "relational"
    big = CubeSpec("big", (5004, 5002, 2186))
    assert planner.plan_render(big, ViewSpec(30, 1024, 1024), kd(big.dims, 128)).executor == "array"
    assert planner.plan_render(SURVEY, ViewSpec(90), plan, interpolate=True).executor == "relational"
    assert "scan: 8 bricks" in planner.explain_render(SURVEY, ViewSpec(30), plan)


def test_wide_messages_keep_values_of_eight_bytes(spark):
    vals = [2**40, -(2**40), 2**31, -(2**31), 2**32 + 2**31, 0, 7, 2**40 + 2**32]
    parts = spark.createDataFrame([(0, i // 4, i % 4, x) for i, x in enumerate(vals)], "node int, u int, v int, val long")
    packed = composite.pack(parts, spark.createDataFrame([(0, 0, 4, 0, 4)], "node int, u0 int, u1 int, v0 int, v1 int"), True)
    want = rows(parts)
    assert rows(composite.unpack(packed)) == want
    for kind in ("zlib", "sparse", "rle"):
        assert rows(composite.unpack(composite.decoded(composite.encoded(packed, kind), kind))) == want
    cost = {r.kind: (r.raw, r.bytes) for r in composite.encoding_cost(packed, repeat=1).collect()}
    assert cost["sparse"] == (64, 4 + 8 * len(vals)) and cost["rle"] == (64, 4 + 8 * (len(vals) + 1))
    two = composite.pack(parts, spark.createDataFrame([(0, 0, 4, 0, 4), (1, 0, 2, 0, 2)], "node int, u0 int, u1 int, v0 int, v1 int"), True)
    assert rows(two.select("node", F.length("data"))) == [(0, 64), (1, 16)] and rows(composite.unpack(two)) == want


def test_image_error_of_large_values(spark):
    a, b = (spark.createDataFrame([(0, 0, x)], "u int, v int, val long") for x in (2**40, 2**38))
    assert measure.image_error(a, b).first()["psnr"] == pytest.approx(10 * math.log10(2.0**80 / (2.0**40 - 2.0**38) ** 2))
