"""Frames: golden values, invariants between executors, partitions and strategies, plan shapes."""

import pytest
from pyspark.sql import functions as F

from cubecast.operators import array_engine, composite, cube, partition, render, view
from cubecast.plans.kd import kd, slab, weighted
from cubecast.plans.spec import SURVEY, CubeSpec, ViewSpec

GOLDEN = "/root/testdata/sf0.01"
A30 = ViewSpec(30)


def rows(df):
    return sorted(tuple(r) for r in df.collect())


@pytest.fixture(scope="module")
def survey(spark, sf):
    v = cube.survey(spark, sf).persist()
    yield v
    v.unpersist()


def test_golden_cube_and_projection(spark):
    v = cube.survey(spark, GOLDEN).persist()
    n, total, lo, hi = v.agg(F.count("*"), F.sum("v"), F.min("v"), F.max("v")).first()
    assert (n, total, lo, hi) == (24870, 318325627163, 92581, 66191316)
    assert v.groupBy("x", "y").agg(F.max("v").alias("m")).agg(F.count("*"), F.sum("m")).first()[:] == (1600, 48498325956)
    f = render.frame(v, SURVEY, A30)
    assert f.agg(F.count("*"), F.sum("val")).first()[:] == (2094, 63306809711)
    samples = render.exact_mids(render.brick_rays(SURVEY, A30, kd(SURVEY.dims, 5), spark)).agg(F.countDistinct("u", "v"), F.sum(F.size("mids"))).first()
    assert samples[:] == (2112, 46816)
    v.unpersist()


@pytest.mark.parametrize("n", [1, 6, 8])
def test_brick_count_changes_nothing(spark, survey, n):
    assert rows(render.frame(survey, SURVEY, A30, kd(SURVEY.dims, n))) == rows(render.frame(survey, SURVEY, A30, slab(SURVEY.dims, 3)))


def test_executors_and_strategies_agree(spark, survey):
    want = rows(render.frame(survey, SURVEY, A30))
    partials = array_engine.cast(array_engine.pack_bricks(survey, kd(SURVEY.dims, 8)), SURVEY, [A30]).persist()
    nodes = composite.node(partials)
    for got in (composite.final(partials), composite.final(nodes), composite.tree(nodes, 8, 3), composite.tiles(nodes, A30)):
        assert rows(got) == want
    stopped = array_engine.cast(array_engine.pack_bricks(survey, kd(SURVEY.dims, 8)), SURVEY, [A30], stop=survey.agg(F.max("v")).first()[0])
    assert rows(composite.final(stopped)) == want
    assert stopped.agg(F.sum("samples")).first()[0] <= partials.agg(F.sum("samples")).first()[0]


def test_perspective_executors_agree(spark, survey):
    near = ViewSpec(30, distance=0.9)
    a = rows(render.frame(survey, SURVEY, near))
    assert a and a == rows(composite.final(array_engine.cast(array_engine.pack_bricks(survey, kd(SURVEY.dims, 6)), SURVEY, [near])))


def test_messages_round_trip(spark, survey):
    plan = kd(SURVEY.dims, 8)
    nodes = composite.node(array_engine.cast(array_engine.pack_bricks(survey, plan), SURVEY, [A30]))
    packed = composite.pack(nodes, view.node_rects(view.rects(plan.frame(spark), A30, SURVEY)))
    want = rows(nodes)
    for kind in ("zlib", "sparse", "rle"):
        assert rows(composite.unpack(composite.decoded(composite.encoded(packed, kind), kind))) == want


def test_rectangles_lose_no_pixel(spark, survey):
    assert rows(render.frame(survey, SURVEY, A30, rectangles=False)) == rows(render.frame(survey, SURVEY, A30))


def test_trilinear_is_exact_on_linear_fields(spark):
    spec = CubeSpec("line", (8, 8, 8))
    field = cube.target_grid(spark, spec.dims).withColumn("v", F.col("x") * 8 + F.col("y") * 4 + F.col("z") * 2)
    r = render.uniform_mids(render.brick_rays(spec, ViewSpec(30), kd(spec.dims, 1), spark), "unit")
    t = render.trilinear(r, field, spec, ("u", "v", "ox", "oy", "oz", "dx", "dy", "dz"))
    p = {a: F.col(f"o{a}") + F.col("t") * F.col(f"d{a}") for a in "xyz"}
    inner = F.lit(True)
    for a in "xyz":
        inner = inner & (p[a] > 0.5) & (p[a] < 7.5)
    error = F.abs(F.col("value") - ((p["x"] - 0.5) * 8 + (p["y"] - 0.5) * 4 + (p["z"] - 0.5) * 2))
    assert t.where(inner).agg(F.max(error)).first()[0] < 1e-9


def test_alpha_over_bricks_equals_alpha_without(spark, survey):
    s = render.table_values(render.nearest(render.samples(render.exact_mids(render.brick_rays(SURVEY, A30, kd(SURVEY.dims, 8), spark))), survey), 0, 10_000_000)
    whole = render.alpha(s)
    parts = render.merge_alpha(render.alpha(s, ("brick", "u", "v")))
    d = whole.alias("a").join(parts.alias("b"), ["u", "v"]).agg(F.max(F.abs(F.col("a.c") - F.col("b.c"))), F.max(F.abs(F.col("a.a") - F.col("b.a")))).first()
    assert max(d) < 1e-9


def test_cloud_in_cell_conserves_mass(spark, sf):
    n = spark.read.parquet(f"{sf}/lineitem.parquet").count()
    assert cube.particle(spark, sf).agg(F.sum("v")).first()[0] == n << 24


def test_assignment_matches_range_join_and_halo_only_adds_ghosts(spark, survey):
    plan = kd(SURVEY.dims, 8)
    own = rows(partition.assign(survey, plan).select("x", "y", "z", "v", "brick"))
    assert own == rows(partition.assign_range(survey, plan.frame(spark)).select("x", "y", "z", "v", "brick"))
    assert own == rows(partition.halo(survey, plan).where(~F.col("ghost")).select("x", "y", "z", "v", "brick"))
    many = partition.assign(survey, kd(SURVEY.dims, 100))
    assert many.count() == survey.count()
    assert len(weighted(survey, SURVEY.dims, 8)) == 8


def test_plans_have_no_cartesian_product_and_merge_in_two_stages(spark, survey):
    text = render.frame(survey, SURVEY, A30)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in text and "partial_max" in text
    many = partition.assign(cube.synth(spark, SURVEY.dims), kd(SURVEY.dims, 100))._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in many and "BroadcastHashJoin" in many
    scan = cube.survey(spark, GOLDEN)._jdf.queryExecution().executedPlan().toString()
    assert "l_quantity" not in scan


def test_null_voxels_and_empty_cubes(spark):
    spec = CubeSpec("tiny", (2, 2, 2))
    v = spark.createDataFrame([(0, 0, 0, 5), (1, 1, 1, None)], "x long, y long, z long, v long")
    assert composite.final(array_engine.cast(array_engine.pack_bricks(v, kd(spec.dims, 2)), spec, [ViewSpec(0, 8, 8)])).agg(F.max("val")).first()[0] == 5
    assert render.frame(v.limit(0), spec, ViewSpec(0, 8, 8)).count() == 0
