"""Voxels to bricks: assignment, ghost layers, balance."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.kd import KdPlan

AXES = ("x", "y", "z")
#: Leaves up to which cuts become nested CASE expressions.
INLINE_LEAVES = 64


def tree_case(tree) -> Column:
    if isinstance(tree, int):
        return F.lit(tree)
    axis, at, low, high = tree
    return F.when(F.col(AXES[axis]) < at, tree_case(low)).otherwise(tree_case(high))


def crown(tree, leaves: int) -> tuple[list, object]:
    """The cuts of the first levels, down to at most ``leaves`` subtrees: (subtrees, tree over their numbers)."""
    subtrees = [tree]
    while True:
        wider = [x for t in subtrees for x in (t[2:] if not isinstance(t, int) else (t,))]
        if len(wider) > leaves or wider == subtrees:
            break
        subtrees = wider
    number = {id(t) if not isinstance(t, int) else t: i for i, t in enumerate(subtrees)}

    def top(t):
        key = id(t) if not isinstance(t, int) else t
        return number[key] if key in number else (t[0], t[1], top(t[2]), top(t[3]))

    return subtrees, top(tree)


def leaves_of(tree) -> list[int]:
    return [tree] if isinstance(tree, int) else leaves_of(tree[2]) + leaves_of(tree[3])


def assign(voxels: DataFrame, plan: KdPlan) -> DataFrame:
    """voxels with their brick. Small plans: comparisons in generated code. Larger ones: comparisons down to at most ``INLINE_LEAVES`` subtrees,
    then an equi-join with the subtree's bricks, one row a brick, and the box test as the rest; never a nested loop over all bricks."""
    if len(plan) <= INLINE_LEAVES:
        return voxels.withColumn("brick", tree_case(plan.tree))
    subtrees, top = crown(plan.tree, INLINE_LEAVES)
    rows = [(i, b, *plan.bricks[b].box) for i, t in enumerate(subtrees) for b in leaves_of(t)]
    table = voxels.sparkSession.createDataFrame(rows, "part int, brick int, x0 int, x1 int, y0 int, y1 int, z0 int, z1 int")
    keyed = voxels.withColumn("part", tree_case(top))
    return keyed.join(F.broadcast(table), "part").where("x >= x0 and x < x1 and y >= y0 and y < y1 and z >= z0 and z < z1").select(*voxels.columns, "brick")


def assign_range(voxels: DataFrame, bricks: DataFrame) -> DataFrame:
    """The plain rival: a range join of every voxel with every brick."""
    inside = "x >= x0 and x < x1 and y >= y0 and y < y1 and z >= z0 and z < z1"
    return voxels.join(F.broadcast(bricks), F.expr(inside)).select(*voxels.columns, "brick")


def halo(voxels: DataFrame, plan: KdPlan, width: int = 1) -> DataFrame:
    """Voxels of each brick and of the layer around it; ghost says whether the voxel is another brick's own."""
    spark = voxels.sparkSession
    bricks = plan.frame(spark)
    own = assign(voxels, plan).select(*AXES, "v", F.col("brick").alias("home"))
    near = bricks.alias("a").join(bricks.alias("b"), F.expr(" and ".join(f"a.{c}0 - {width} < b.{c}1 and b.{c}0 < a.{c}1 + {width}" for c in "xyz")))
    near = near.select(F.col("b.brick").alias("home"), F.col("a.brick").alias("brick"), *[F.col(f"a.{c}{i}").alias(f"{c}{i}") for c in "xyz" for i in (0, 1)])
    inside = " and ".join(f"{c} >= {c}0 - {width} and {c} < {c}1 + {width}" for c in "xyz")
    return own.join(F.broadcast(near), "home").where(inside).select("brick", *AXES, "v", (F.col("home") != F.col("brick")).alias("ghost"))


def held(voxels: DataFrame, *plans: KdPlan) -> DataFrame:
    """Bricks of plans (numbered from 0) shrunk to the boxes of the voxels in them, and n, how many they are; bricks without voxels drop.
    The voxels are read once for all plans, of at most ``INLINE_LEAVES`` bricks each."""
    at = F.explode(F.array(*[F.struct(F.lit(i).alias("plan"), tree_case(p.tree).alias("brick")) for i, p in enumerate(plans)]))
    own = voxels.select(*AXES, at.alias("at")).select(*AXES, "at.*").groupBy("plan", "brick")
    box = own.agg(*[c.cast("int").alias(f"{a}{i}") for a in AXES for i, c in enumerate((F.min(a), F.max(a) + 1))], F.count("*").alias("n"))
    nodes = voxels.sparkSession.createDataFrame([(i, b.brick, b.node, b.gpu) for i, p in enumerate(plans) for b in p.bricks], "plan int, brick int, node int, gpu int")
    return nodes.join(box, ["plan", "brick"])


def loads(rows: DataFrame, plan: KdPlan) -> DataFrame:
    """n, the rows in each brick; 0 for those that hold none."""
    n = assign(rows, plan).groupBy("brick").agg(F.count("*").alias("n"))
    return plan.frame(rows.sparkSession).join(n, "brick", "left").fillna(0, ["n"])


def quality(spark: SparkSession, plan: KdPlan, rows: DataFrame | None = None) -> DataFrame:
    """Balance and shape: largest to smallest volume, or number of ``rows`` in a brick, and largest side ratio."""
    volume = ((F.col("x1") - F.col("x0")) * (F.col("y1") - F.col("y0")) * (F.col("z1") - F.col("z0"))).cast("long")
    b = (plan.frame(spark) if rows is None else loads(rows, plan)).select(
        (volume if rows is None else F.col("n")).alias("volume"),
        F.greatest(*[F.col(f"{c}1") - F.col(f"{c}0") for c in "xyz"]).alias("long_side"),
        F.least(*[F.col(f"{c}1") - F.col(f"{c}0") for c in "xyz"]).alias("short_side"),
    )
    return b.agg(
        F.count("*").alias("bricks"),
        F.min("volume").alias("least"),
        F.max("volume").alias("most"),
        F.round(F.max("volume") / F.nullif(F.min("volume"), F.lit(0)), 6).alias("balance"),
        F.round(F.max(F.col("long_side") / F.col("short_side")), 6).alias("side_ratio"),
    )


def migrated(voxels: DataFrame, before: KdPlan, after: KdPlan) -> DataFrame:
    """Voxels that change owner between two plans."""
    a = assign(voxels, before).withColumnRenamed("brick", "old")
    return assign(a, after).withColumnRenamed("brick", "new").where("old <> new")
