"""Partition plans from metadata alone: k-d trees, forests, two levels, slabs, and plans weighted by counts."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .spec import Box

AXES = "xyz"


@dataclass(frozen=True)
class Brick:
    brick: int
    node: int
    gpu: int
    box: Box

    @property
    def volume(self) -> int:
        x0, x1, y0, y1, z0, z1 = self.box
        return (x1 - x0) * (y1 - y0) * (z1 - z0)


@dataclass(frozen=True)
class KdPlan:
    """Bricks that tile a cube, and the cuts that made them (axis, place, below, above), for assignment without a join."""

    bricks: tuple[Brick, ...]
    tree: tuple | int

    def __len__(self) -> int:
        return len(self.bricks)

    def frame(self, spark: SparkSession) -> DataFrame:
        """One row a brick; grows with workers, not with data."""
        return spark.createDataFrame(
            [(b.brick, b.node, b.gpu, *b.box) for b in self.bricks], "brick int, node int, gpu int, x0 int, x1 int, y0 int, y1 int, z0 int, z1 int"
        )


def below(n: int) -> int:
    """Leaves of the first tree: the largest power of two under n; for powers of two, half."""
    return 1 << ((n - 1).bit_length() - 1)


def extents(box: Box) -> tuple[int, int, int]:
    return tuple(box[2 * i + 1] - box[2 * i] for i in range(3))


def longest(box: Box) -> int:
    size = extents(box)
    return size.index(max(size))


def halves(box: Box, axis: int, at: int) -> tuple[Box, Box]:
    lower, upper = list(box), list(box)
    lower[2 * axis + 1] = upper[2 * axis] = at
    return tuple(lower), tuple(upper)


def even_cut(box: Box, axis: int, left: int, n: int) -> int:
    """The place that gives the lower side its share of the volume, rounded half up."""
    lo, extent = box[2 * axis], extents(box)[axis]
    return lo + (2 * extent * left + n) // (2 * n)


def grow(box: Box, n: int, cut: Callable = even_cut, axis_of: Callable = longest, start: int = 0):
    """(tree, boxes) of n leaves."""
    if n == 1:
        return start, [box]
    axis, left = axis_of(box), below(n)
    at = cut(box, axis, left, n)
    first, second = halves(box, axis, at)
    tree_a, boxes_a = grow(first, left, cut, axis_of, start)
    tree_b, boxes_b = grow(second, n - left, cut, axis_of, start + left)
    return (axis, at, tree_a, tree_b), boxes_a + boxes_b


def plan_of(tree, boxes: list[Box], gpus: int = 1) -> KdPlan:
    return KdPlan(tuple(Brick(i, i // gpus, i % gpus, b) for i, b in enumerate(boxes)), tree)


def kd(dims, n: int) -> KdPlan:
    """n leaves by halving the longest axis (x before y before z); other counts than powers of two make a forest whose roots are cut at the ratio of leaves."""
    if n < 1:
        raise ValueError("at least one brick is needed")
    return plan_of(*grow((0, dims[0], 0, dims[1], 0, dims[2]), n))


kd_forest = kd


def two_level(dims, gpus: list[int]) -> KdPlan:
    """A leaf for each node, cut at the ratio of its GPUs, then one brick for each GPU of the node."""
    whole = (0, dims[0], 0, dims[1], 0, dims[2])
    bricks: list[Brick] = []

    def nodes(box, first, count):
        if count == 1:
            start = len(bricks)
            tree, boxes = grow(box, gpus[first], start=start)
            bricks.extend([Brick(start + g, first, g, b) for g, b in enumerate(boxes)])
            return tree
        left = below(count)
        mine, all_ = sum(gpus[first : first + left]), sum(gpus[first : first + count])
        axis = longest(box)
        at = even_cut(box, axis, mine, all_)
        lower, upper = halves(box, axis, at)
        tree_a = nodes(lower, first, left)
        return (axis, at, tree_a, nodes(upper, first + left, count - left))

    tree = nodes(whole, 0, len(gpus))
    return KdPlan(tuple(bricks), tree)


def slab(dims, n: int, axis: int = 2) -> KdPlan:
    """n slices along one axis."""
    return plan_of(*grow((0, dims[0], 0, dims[1], 0, dims[2]), n, axis_of=lambda box: axis))


def planes(voxels: DataFrame, weight: str | None = None) -> dict[int, dict[int, int]]:
    """Weight of each plane of each axis: as many numbers as the cube has planes."""
    w = F.col(weight) if weight else F.lit(1)
    found: dict[int, dict[int, int]] = {0: {}, 1: {}, 2: {}}
    rows = voxels.groupBy(F.explode(F.array(*[F.struct(F.lit(i).alias("axis"), F.col(a).alias("at")) for i, a in enumerate(AXES)])).alias("p")).agg(F.sum(w).alias("w")).collect()
    for r in rows:
        found[r["p"]["axis"]][r["p"]["at"]] = r["w"]
    return found


def weighted(voxels: DataFrame, dims, n: int, weight: str | None = None) -> KdPlan:
    """Cuts that give each side its share of occupied voxels (or of a weight), from the plane sums of each box; one aggregation a level."""
    boxes: list[tuple[Box, int, list]] = [((0, dims[0], 0, dims[1], 0, dims[2]), n, [])]
    cuts: dict[tuple, tuple[int, int]] = {}
    while any(k > 1 for _, k, _ in boxes):
        condition = F.lit(None).cast("int")
        for i, (b, k, _) in enumerate(boxes):
            if k > 1:
                inside = (F.col("x") >= b[0]) & (F.col("x") < b[1]) & (F.col("y") >= b[2]) & (F.col("y") < b[3]) & (F.col("z") >= b[4]) & (F.col("z") < b[5])
                condition = F.when(inside, F.lit(i)).otherwise(condition)
        axes = [longest(b) for b, _, _ in boxes]
        place = F.element_at(F.array(*[F.lit(a) for a in axes]), condition + 1)
        at = F.when(place == 0, F.col("x")).when(place == 1, F.col("y")).otherwise(F.col("z"))
        w = F.col(weight) if weight else F.lit(1)
        rows = voxels.select(condition.alias("b"), at.alias("at"), w.alias("w")).where("b is not null").groupBy("b", "at").agg(F.sum("w").alias("w")).collect()
        sums: dict[int, dict[int, int]] = {}
        for r in rows:
            sums.setdefault(r["b"], {})[r["at"]] = r["w"]
        new = []
        for i, (b, k, path) in enumerate(boxes):
            if k == 1:
                new.append((b, k, path))
                continue
            left, axis = below(k), axes[i]
            total, run, cut = sum(sums.get(i, {}).values()), 0, None
            for p in range(b[2 * axis], b[2 * axis + 1] - 1):
                run += sums.get(i, {}).get(p, 0)
                if run * k >= total * left:
                    cut = p + 1
                    break
            cut = cut or even_cut(b, axis, left, k)
            cut = min(max(cut, b[2 * axis] + 1), b[2 * axis + 1] - 1) if extents(b)[axis] > 1 else cut
            cuts[tuple(path)] = (axis, cut)
            lower, upper = halves(b, axis, cut)
            new += [(lower, left, [*path, 0]), (upper, k - left, [*path, 1])]
        boxes = new
    leaves = {tuple(path): i for i, (_, _, path) in enumerate(boxes)}

    def tree(path=()):
        return leaves[path] if path in leaves else (*cuts[path], tree((*path, 0)), tree((*path, 1)))

    return plan_of(tree(), [b for b, _, _ in boxes])


def needed_bytes(dims, value_bytes: int = 4) -> int:
    return dims[0] * dims[1] * dims[2] * value_bytes


def min_nodes(dims, gpus_per_node: int, gpu_bytes: int, node_bytes: int, value_bytes: int = 4) -> int:
    """Fewest nodes whose memory, and whose GPUs' memory together, hold the cube."""
    need = needed_bytes(dims, value_bytes)
    return -(-need // min(node_bytes, gpus_per_node * gpu_bytes))


def check_fit(plan: KdPlan, gpu_bytes: int, value_bytes: int = 4) -> None:
    """Raises before any job if a brick outgrows its worker."""
    for b in plan.bricks:
        if b.volume * value_bytes > gpu_bytes:
            raise ValueError(f"brick {b.brick} needs {b.volume * value_bytes} bytes; its worker has {gpu_bytes}")
