"""Array executor: dense blocks, many rays at a time in NumPy. Samples never become rows.

A brick is stored as blocks, one row each: cells of a regular grid of ``BLOCK`` voxels a side, cut at the brick's faces, so a row
stays a few MB however large the brick is. Absent voxels hold a blank value, which no voxel has, so negative and zero
values are kept. A block may carry the layer of voxels around it, which interpolation at its faces needs.
Traversal is anchored at the ray and the whole cube, never at a block: results do not depend on bricks or blocks and
equal those of the relational executor.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.kd import KdPlan, check_fit
from ..plans.planner import rectangle
from ..plans.spec import CubeSpec, ViewSpec
from .partition import AXES, assign, halo

BLOCK = 64
BOX = ("x0", "x1", "y0", "y1", "z0", "z1")
BRICK = "brick int, node int, block long, x0 int, x1 int, y0 int, y1 int, z0 int, z1 int, ghost int, lo double, hi double, present long, dtype string, data binary"
NAMES = [c.split(" ")[0] for c in BRICK.split(", ")]
RAYS = 4096
EPS = 1e-9
#: Storage forms and their blank values: whole numbers of 8 or 4 bytes, and reals of 4.
BLANKS = {"<i8": np.iinfo(np.int64).min, "<i4": np.iinfo(np.int32).min, "<f4": np.nan}
MEMORY = 6 << 30


def blank(cells: np.ndarray) -> np.ndarray:
    return np.isnan(cells) if cells.dtype.kind == "f" else cells == np.iinfo(cells.dtype).min


def pack_bricks(voxels: DataFrame, plan: KdPlan, ghost: int = 0, dtype: str = "<i8", block: int = BLOCK, memory: int = MEMORY) -> DataFrame:
    """One row a block that holds a voxel, its ghost layer included: its box, range and dense values. Raises before any job if a brick outgrows its worker."""
    check_fit(plan, memory, np.dtype(dtype).itemsize)
    spark = voxels.sparkSession
    own = voxels.where("v is not null")
    rows = halo(own, plan, ghost) if ghost else assign(own, plan).withColumn("ghost", F.lit(False))
    boxes = F.broadcast(plan.frame(spark).select("brick", "node", *BOX))
    rows = rows.select("brick", *AXES, "v").join(boxes, "brick")

    def cells_of(a: str) -> Column:
        """Grid cells along an axis whose blocks hold the voxel or have it in their ghost layer."""
        low, high = F.expr(f"{a}0 div {block}"), F.expr(f"({a}1 - 1) div {block}")
        first, last = F.expr(f"greatest({a} - {ghost}, 0) div {block}"), F.expr(f"({a} + {ghost}) div {block}")
        return F.sequence(F.greatest(first, low), F.least(last, high))

    for a in AXES:
        rows = rows.withColumn(f"g{a}", F.explode(cells_of(a)))

    def dense(table: pa.Table) -> pa.Table:
        def first(c):
            return table.column(c)[0].as_py()

        g = [first(f"g{a}") for a in AXES]
        box = [(max(first(f"{a}0"), k * block), min(first(f"{a}1"), (k + 1) * block)) for a, k in zip(AXES, g, strict=True)]
        at = [table.column(a).to_numpy() - lo + ghost for a, (lo, _) in zip(AXES, box, strict=True)]
        v = table.column("v").to_numpy()
        size = [hi - lo + 2 * ghost for lo, hi in box]
        inside = np.all([(p >= 0) & (p < n) for p, n in zip(at, size, strict=True)], axis=0)
        own = np.all([(p >= ghost) & (p < n - ghost) for p, n in zip(at, size, strict=True)], axis=0)
        cells = np.full(size, BLANKS[dtype], dtype)
        limits = np.iinfo(cells.dtype) if cells.dtype.kind == "i" else None
        if limits and len(v) and (v.min() <= limits.min or v.max() > limits.max):
            raise OverflowError(f"values of brick {first('brick')} don't fit {dtype}")
        cells[tuple(p[inside] for p in at)] = v[inside]
        number = (g[0] << 42) | (g[1] << 21) | g[2]
        mine = v[inside]  # a sample near a face can take its value from the ghost layer
        values = [first("brick"), first("node"), number, *(x for lo_hi in box for x in lo_hi), ghost]
        values += [float(mine.min()), float(mine.max())] if len(mine) else [None, None]
        return pa.Table.from_arrays([pa.array([x], t) for x, t in zip([*values, int(own.sum()), dtype, cells.tobytes()], TYPES, strict=True)], names=NAMES)

    blocks = rows.groupBy("brick", "gx", "gy", "gz").applyInArrow(dense, BRICK)
    return blocks if ghost else blocks.where("present > 0")


TYPES = [pa.int32(), pa.int32(), pa.int64(), *[pa.int32()] * 7, pa.float64(), pa.float64(), pa.int64(), pa.string(), pa.binary()]


def skip_empty(bricks: DataFrame, background: float = 0.0) -> DataFrame:
    """Blocks with anything above the background: a filter on a column of the block table, which storage prunes by its statistics."""
    return bricks.where(F.col("hi") > F.lit(float(background)))


def seen_bricks(plan: KdPlan, cube: CubeSpec, views: list[ViewSpec]) -> list[int]:
    """Bricks that any of the views has in its frame: what a scan needs to open."""
    return [b.brick for b in plan.bricks if any(rectangle(v, cube, b.box) for v in views)]


def ray_table(view: ViewSpec, cube: CubeSpec, u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    s, c = view.scale(cube), cube.centre
    right, up = (u + 0.5 - view.width / 2) / s, (v + 0.5 - view.height / 2) / s
    on = np.stack([c[0] + right * view.cos, c[1] + up, c[2] + right * view.sin], axis=1)
    if view.distance is None:
        return on, np.broadcast_to(np.array([-view.sin, 0.0, view.cos]), on.shape)
    eye = np.array(view.eye(cube))
    return np.broadcast_to(eye, on.shape), on - eye


def clipped(o, d, box):
    low, high = np.full(len(o), -np.inf), np.full(len(o), np.inf)
    inside = np.ones(len(o), bool)
    for a in range(3):
        lo, hi = box[2 * a], box[2 * a + 1]
        zero = d[:, a] == 0
        safe = np.where(zero, 1.0, d[:, a])
        ta, tb = (lo - o[:, a]) / safe, (hi - o[:, a]) / safe
        low = np.where(zero, low, np.maximum(low, np.minimum(ta, tb)))
        high = np.where(zero, high, np.minimum(high, np.maximum(ta, tb)))
        inside &= ~zero | ((o[:, a] >= lo) & (o[:, a] < hi))
    return low, high, inside & (high - low > EPS)


# Samples: ray and parameter of each, in the order of rays and along them


def exact_samples(box, o, d, te, tx):
    """The middle of every stretch between crossings in the box: one sample in each crossed voxel."""
    planes = []
    for a in range(3):
        zero = d[:, a] == 0
        t = (np.arange(box[2 * a], box[2 * a + 1] + 1)[None, :] - o[:, [a]]) / np.where(zero, 1.0, d[:, a])[:, None]
        t[zero] = np.inf
        planes.append(t)
    t = np.concatenate([te[:, None], *planes, tx[:, None]], axis=1)
    t = np.sort(np.where((t >= te[:, None]) & (t <= tx[:, None]), t, np.inf), axis=1)
    with np.errstate(invalid="ignore"):
        good = t[:, 1:] - t[:, :-1] > EPS
    good &= np.isfinite(t[:, 1:])
    ray, k = np.nonzero(good)
    return ray, (t[ray, k] + t[ray, k + 1]) / 2


def uniform_count(rule: str, o, d, te, tx) -> np.ndarray:
    """Number of samples of a uniform step, from entry and exit of the whole cube."""
    if rule in ("l1", "linf"):
        moved = np.abs(np.floor(o + (tx - 1e-9)[:, None] * d) - np.floor(o + (te + 1e-9)[:, None] * d))
        n = (moved[:, 0] + moved[:, 1] + moved[:, 2] if rule == "l1" else moved.max(axis=1)) + 1
    else:
        delta = (tx - te)[:, None] * np.abs(d)
        chord = np.sqrt(0.0 + delta[:, 0] * delta[:, 0] + delta[:, 1] * delta[:, 1] + delta[:, 2] * delta[:, 2])
        n = np.ceil(chord) if rule == "unit" else np.ceil(chord * 2.0)
    return np.maximum(n, 1).astype(np.int64)


def spaced(first, last):
    """Ray and number of each of the numbers from first to last."""
    size = np.maximum(last - first + 1, 0)
    ray = np.repeat(np.arange(len(first)), size)
    return ray, np.arange(len(ray)) - np.repeat(np.cumsum(size) - size, size) + first[ray]


def uniform_samples(cube: CubeSpec, o, d, te, tx, rule: str):
    low, high, _ = clipped(o, d, cube.box)
    n = uniform_count(rule, o, d, low, high)
    step = (high - low) / n
    ray, i = spaced(np.maximum(np.floor((te - low) / step - 0.5).astype(np.int64) - 1, 0), np.minimum(np.ceil((tx - low) / step).astype(np.int64) + 1, n - 1))
    return ray, low[ray] + (i + 0.5) * step[ray]


def fixed_samples(cube: CubeSpec, o, d, te, tx, dt: float):
    low, high, _ = clipped(o, d, cube.box)
    first, last = np.ceil(low / dt).astype(np.int64), np.ceil(high / dt).astype(np.int64) - 1
    ray, i = spaced(np.maximum(first, np.floor(te / dt).astype(np.int64) - 1), np.minimum(last, np.ceil(tx / dt).astype(np.int64) + 1))
    return ray, i * dt


def interpolated(cells, box, ghost: int, cube: CubeSpec, p) -> np.ndarray:
    """Value at points from the eight cell centres around; borders repeat, absent voxels count as 0."""
    q = p - 0.5
    low = np.floor(q).astype(np.int64)
    f = q - low
    corner = []
    for c in range(8):
        at = [np.clip(low[:, a] + (c >> a & 1), 0, cube.dims[a] - 1) - box[2 * a] + ghost for a in range(3)]
        x = cells[at[0], at[1], at[2]]
        corner.append(np.where(blank(x), 0, x).astype(np.float64))
    x = [corner[2 * i] + f[:, 0] * (corner[2 * i + 1] - corner[2 * i]) for i in range(4)]
    y = [x[2 * i] + f[:, 1] * (x[2 * i + 1] - x[2 * i]) for i in range(2)]
    return y[0] + f[:, 2] * (y[1] - y[0])


def blended(ray, colour, opacity, rays: int, limit: float | None):
    """Front-to-back blend of each ray's samples, the k-th of all rays at a time; a ray at the limit takes no more."""
    c, a = np.zeros(rays), np.zeros(rays)
    turn = np.arange(len(ray)) - np.searchsorted(ray, ray)
    for k in range(int(turn.max(initial=-1)) + 1):
        at = np.flatnonzero(turn == k)
        if limit is not None:
            at = at[a[ray[at]] < limit]
        r = ray[at]
        left = (1.0 - a[r]) * opacity[at]
        c[r], a[r] = c[r] + left * colour[at], a[r] + left
    return c, a


def table_lookup(value, lo: int, hi: int, buckets: int = 16):
    """Colour and opacity from the ramp table of the relational executor."""
    b = np.minimum(buckets - 1, np.trunc((value - lo) * buckets / max(1, hi - lo)))
    return b / (buckets - 1), b * b / (4.0 * (buckets - 1) ** 2)


def cast(
    bricks: DataFrame,
    cube: CubeSpec,
    views: list[ViewSpec],
    stop: int | None = None,
    mode: str = "exact",
    rule: str = "unit",
    dt: float = 1.0,
    interpolate: bool = False,
    transfer: str = "max",
    table: tuple[int, int] | None = None,
    limit: float | None = None,
    rectangles: bool = True,
) -> DataFrame:
    """Partial images of all views in one job: frame, node, brick, u, v, samples and what the transfer gives.

    transfer: max, min or sum give val; alpha (with the range of its table) gives t, c, a of a segment, to be merged in the order of t.
    samples: those that saw a voxel. stop: value at which a ray ends early in its block.
    """
    ghost_needed = 1 if interpolate else 0
    real = interpolate

    def samples_of(o, d, te, tx, box):
        if mode == "exact":
            ray, t = exact_samples(box, o, d, te, tx)
        else:
            ray, t = uniform_samples(cube, o, d, te, tx, rule) if mode == "uniform" else fixed_samples(cube, o, d, te, tx, dt)
        p = o[ray] + t[:, None] * d[ray]
        at = np.floor(p).astype(np.int64)
        if mode != "exact":
            inside = np.all([(at[:, a] >= box[2 * a]) & (at[:, a] < box[2 * a + 1]) for a in range(3)], axis=0)
            ray, t, p, at = ray[inside], t[inside], p[inside], at[inside]
        return ray, t, p, at

    def traced(cells, box, ghost, o, d, te, tx):
        ray, t, p, at = samples_of(o, d, te, tx, box)
        if interpolate:
            value = interpolated(cells, box, ghost, cube, p)
        else:
            value = cells[tuple(at[:, a] - box[2 * a] + ghost for a in range(3))]
            there = ~blank(value)
            ray, t, value = ray[there], t[there], value[there]
        if stop is not None:  # samples behind the first stop value don't count
            hit = value >= stop
            before = np.cumsum(hit) - hit
            start = np.searchsorted(ray, ray)
            keep = before - before[start] == 0 if len(ray) else hit
            ray, t, value = ray[keep], t[keep], value[keep]
        n = np.bincount(ray, minlength=len(te))
        some = n > 0
        if transfer == "alpha":
            colour, opacity = table_lookup(value.astype(np.float64), *table)
            c, a = blended(ray, colour, opacity, len(te), limit)
            entry = np.zeros(len(te))
            head = np.searchsorted(ray, np.flatnonzero(some))
            entry[some] = t[head]
            return some, n, [entry, c, a]
        heads = np.searchsorted(ray, np.flatnonzero(some))
        out = np.zeros(len(te), np.float64 if real else np.int64)
        if len(heads):
            value = value if real else value.astype(np.int64)
            out[some] = {"max": np.maximum, "min": np.minimum, "sum": np.add}[transfer].reduceat(value, heads)
        return some, n, [out]

    values = ["t", "c", "a"] if transfer == "alpha" else ["val"]

    def run(batches):
        for batch in batches:
            for row in batch.to_pylist():
                box, ghost = tuple(row[c] for c in BOX), row["ghost"]
                if ghost < ghost_needed:
                    raise ValueError("interpolation needs blocks packed with a ghost layer")
                size = [box[2 * a + 1] - box[2 * a] + 2 * ghost for a in range(3)]
                cells = np.frombuffer(row["data"], row["dtype"]).reshape(size)
                for view in views:
                    r = rectangle(view, cube, box) if rectangles else (0, view.width, 0, view.height)
                    if r is None:
                        continue
                    u, v = (a.ravel() for a in np.meshgrid(np.arange(r[0], r[1]), np.arange(r[2], r[3]), indexing="ij"))
                    for at in range(0, len(u), RAYS):
                        uu, vv = u[at : at + RAYS], v[at : at + RAYS]
                        o, d = ray_table(view, cube, uu, vv)
                        te, tx, hit = clipped(o, d, box)
                        if not hit.any():
                            continue
                        some, n, out = traced(cells, box, ghost, o[hit], d[hit], te[hit], tx[hit])
                        m = int(some.sum())
                        yield pa.RecordBatch.from_arrays(
                            [
                                pa.array(np.full(m, view.frame, np.int64)),
                                *(pa.array(np.full(m, row[c], np.int32)) for c in ("node", "brick")),
                                pa.array(uu[hit][some].astype(np.int32)),
                                pa.array(vv[hit][some].astype(np.int32)),
                                *(pa.array(x[some]) for x in out),
                                pa.array(n[some].astype(np.int64)),
                            ],
                            ["frame", "node", "brick", "u", "v", *values, "samples"],
                        )

    kinds = "t double, c double, a double" if transfer == "alpha" else f"val {'double' if real else 'long'}"
    return bricks.select("brick", "node", *BOX, "ghost", "dtype", "data").mapInArrow(run, f"frame long, node int, brick int, u int, v int, {kinds}, samples long")
