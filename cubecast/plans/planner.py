"""Chooses how a frame is made, from metadata alone, and says why."""

from __future__ import annotations

import math
from dataclasses import dataclass

from .kd import KdPlan, extents
from .spec import Box, CubeSpec, ViewSpec

#: Samples up to which rows for each are cheaper than packing bricks.
FEW = 10**7


@dataclass(frozen=True)
class RenderPlan:
    view: ViewSpec
    executor: str  # object_order, relational or array
    bricks: tuple[int, ...]  # those that the frame can see: all that a scan opens
    rays: int
    most_samples: int
    message_bytes: int
    reason: str

    def explain(self) -> str:
        return (
            f"{self.executor}: {self.reason}\n  scan: {len(self.bricks)} bricks {list(self.bricks[:8])}{' ...' if len(self.bricks) > 8 else ''}\n"
            f"  rays: {self.rays}, samples at most: {self.most_samples}\n  messages: {self.message_bytes} bytes in rectangles"
        )


def rectangle(view: ViewSpec, cube: CubeSpec, box: Box) -> tuple[int, int, int, int] | None:
    """Bounds of the eight projected corners, clipped to the frame; the whole frame if a corner is behind the eye."""
    m = view.matrix(cube)
    us, vs = [], []
    for i in range(8):
        p = [box[2 * a + (i >> a & 1)] for a in range(3)]
        u, v, w = (m[4 * r] * p[0] + m[4 * r + 1] * p[1] + m[4 * r + 2] * p[2] + m[4 * r + 3] for r in (0, 1, 3))
        if w <= 0:
            return 0, view.width, 0, view.height
        us.append(u / w)
        vs.append(v / w)
    u0, u1 = max(0, math.floor(min(us))), min(view.width, math.ceil(max(us)))
    v0, v1 = max(0, math.floor(min(vs))), min(view.height, math.ceil(max(vs)))
    return (u0, u1, v0, v1) if u0 < u1 and v0 < v1 else None


def plan_render(cube: CubeSpec, view: ViewSpec, bricks: KdPlan, transfer: str = "max", sampling: str = "exact", interpolate: bool = False, few: int = FEW) -> RenderPlan:
    """The executor for a frame: right angles of a nearest-voxel maximum need no rays; few samples go as rows; all else as arrays."""
    seen = [(b, r) for b in bricks.bricks if (r := rectangle(view, cube, b.box))]
    area = [(r[1] - r[0]) * (r[3] - r[2]) for _, r in seen]
    samples = sum(a * sum(extents(b.box)) for a, (b, _) in zip(area, seen, strict=True))
    straight = view.distance is None and 0.0 in (view.cos, view.sin)
    if straight and transfer == "max" and sampling == "exact" and not interpolate:
        executor, reason = "object_order", "a right angle, the maximum, nearest voxels: project voxels, look pixels up"
    elif samples < few:
        executor, reason = "relational", f"under {few} samples: a row each"
    else:
        executor, reason = "array", f"{few} samples or more: dense blocks, no row a sample"
    return RenderPlan(view, executor, tuple(b.brick for b, _ in seen), sum(area), samples, 4 * sum(area), reason)


def explain_render(cube: CubeSpec, view: ViewSpec, bricks: KdPlan, **how) -> str:
    return plan_render(cube, view, bricks, **how).explain()
