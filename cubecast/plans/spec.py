"""Cubes and views as small driver-side values."""

from __future__ import annotations

import json
import math
from dataclasses import asdict, dataclass

Box = tuple[int, int, int, int, int, int]  # x0, x1, y0, y1, z0, z1, half open


@dataclass(frozen=True)
class CubeSpec:
    """A regular grid: voxel (i, j, k) fills [i, i+1) x [j, j+1) x [k, k+1)."""

    name: str
    dims: tuple[int, int, int]
    value_bytes: int = 4
    lo: int | None = None
    hi: int | None = None

    @property
    def volume(self) -> int:
        return math.prod(self.dims)

    @property
    def centre(self) -> tuple[float, float, float]:
        return tuple(d / 2 for d in self.dims)

    @property
    def diagonal(self) -> float:
        return math.sqrt(sum(d * d for d in self.dims))

    @property
    def box(self) -> Box:
        nx, ny, nz = self.dims
        return (0, nx, 0, ny, 0, nz)

    def to_json(self) -> str:
        return json.dumps(asdict(self))

    @classmethod
    def from_json(cls, text: str) -> CubeSpec:
        d = json.loads(text)
        return cls(**d | {"dims": tuple(d["dims"])})


def snapped(x: float) -> float:
    """Exact 0 and +-1 at right angles."""
    return float(round(x)) if abs(x - round(x)) < 1e-12 else x


@dataclass(frozen=True)
class ViewSpec:
    """A frame request: the camera turns about the Y axis around the cube's centre.

    ``distance`` is None for an orthographic view, else the eye's distance from the centre in units of the cube's diagonal.
    """

    angle: float = 0.0
    width: int = 64
    height: int = 64
    zoom: float = 1.0
    distance: float | None = None
    frame: int = 0

    @property
    def cos(self) -> float:
        return snapped(math.cos(math.radians(self.angle)))

    @property
    def sin(self) -> float:
        return snapped(math.sin(math.radians(self.angle)))

    def scale(self, cube: CubeSpec) -> float:
        """Pixels per voxel; at zoom 1 the bounding sphere fits the width."""
        return self.zoom * self.width / cube.diagonal

    def eye(self, cube: CubeSpec) -> tuple[float, float, float]:
        far = (self.distance or 0.0) * cube.diagonal
        cx, cy, cz = cube.centre
        return (cx + self.sin * far, cy, cz - self.cos * far)

    def matrix(self, cube: CubeSpec) -> list[float]:
        """Row-major 4 x 4 from voxel space to (u w, v w, depth, w); w is 1 for orthographic views."""
        s, (cx, cy, cz) = self.scale(cube), cube.centre
        c, n = self.cos, self.sin
        right, up, ahead = (c, 0.0, n), (0.0, 1.0, 0.0), (-n, 0.0, c)
        half = (self.width / 2, self.height / 2)

        def row(axis):
            return [s * axis[0], s * axis[1], s * axis[2], -s * (axis[0] * cx + axis[1] * cy + axis[2] * cz)]

        depth = [*ahead, -(ahead[0] * cx + ahead[1] * cy + ahead[2] * cz)]
        if self.distance is None:
            w = [0.0, 0.0, 0.0, 1.0]
        else:
            far = self.distance * cube.diagonal
            w = [ahead[0] / far, ahead[1] / far, ahead[2] / far, depth[3] / far + 1.0]
        u = [a + half[0] * b for a, b in zip(row(right), w, strict=True)]
        v = [a + half[1] * b for a, b in zip(row(up), w, strict=True)]
        return [*u, *v, *depth, *w]


# The stand-in cubes on the given tables.
SURVEY = CubeSpec("survey", (40, 40, 18))
WIDE = CubeSpec("wide", (27, 27, 16))
PARTICLE = CubeSpec("particle", (32, 32, 32))
SURVEY_SCALED = CubeSpec("survey_scaled", (80, 80, 36))
PARTICLE_SCALED = CubeSpec("particle_scaled", (81, 81, 81))
#: Points in the space of the first three vector components, [-1, 1) on each axis.
VEC = CubeSpec("vec", (32, 32, 32))
CUBES = {c.name: c for c in (SURVEY, WIDE, PARTICLE, SURVEY_SCALED, PARTICLE_SCALED)}


def spec_of(name: str) -> CubeSpec:
    return VEC if name == "vec" else CUBES[name]


# The published datasets, dimensions and size in GB.
PUBLISHED = {
    "particle": ((1024, 1024, 1024), 4.0),
    "survey_1": ((1721, 1721, 1025), 12.0),
    "survey_2": ((2502, 2501, 1093), 25.0),
    "particle_scaled": ((2600, 2600, 2600), 65.4),
    "survey_scaled": ((5004, 5002, 2186), 203.8),
}
ANGLES = tuple(range(0, 360, 15))
NODES = (2, 4, 8, 16, 32, 64)
