"""Partition plans and views on the driver: worked values and invariants."""

import pytest

from cubecast.plans import kd
from cubecast.plans.spec import SURVEY, CubeSpec, ViewSpec


@pytest.mark.parametrize("n", [1, 2, 3, 5, 6, 7, 8, 12, 16, 32, 64])
def test_bricks_tile_the_cube(n):
    plan = kd.kd(SURVEY.dims, n)
    assert len(plan) == n and sum(b.volume for b in plan.bricks) == SURVEY.volume
    for a in plan.bricks:
        for b in plan.bricks:
            if a.brick < b.brick:
                assert any(a.box[2 * i + 1] <= b.box[2 * i] or b.box[2 * i + 1] <= a.box[2 * i] for i in range(3))


def test_worked_volumes():
    volumes = lambda n: sorted(b.volume for b in kd.kd((40, 40, 18), n).bricks)
    assert volumes(8) == [3600] * 8
    assert volumes(5) == [5760] * 5
    assert volumes(6) == [4680] * 4 + [5040] * 2
    assert volumes(3) == [9360, 9720, 9720]
    assert volumes(1) == [28800]
    assert {b.box for b in kd.kd((1024,) * 3, 64).bricks} >= {(0, 256, 0, 256, 0, 256)}


def test_two_levels_number_bricks_and_nodes():
    plan = kd.two_level((40, 40, 18), [2, 2, 2, 2])
    assert [(b.brick, b.node, b.gpu) for b in plan.bricks] == [(i, i // 2, i % 2) for i in range(8)]
    uneven = kd.two_level((100, 100, 100), [1, 3, 2])
    assert [b.node for b in uneven.bricks] == [0, 1, 1, 1, 2, 2]


def test_capacity():
    assert kd.min_nodes((5004, 5002, 2186), 2, 6 << 30, 32 << 30) == 17
    with pytest.raises(ValueError):
        kd.check_fit(kd.kd((1024,) * 3, 2), 1 << 30)


def test_right_angles_are_exact_and_specs_round_trip():
    assert [(ViewSpec(a).cos, ViewSpec(a).sin) for a in (0, 90, 180, 270)] == [(1, 0), (0, 1), (-1, 0), (0, -1)]
    assert CubeSpec.from_json(SURVEY.to_json()) == SURVEY
