"""Registered queries: methods, baselines, measures, experiments and the engine surface."""

from ..operators import cube, render
from ..plans.kd import kd
from ..plans.spec import SURVEY, ViewSpec
from . import experiments, frames, methods, surface
from .registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES", "experiments", "flagship", "frames", "methods", "surface"]


def flagship(spark, sf_dir):
    """One frame of the survey cube at 30 degrees."""
    return render.frame(cube.survey(spark, sf_dir), SURVEY, ViewSpec(30), kd(SURVEY.dims, 8))
