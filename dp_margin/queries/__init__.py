"""All queries of the classifier methods, with the SQL that must give the same rows."""

from __future__ import annotations

from . import calibration, constructions, fits, kernels, measures, relational
from .base import ORACLES, QUERIES
from .fits import finite_release_lineitem as flagship

__all__ = ["ORACLES", "QUERIES", "calibration", "constructions", "fits", "flagship", "kernels", "measures", "relational"]
