"""All registered queries of the engine."""

from __future__ import annotations

from .. import sqlsurface  # noqa: F401  these modules register on import
from ..functions import scalar  # noqa: F401
from ..operators import aggregates, relational  # noqa: F401
from ..streaming import ops  # noqa: F401
from . import calibration_queries, method_queries  # noqa: F401
from .registry import QUERIES, TWINS


def queries() -> dict:
    return dict(QUERIES)


def twins() -> dict[str, str]:
    return dict(TWINS)
