"""All queries of the library and their SQL."""

from __future__ import annotations

from ..functions import scalar  # noqa: F401
from ..operators import relational
from ..sources import io  # noqa: F401
from ..streaming import streams  # noqa: F401
from ..workload import queries  # noqa: F401

QUERIES, ORACLES = relational.QUERIES, relational.ORACLES
