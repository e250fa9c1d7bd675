"""All queries of the library: importing the modules registers them."""

from __future__ import annotations

from doccurate.operators import relational  # noqa: F401
from doccurate.plans import ablations, measures, workloads  # noqa: F401
from doccurate.plans.registry import ORACLES, QUERIES
from doccurate.sources import records  # noqa: F401
from doccurate.streaming import ingest  # noqa: F401

__all__ = ["ORACLES", "QUERIES"]
