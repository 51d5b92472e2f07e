"""All queries of the engine and their SQL twins."""

from __future__ import annotations

import dupflow.queries.general
import dupflow.queries.methods
import dupflow.queries.streams  # noqa: F401
from dupflow.registry import ORACLES, QUERIES  # noqa: F401
