"""Registry of the engine's queries and of their SQL twins."""

from __future__ import annotations

from vpcoreset.operators import more  # noqa: F401  adds to the queries of the operators
from vpcoreset.operators import queries as operators
from vpcoreset.plans import methods
from vpcoreset.streaming import queries as streaming

QUERIES: dict = methods.QUERIES | operators.QUERIES | streaming.QUERIES
ORACLES: dict[str, str] = methods.ORACLES | operators.ORACLES | streaming.ORACLES
