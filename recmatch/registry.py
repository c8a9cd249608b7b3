"""All queries of the engine but those of the training-data operators."""

from recmatch.operators import surface  # noqa: F401  these fill the tables below
from recmatch.plans import experiments, methods  # noqa: F401
from recmatch.streaming import jobs  # noqa: F401

QUERIES, ORACLES = methods.QUERIES, methods.ORACLES
