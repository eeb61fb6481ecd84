"""All queries of the engine and their SQL."""

from . import experiments, methods, relational

QUERIES = methods.QUERIES | experiments.QUERIES | relational.QUERIES
ORACLES = methods.ORACLES | experiments.ORACLES | relational.ORACLES
