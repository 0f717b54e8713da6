"""All queries of the engine and the SQL that gives the same rows."""

from . import experiments, methods, relops, streaming  # noqa: F401  (they add their queries to those of methods)

QUERIES: dict = dict(methods.QUERIES)
ORACLES: dict = dict(methods.ORACLES)
