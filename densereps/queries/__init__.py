"""Registered queries of the clustering engine, and the SQL that they are held against."""

from densereps.queries import variants  # noqa: F401  registers its queries among the methods
from densereps.queries.methods import METHOD_ORACLES, METHODS
from densereps.queries.surface import SURFACE, SURFACE_ORACLES

QUERIES = METHODS | SURFACE
ORACLES = METHOD_ORACLES | SURFACE_ORACLES
