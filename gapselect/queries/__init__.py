"""All registered queries of the engine and their SQL twins."""

from gapselect.queries import around, learned, methods, streams
from gapselect.queries.base import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES", "around", "learned", "methods", "streams"]
