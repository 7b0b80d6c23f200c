"""All queries of the library by name, and the SQL each is checked against."""

from . import measured, measures, relational, sorts, streams

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
for _part in (sorts, measures, measured, relational, streams):
    QUERIES |= _part.QUERIES
    ORACLES |= _part.ORACLES
