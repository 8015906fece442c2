"""All queries of the engine, with SQL twins where SQL can express them."""

from . import experiments, graph, methods, relational, stream

QUERIES: dict = {}
ORACLES: dict = {}
for _part in (graph, methods, experiments, relational, stream):
    QUERIES |= _part.QUERIES
    ORACLES |= _part.ORACLES
