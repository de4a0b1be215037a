"""Registry of the workloads on the given tables."""

from pathtwin.workloads import documents, flows, measures, methods, operators, streams, variants

_MODULES = (documents, variants, flows, operators, streams, methods, measures)
QUERIES: dict = {}
ORACLES: dict = {}
for _module in _MODULES:
    QUERIES |= _module.QUERIES
    ORACLES |= _module.ORACLES
