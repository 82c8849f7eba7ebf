"""Named queries over the given tables, each with its SQL where SQL can express it."""

from approxboot.catalog import methods, streams, surface, workloads

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
for _m in (methods, surface, streams, workloads):
    QUERIES |= _m.QUERIES
    ORACLES |= _m.ORACLES
