"""Registered queries and their SQL twins, by group."""

from freqsketch.workloads import accuracy, builds, controllers, hashes, lookups, mergers, relational, streams, surface
from freqsketch.workloads.surface import flagship

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
for _m in (hashes, builds, controllers, lookups, accuracy, mergers, streams, relational, surface):
    for _name, (_query, _sql) in _m.CATALOGUE.items():
        QUERIES[_name] = _query
        if _sql:
            ORACLES[_name] = _sql

__all__ = ["ORACLES", "QUERIES", "flagship"]
