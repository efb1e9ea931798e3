"""Queries of the library, by family, with their SQL."""

from . import algebra, search, selection, shapes, streams

MODULES = (algebra, selection, search, streams, shapes)
QUERIES: dict = {}
ORACLES: dict = {}
for _m in MODULES:
    QUERIES |= _m.Q
    ORACLES |= _m.O
