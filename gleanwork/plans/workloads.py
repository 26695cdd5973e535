"""All registered queries of the engine and their SQL."""

from __future__ import annotations

from . import baselines, corpus, relational, streams
from .corpus import flagship  # noqa: F401

_ALL: dict = {}
for _part in (corpus, baselines, relational, streams):
    _ALL.update(_part.Q)
QUERIES = {name: f for name, (f, _) in _ALL.items()}
ORACLE_SQL = {name: sql for name, (_, sql) in _ALL.items() if sql}
