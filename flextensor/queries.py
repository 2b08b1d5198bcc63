"""Registered queries of the engine and their SQL twins."""

from .operators import experiments, relational, streaming_queries, tensor_queries
from .operators.tensor_queries import flagship

_ALL = {**relational.TABLE, **tensor_queries.TABLE, **streaming_queries.TABLE, **experiments.TABLE}
# harnesses of minutes come last
LONG = tuple(n for n in _ALL if n.startswith(("q_ctr", "q_w9", "q_w11", "q_w12", "q_w13")) or n == "q_w14_balanced")
QUERIES = {name: _ALL[name][0] for name in (*(n for n in _ALL if n not in LONG), *LONG)}
ORACLES = {name: sql for name, (_, sql) in _ALL.items() if sql is not None}

__all__ = ["LONG", "ORACLES", "QUERIES", "flagship"]
