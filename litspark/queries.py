"""All registered queries of the engine and the SQL that their results are held against."""

from __future__ import annotations

from litspark.plans import q_chunks, q_index, q_more, q_ops, q_parse, q_qa, q_stream, q_tables
from litspark.plans.q_stream import flagship

__all__ = ["ORACLES", "QUERIES", "flagship"]

_PARTS = (q_parse, q_chunks, q_index, q_qa, q_ops, q_stream, q_more, q_tables)
QUERIES = {name: query for part in _PARTS for name, query in part.QUERIES.items()}
ORACLES = {name: sql for part in _PARTS for name, sql in part.ORACLES.items()}
