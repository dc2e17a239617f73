"""Registered queries of the methods and of the operators around them, each with DuckDB SQL where SQL has it."""

from . import learning, partitions, relational, streams, structure
from .registry import ORACLES, QUERIES

__modules__ = (learning, partitions, relational, streams, structure)
flagship = structure.flagship

__all__ = ["ORACLES", "QUERIES", "flagship"]
