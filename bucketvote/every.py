"""All queries of the engine: importing this registers them."""

from . import catalogue, physical_queries, stream_queries, surface, workload_queries  # noqa: F401
from .registry import QUERIES

__all__ = ["QUERIES"]
