"""Tag-cover route queries: specification, search, and the engine that runs batches of them."""

from .engine import ANSWER_SCHEMA, COUNTER_SCHEMA, Engine, RouteIndex
from .spec import QuerySpec, queries_frame

__all__ = ["ANSWER_SCHEMA", "COUNTER_SCHEMA", "Engine", "QuerySpec", "RouteIndex", "queries_frame"]
