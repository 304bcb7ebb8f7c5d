from __future__ import annotations

from pyspark.sql import DataFrame

#: A network up to this many arcs is sent to the tasks as arrays (about 24 bytes an arc); beyond it, DataFrame rounds.
LOCAL_ARCS = 4_000_000


def choose_mode(arcs: DataFrame, limit: int = LOCAL_ARCS) -> str:
    """"local" if the network fits a task, counted up to the limit alone; else "wide"."""
    return "local" if arcs.limit(limit + 1).count() <= limit else "wide"
