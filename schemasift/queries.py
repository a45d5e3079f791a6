"""Importing this module registers every query of the library (the corpus operators register their own)."""

from .operators import general
from .plans import baselines, context, depgraph, describe, gold, keys, metrics, pipeline, profile, relgraph, spanner, valueindex, workloads
from .sources import sinks
from .streaming import streams

__all__ = ["baselines", "context", "depgraph", "describe", "general", "gold", "keys", "metrics", "pipeline", "profile", "relgraph", "sinks", "spanner", "streams", "valueindex", "workloads"]
