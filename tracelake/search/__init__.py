"""Multi-step pattern search: small data queries in the order of their pruning power."""

from tracelake.search.run import SearchResult, search
from tracelake.search.schedule import Weights, prune_score, schedule

__all__ = ["SearchResult", "Weights", "prune_score", "schedule", "search"]
