"""Dependency tracking: backward and forward, with filters applied while tracing."""

from tracelake.track.run import EdgeFilter, Limits, NodeFilter, Seed, track, track_back, track_forward, track_many

__all__ = ["EdgeFilter", "Limits", "NodeFilter", "Seed", "track", "track_back", "track_forward", "track_many"]
