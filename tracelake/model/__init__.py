"""Entities, events, stores, and views of the given tables as event histories."""
