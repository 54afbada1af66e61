"""Streaming of the station identity engine."""
