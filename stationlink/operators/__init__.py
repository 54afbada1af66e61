"""Operators of the station identity engine."""
