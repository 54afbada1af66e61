"""Sources of the station identity engine."""
