"""Plans of the station identity engine."""
