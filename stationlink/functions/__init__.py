"""Functions of the station identity engine."""
