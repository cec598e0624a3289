"""Tables in, results out."""

from .series import components_of, densify, explode_vectors, read_series, series_from_table, to_wide
from .tables import load, write_result

__all__ = ["components_of", "densify", "explode_vectors", "load", "read_series", "series_from_table", "to_wide", "write_result"]
