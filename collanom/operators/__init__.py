"""Distributed operators: grids, scaling, savings, islands, lags, measures."""
