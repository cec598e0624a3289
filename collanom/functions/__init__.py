"""Scalar mathematics: penalties, costs, normal and chi-square tails."""
