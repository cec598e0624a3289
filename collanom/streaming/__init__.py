"""Streaming forms: counts over event time and the online detector."""
