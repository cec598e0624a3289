"""Baselines: higher-criticism scan, sparse projection, classical changepoints, per-component scans."""
