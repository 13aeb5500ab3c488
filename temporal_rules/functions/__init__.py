"""Time-series functions."""
