"""Experiment workloads on the given tables."""
