"""Experiment workloads re-expressed on the given tables."""
