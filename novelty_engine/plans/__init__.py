"""Experiment workloads on the given tables, and their SQL."""
