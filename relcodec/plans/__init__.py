"""Experiment workloads, as plans over the given tables."""
