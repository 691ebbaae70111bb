"""Experiment workloads and the query catalogue."""
