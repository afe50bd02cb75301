"""Experiment workloads; each returns rows of (workload, fixture, params, metric, value)."""
