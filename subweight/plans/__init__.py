"""Experiment workloads, measures and the catalogue of queries."""
