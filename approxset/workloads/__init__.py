"""Experiment workloads and the registered queries, each beside its SQL."""
