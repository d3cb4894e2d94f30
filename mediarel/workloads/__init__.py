"""Experiment workloads and the catalog of registered queries."""
