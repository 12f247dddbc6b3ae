"""Experiment workloads and surrounding relational queries."""
