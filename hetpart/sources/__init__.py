"""Graphs from tables, generators and files; sinks for assignments."""
