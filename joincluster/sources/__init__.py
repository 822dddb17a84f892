"""Readers, writers and the experiment workloads over the given tables."""
