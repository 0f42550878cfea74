"""Readers, writers and the point tables of the experiment workloads."""
