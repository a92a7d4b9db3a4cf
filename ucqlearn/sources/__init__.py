"""Readers, written artifacts and the experiment workloads."""
