"""Experiment workloads and their SQL twins."""
