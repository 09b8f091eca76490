"""Experiment workloads and the catalogue of surrounding relational queries."""
