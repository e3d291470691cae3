"""Whole codec runs, experiment workloads and the query registry."""
