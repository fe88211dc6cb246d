"""Experiment workloads and graph applications built on the sparse product."""
