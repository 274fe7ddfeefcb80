"""Experiment workloads and registered queries."""
