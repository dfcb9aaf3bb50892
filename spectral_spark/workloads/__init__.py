"""Experiment workloads and surrounding operators as driver queries."""
