"""Analytic models, experiment workloads and their registered queries."""
