"""Experiment workloads and operator queries, each with its oracle SQL."""
