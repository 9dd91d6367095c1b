"""Queries, their SQL, experiments and tuning."""
