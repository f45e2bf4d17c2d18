"""Registered queries, their SQL and the cost measures."""
