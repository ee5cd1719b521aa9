"""Relational operators around graphs, each as a query with its SQL."""
