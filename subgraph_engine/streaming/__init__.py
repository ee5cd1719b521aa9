"""Streams of events as edges, and components that grow with them."""
