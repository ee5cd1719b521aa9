"""Vertex programs by name."""

from subgraph_engine.programs.core import Program, lookup, register  # noqa: F401
from subgraph_engine.programs import algorithms  # noqa: F401
