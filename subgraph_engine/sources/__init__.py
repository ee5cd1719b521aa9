"""Readers and writers of graphs."""

from subgraph_engine.sources.edge_lists import (  # noqa: F401
    read_edge_list,
    read_edges,
    read_result,
    read_vertex_list,
    write_edge_list,
    write_result,
)
