"""Ways to carry out a superstep; all give the same values."""

from subgraph_engine.engines.relational import PartitionEngine  # noqa: F401
from subgraph_engine.engines.simple import (  # noqa: F401
    EdgeCentricEngine,
    PerVertexKeyEngine,
    SharedMemoryEngine,
    VertexCentricEngine,
)
from subgraph_engine.engines.block import BlockEngine  # noqa: F401
from subgraph_engine.engines.store import StoreEngine  # noqa: F401

ENGINES = {
    "partition": PartitionEngine,
    "vertex_centric": VertexCentricEngine,
    "edge_centric": EdgeCentricEngine,
    "shared_memory": SharedMemoryEngine,
    "per_vertex_kv": PerVertexKeyEngine,
    "block": BlockEngine,
    "store": StoreEngine,
}
