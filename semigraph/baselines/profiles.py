"""The compared systems as settings of this engine: policies and toggles by feature profile."""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..algorithms import components, ranking, triangles
from ..algorithms.traversal import bfs
from ..operators.objects import SparseMatrix
from ..plans.direction import AlwaysPull, AlwaysPush, EdgeFractionPolicy, ReferencePolicy, TwoThresholdPolicy, UnvisitedEdgePolicy

#: Settings of breadth-first search per profile.
PROFILES = {
    "reference": {"policy": ReferencePolicy()},
    "cpu_la": {"policy": UnvisitedEdgePolicy(), "operand_reuse": False},
    "cpu_trav": {"policy": EdgeFractionPolicy(), "operand_reuse": False},
    "cpu_work": {"policy": UnvisitedEdgePolicy(), "operand_reuse": False, "masked": False},
    "gpu_front": {"policy": TwoThresholdPolicy(), "early_exit": True},
    "gpu_shard": {"policy": AlwaysPull(), "operand_reuse": False, "masked": False},
    "gpu_push": {"policy": AlwaysPush(), "masked": False},
    "gpu_lap": {"via_mxm": True},
}

#: Settings of the other algorithms per profile, of those that a profile's system was compared in.
SETTINGS = {
    "reference": {"bfs": PROFILES["reference"], "sssp": {}, "pagerank": {}, "cc": {"sparsified": True}, "tc": {}},
    "cpu_la": {"bfs": PROFILES["cpu_la"], "sssp": {"sparsified": False}, "pagerank": {}, "tc": {"degree_ordered": True}},
    "cpu_trav": {"bfs": PROFILES["cpu_trav"], "sssp": {"policy": EdgeFractionPolicy()}, "pagerank": {"f": ranking.pagerank_push}, "cc": {"f": components.label_propagation}, "tc": {"f": triangles.count_search}},
    "cpu_work": {"bfs": PROFILES["cpu_work"], "sssp": {"policy": UnvisitedEdgePolicy()}, "pagerank": {}, "cc": {"f": components.multistep}, "tc": {"f": triangles.count_search}},
    "gpu_front": {"bfs": PROFILES["gpu_front"], "sssp": {"policy": AlwaysPush()}, "pagerank": {"f": ranking.pagerank_push}, "cc": {"f": components.edge_filter}, "tc": {"f": triangles.count_search}},
    "gpu_shard": {"bfs": PROFILES["gpu_shard"], "sssp": {"policy": AlwaysPull(), "sparsified": False}, "pagerank": {"windows": 4}},
    "gpu_push": {"bfs": PROFILES["gpu_push"], "sssp": {"policy": AlwaysPush()}, "pagerank": {"f": ranking.pagerank_push}},
    "gpu_lap": {"bfs": PROFILES["gpu_lap"], "tc": {"plan": "multiply_first"}},
}

#: Which features each system has, as published.
FEATURES = {
    "direction optimization": ("reference", "cpu_work", "gpu_front", "cpu_trav", "cpu_la"),
    "generalized direction optimization": ("reference", "cpu_trav"),
    "early exit": ("reference", "gpu_front", "cpu_la"),
    "structure only": tuple(PROFILES),
    "no conversion of sparse to dense": ("reference", "gpu_front"),
    "masking": ("reference", "gpu_front", "cpu_la"),
    "mapping by vertex": tuple(PROFILES),
    "mapping by edge": ("reference", "gpu_front", "cpu_trav", "cpu_la"),
}


def bfs_with(name: str, a: SparseMatrix, source: int, **more) -> DataFrame:
    return bfs(a, source, **(PROFILES[name] | more))
