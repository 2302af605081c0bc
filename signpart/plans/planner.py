"""Choosing a strategy from counts, and settings that suit the size of a job."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from signpart import tables

#: Bytes of an edge in a kernel's memory, about.
EDGE_BYTES = 320


def choose(edges: DataFrame, cap: int, warm: bool = False) -> str:
    """kernel if the edges fit one task, else component (which sends components beyond the cap to bands)."""
    if tables.at_most(edges, cap // 2):
        return "kernel"
    return "component"


@dataclass(frozen=True)
class Sizing:
    """Derived settings: shuffle partitions, and the cap of a task."""

    shuffle_partitions: int
    cap: int
    bands: int


def sizing(n_edges: int, cores: int, task_memory: int, bytes_per_edge: int = 32) -> Sizing:
    """Partitions of about 128 MB but at least one for each core; a cap that fits a task's memory."""
    partitions = max(cores, -(-n_edges * bytes_per_edge // (128 << 20)))
    cap = max(10_000, task_memory // EDGE_BYTES)
    return Sizing(int(partitions), int(cap), int(max(1, min(200, -(-n_edges // (cap * max(1, cores)))))))
