"""Cost model: distance counts, memory and the share of useful bits in wide loads."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def load_efficiency(dim: Column, bits: Column, team: Column, load_bits: int = 128) -> Column:
    """Useful share of the bits that a team of lanes loads for one vector."""
    total, step = dim * bits, team * load_bits
    return total / (step * F.ceil(total / step))


def distance_reorder(n: int, degree: int) -> int:
    """Distances computed when edges are reordered by distance on the fly; by rank there are none."""
    return n * degree * (degree - 1)


def memory(n: int, dim: int, degree: int, *, base: int, vector_bits: int = 32, id_bytes: int = 8, slots: int = 1024, slot_bytes: int = 4) -> dict[str, int]:
    """Bytes of vectors, graph and distance table, and of one query's visited set."""
    return {"vectors": n * dim * vector_bits // 8, "graph": n * degree * id_bytes, "distance_table_entries": n * base, "visited_per_query": slots * slot_bytes}
