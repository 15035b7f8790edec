"""Search-list expressions: merging the best M, and the expanded flag kept in an id's top bit."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

TOP_BIT = -(1 << 63)


def mark(node: Column) -> Column:
    return node.bitwiseOR(F.lit(TOP_BIT))


def is_marked(node: Column) -> Column:
    return node < 0


def strip(node: Column) -> Column:
    return node.bitwiseAND(F.lit((1 << 63) - 1))


def merge_top(top: Column, candidates: Column, M: int) -> Column:
    """Best M of two arrays of struct(dist, nid, ...) with distinct nids, by (dist, nid)."""
    return F.slice(F.array_sort(F.concat(top, candidates)), 1, M)


def seed_id(qid: Column, j: Column, seed: int, n: int) -> Column:
    """Start node ``j`` of a query in integer arithmetic."""
    from neargraph.params import SEED_FACTOR, SEED_MODULUS

    t = (qid * 1000003 + j * 7919 + seed * 104729 + 12345) % SEED_MODULUS
    return t * SEED_FACTOR % SEED_MODULUS % n
