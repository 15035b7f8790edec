"""Parameters of builds and searches, and the rules that tie them together."""

from __future__ import annotations

from dataclasses import dataclass

#: List length over which several walkers share a query, and candidate number up to which sorted lists are merged.
LIST_THRESHOLD = 512
MERGE_SWITCH = 512
SEED_MODULUS = 2147483647
SEED_FACTOR = 48271


@dataclass(frozen=True)
class SearchParams:
    """``stop``: 'exhausted' ends when every list entry is expanded, 'unchanged' when a round leaves the list of ids as it was."""

    k: int = 10
    M: int = 64
    p: int = 1
    max_iter: int | None = None
    visited: str = "full"  # or 'forget', 'none'
    bits: int = 10
    every: int = 1
    stop: str = "exhausted"
    merge: str = "auto"
    seed: int = 1
    metric: str = "l2"
    dtype: str = "fp32"
    walkers: int = 4
    team_list: int | None = None  # entries of each walker's list; None: M
    sharing: str = "superstep"
    expanded: str = "flag"  # beside each list entry, or 'table': a set of its own that is looked up
    in_step: int = 256  # queries of a batch that a core advances together

    def __post_init__(self) -> None:
        if self.M < self.k or (self.team_list is not None and self.team_list * self.walkers < self.k):
            raise ValueError("the list must hold at least k entries")
        if self.stop not in ("exhausted", "unchanged") or self.visited not in ("full", "forget", "none") or self.expanded not in ("flag", "table"):
            raise ValueError("unknown stop rule, visited set or place of the expanded nodes")

    @property
    def rounds(self) -> int:
        return self.max_iter or 2 * -(-self.M // self.p) + 10


def initial_degree(d: int, factor: int = 3) -> int:
    if factor not in (2, 3):
        raise ValueError("the base graph has two or three times the final degree")
    return factor * d


def aligned_degree(average: float, step: int = 16) -> int:
    """Largest multiple of ``step`` that is no more than a mean out-degree."""
    return int(average // step) * step


def table_size(rounds: int, p: int, d: int) -> int:
    """Slots of a full visited set: a power of two, at least twice what all rounds can bring."""
    need = 2 * rounds * p * d
    size = 1
    while size < need:
        size *= 2
    return size


def choose_mode(batch: int, M: int, *, b_t: int, m_t: int = LIST_THRESHOLD) -> str:
    """Several walkers for each query when the batch leaves workers idle or the list is long; else one."""
    return "team" if batch < b_t or M > m_t else "solo"


def choose_merge(candidates: int, switch: int = MERGE_SWITCH) -> str:
    return "merge" if candidates <= switch else "partition"


def seed_point(qid: int, j: int, seed: int, n: int) -> int:
    """Start node ``j`` of a query: integer arithmetic that SQL can repeat."""
    return (qid * 1000003 + j * 7919 + seed * 104729 + 12345) % SEED_MODULUS * SEED_FACTOR % SEED_MODULUS % n
