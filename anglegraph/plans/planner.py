"""Choices made from counts and bytes before a plan is built."""

from __future__ import annotations

from dataclasses import dataclass

EXACT_ROWS = 20_000
SCAN_ROWS = 5_000
WORKER_BYTES = 2 << 30


@dataclass(frozen=True)
class Choice:
    method: str
    n_shards: int
    routing: str
    reason: str


def choose_build(n: int, dim: int, degree: int = 50, worker_bytes: int = WORKER_BYTES) -> Choice:
    """The exact graph for small sets; else shards whose points and edges fill 40 % of a worker."""
    if n <= SCAN_ROWS:
        return Choice("scan", 1, "random", "a scan is cheaper than an index")
    if n <= EXACT_ROWS:
        return Choice("nag", 1, "random", "one graph fits a task")
    each = 8 * dim + 8 * degree + 16
    rows = max(1, int(0.4 * worker_bytes / each))
    shards = -(-n // rows)
    return Choice("nag_on_the_fly" if n > 50_000_000 else "nag", shards, "kmeans" if shards > 64 else "random", f"{rows} points fit a task")


def choose_search(n_queries: int, query_bytes: int, index_bytes: int, bound: int = 256 << 20) -> str:
    """What travels: the queries to the shards, a small index to the queries, or both by routed shard."""
    if query_bytes <= bound:
        return "broadcast_queries"
    return "broadcast_index" if index_bytes <= bound else "route"
