"""Choices that Catalyst can't make, each with its reason."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Choice:
    choice: str
    reason: str

    def explain(self) -> str:
        return f"{self.choice}: {self.reason}"


def choose_search(n: int, selectivity: float, k: int, exact_limit: int = 100_000) -> Choice:
    """Exact search where few points pass the filter; else the graph."""
    passing = n * selectivity
    return Choice("exact", f"{passing:.0f} points pass, at most {exact_limit}") if passing <= max(exact_limit, 10 * k) else Choice("graph", f"{passing:.0f} points pass, more than {exact_limit}")


def choose_repair(deleted: int, shards: int, per_shard: int = 10_000) -> Choice:
    """In-order kernel for small batches, set-at-a-time joins for large ones."""
    share = deleted / max(shards, 1)
    return Choice("kernel", f"{share:.0f} slots a shard") if share <= per_shard else Choice("relational", f"{share:.0f} slots a shard, more than {per_shard}")


def prefilter_or_postfilter(selectivity: float, k: int, ef: int) -> Choice:
    """Filter before the search unless a beam of ef is expected to keep k after it."""
    return Choice("post", f"{ef * selectivity:.1f} of {ef} should pass") if ef * selectivity >= 2 * k else Choice("pre", f"only {ef * selectivity:.1f} of {ef} should pass")


def broadcast_or_shuffle_queries(queries: int, dim: int, limit_bytes: int = 64 << 20) -> Choice:
    size = queries * dim * 8
    return Choice("broadcast", f"{size} bytes") if size <= limit_bytes else Choice("shuffle", f"{size} bytes, more than {limit_bytes}")
