"""Which batch strategy answers many range summaries: from the monoid's traits and the sizes."""

from __future__ import annotations

from ordsum.functions.monoids import Monoid

SMALL_BATCH = 64


def windowable(m: Monoid) -> bool:
    return m.agg is not None and m.commutative and "<" not in m.dtype


def choose(m: Monoid, queries: int | None = None, stored: bool = False) -> tuple[str, str]:
    """(strategy, reason)."""
    if queries is not None and queries <= SMALL_BATCH and stored:
        return "few", f"{queries} queries on a stored map: its block table, and the blocks that their bounds cut"
    if queries is not None and queries <= SMALL_BATCH:
        return "canonical", "few queries: boundary blocks and cover nodes only"
    if m.inverse is not None and windowable(m):
        return "prefix", f"{m.name} has an inverse: one sorted pass gives both prefixes"
    if m.idempotent and m.commutative:
        return "overlap", f"{m.name} may count entries twice: two overlapping windows of blocks"
    return "canonical", f"{m.name} is any monoid: ordered cover of pyramid nodes"
