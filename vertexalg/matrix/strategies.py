"""Which physical plan a product takes; every decision rests on a counted size."""

from __future__ import annotations

STRATEGIES = ("columns", "rows_broadcast", "cols_shuffle", "grid", "triplet")


def choose(messages: int | None, message_bytes: int, limit: int, vertices: int | None = None, blocks: int = 1, needs_dst_state: bool = False) -> str:
    """For a product by itself, or a program that reads destinations (any other takes columns): rows_broadcast up to limit bytes of messages; beyond that a grid where destinations are read too or most vertices
    send and there are blocks to spread over; else columns with a shuffle of partial results.

    Moved per round: rows_broadcast bytes(x) per executor; cols_shuffle min(edges, blocks * receivers) rows;
    grid sqrt(blocks) times (x + y). An unknown size is never broadcast."""
    if messages is not None and messages * message_bytes <= limit:
        return "rows_broadcast"
    dense = messages is not None and vertices and messages > vertices / 2
    return "grid" if blocks >= 64 and (needs_dst_state or dense) else "cols_shuffle"
