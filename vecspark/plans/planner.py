"""Which scan and which join for a workload; pure functions."""

from __future__ import annotations

from dataclasses import dataclass

from vecspark.operators.encode import max_group_components


@dataclass(frozen=True)
class Plan:
    scan: str
    grouped: int
    tables: str
    partitions: int


def choose(n: int, lists: int, queries: int, m: int = 8, b: int = 8, ma: int = 1, code_bytes: int = 8, broadcast_bytes: int = 256 << 20, target_bytes: int = 128 << 20) -> Plan:
    """n codes in lists, a batch of queries that probe ma lists each.

    Small sets are scanned whole; large lists of 8-bit codes get the bounded scan with as
    many grouped components as their size allows; 4-bit codes the nibble scan; 16-bit codes
    the two-pass scan. Tables are broadcast up to a size, beyond it sent to their lists.
    """
    mean = n // max(1, lists)
    g = max_group_components(mean)
    if b == 4:
        scan = "nibble"
    elif b == 16:
        scan = "nested"
    elif g < 2:  # lists too small for groups to pay
        scan = "plain"
    else:
        scan = "bounded"
    table_bytes = queries * ma * m * (4 << b)
    return Plan(scan, min(g, 4, m) if scan == "bounded" else 0, "broadcast" if table_bytes <= broadcast_bytes else "shuffle", max(1, -(-n * (code_bytes + 8) // target_bytes)))


def query_batch(m: int, b: int, ma: int, broadcast_bytes: int = 256 << 20) -> int:
    """Queries whose tables fit one broadcast."""
    return max(1, broadcast_bytes // (ma * m * (4 << b)))
