"""Choices by the size of the input: summary or direct solving, capacity, kernel or wide expressions, how medians are found."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.expressions import WIDE
from ..model import PRACTICAL, Profile

LOCAL_BYTES = 256 << 20


def plan(nodes: DataFrame, k: int, profile: Profile = PRACTICAL) -> dict:
    """route 'direct' or 'summary', 'kernel' or 'wide', bytes of a node, its most locations, and the profile with its capacity set.

    The size never changes what a summary holds: supports are compressed where the profile says so, not by a limit.
    """
    n, z, most = nodes.agg(F.count("*"), F.avg(F.size("support")), F.max(F.size("support"))).first()
    row = nodes.select(F.size(F.element_at("support", 1)["coords"]).alias("d")).limit(1).first()
    d = row["d"] if row else 0
    node_bytes = int((z or 0) * (8 * d + 24))
    budget = profile.per_k * k
    capacity = max(2 * budget, 1024)
    while capacity > 2 * budget and capacity * node_bytes > LOCAL_BYTES:
        capacity //= 2
    chosen = replace(profile, capacity=capacity)
    return {"n": n, "d": d, "node_bytes": node_bytes, "most_locations": most or 0, "route": "direct" if n <= budget else "summary", "kernel": "wide" if d <= WIDE else "arrow", "profile": chosen}


def cluster(nodes: DataFrame, k: int, seed: int = 1, restarts: int = 1):
    """The planned end-to-end run."""
    from .summarise import cluster_uncertain

    return cluster_uncertain(nodes, k, plan(nodes, k)["profile"], seed, restarts)
