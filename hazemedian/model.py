"""Schemas of nodes, summaries and centres, and the options of a summary.

A node is a weight and a discrete distribution over locations: rows of `realisations` (long form) or one row with its
support (packed form).  `mass` is the chance that it is realised at all, at most 1.
"""

from __future__ import annotations

from dataclasses import dataclass, replace
from math import ceil, log2

SUPPORT = "array<struct<loc_id:bigint,coords:array<double>,prob:double>>"
NODES = f"node_id long, weight double, mass double, support {SUPPORT}"
REALISATIONS = "node_id long, loc_id long, coords array<double>, prob double, weight double"
MEDIANS = "node_id long, coords array<double>, weight double, mass double, spread double, steps int, status string"
CENTRES = "centre_id int, coords array<double>"
SUMMARY = f"{NODES}, median array<double>, spread double, level int, copies int, cell struct<centre:int,ring:int,spread:int>"

MASS_SLACK = 1e-9


@dataclass(frozen=True)
class Profile:
    """Every choice of a summary; the defaults are the practical summariser.

    median: 'iterative' or 'sampled'; centres: 'lloyd' or 'sampled_bicriteria'; stop: 'step_ratio' (as described: go on while a step
    is at most `ratio` of the one before) or 'step_tolerance'; allotment: 'even', 'as_printed' or 'proportional';
    draw_mass: 'weight', 'expected_weight' or 'uniform'; basis of the radius: 'location_spread' or 'location'.
    """

    median: str = "iterative"
    stop: str = "step_ratio"
    ratio: float = 0.1
    max_steps: int = 15
    dense_threshold: int = 100_000
    confidence: float = 0.9
    repeats: int = 1  # of sampled medians and of the centre search; 0: the logarithm of the nodes over delta
    candidates: str = "support"  # of the sampled median; or 'lattice'
    eps: float = 0.5
    delta: float = 0.1
    centres: str = "lloyd"
    weighted_seeding: bool = True
    max_rounds: int = 10
    guard: bool = True
    empty: str = "keep"
    alpha: float = 4.0
    basis: str = "location_spread"
    per_k: int = 200
    allotment: str = "even"
    draw_mass: str = "weight"
    exhaust_small: bool = False
    compress_support: bool = False
    capacity: int = 0

    def repeats_for(self, n: int) -> int:
        return self.repeats or max(1, ceil(log2(max(n, 2) / self.delta)))

    def capacity_for(self, k: int) -> int:
        """Nodes of a ladder bucket; more than the budget, or nothing would shrink."""
        return self.capacity or max(2 * self.per_k * k, 1024)


PRACTICAL = Profile()
REFERENCE = replace(PRACTICAL, median="sampled", centres="sampled_bicriteria", repeats=0, compress_support=True)
#: The centre search as it is described for the practical summariser: seeds by distance alone, centres always moved.
LITERAL = replace(PRACTICAL, weighted_seeding=False, guard=False)
