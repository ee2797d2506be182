"""Batch sizes: the least that costs at most twice a single batch on two nodes, a cap on batch time, and multiples."""

from __future__ import annotations

import math

from .model import QuerySpec, TimeLaw

FEWEST_NODES = 2


def base_size(total: int, law: TimeLaw, nodes: int = FEWEST_NODES) -> int:
    """The least x for which ceil(total / x) batches of x units take at most twice one batch of all units.

    For each number of batches k only ceil(total / k) can be least, and more batches mean smaller ones, so the answer
    belongs to the largest k that fits; k is bounded by the fixed time of a batch.
    """
    if total <= 0:
        return 1
    limit = 2 * law.batch(nodes, total)
    fixed, each = law.b0 + law.bp / nodes, law.bn + law.bnp / nodes
    if fixed <= 0 or limit - each * total >= total * fixed:
        most = total
    else:  # k batches hold total units at least
        most = math.floor((limit - each * total) / fixed + 1e-9)
    for k in range(max(1, most), 0, -1):
        x = -(-total // k)
        if -(-total // x) * law.batch(nodes, x) <= limit * (1 + 1e-12):
            while x > 1 and -(-total // (x - 1)) * law.batch(nodes, x - 1) <= limit * (1 + 1e-12):
                x -= 1
            return x
    return total


def cap_size(law: TimeLaw, longest_s: float, nodes: int = FEWEST_NODES) -> int:
    """The most units whose batch takes less than longest_s."""
    if math.isinf(longest_s):
        return 1 << 60
    x = law.units_within(nodes, longest_s)
    while x > 1 and law.batch(nodes, x) >= longest_s:
        x -= 1
    return max(1, x)


def batch_size(spec: QuerySpec, factor: float, longest_s: float = math.inf) -> int:
    base = base_size(spec.total, spec.law)
    return max(1, min(math.ceil(factor * base), cap_size(spec.law, longest_s), max(1, spec.total)))


def sizes(specs: list[QuerySpec], factor: float, longest_s: float = math.inf) -> dict[str, int]:
    return {s.query_id: batch_size(s, factor, longest_s) for s in specs}
