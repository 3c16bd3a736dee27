"""Limits, slack, counts and predicted cost: the numbers that steer a partitioner."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Cluster-bound warning: below this many unit nodes a cluster can hardly form.
LEAST_CLUSTER = 4


def limit_relaxed(total: float, k: int, eps: float, heaviest: float) -> float:
    """The larger of the average block with slack and the average block plus the heaviest node."""
    return max((1 + eps) * total / k, total / k + heaviest)


def limit_strict(total: int, k: int, eps: float) -> float:
    """Slack over the average block rounded up."""
    return (1 + eps) * -(-total // k)


def limit_two_way(total: int, eps: float, share: float = 0.5) -> float:
    """Largest side of a bisection; uneven shares scale the side's own part."""
    return (1 + eps) * -(-total // 2) if share == 0.5 else (1 + eps) * total * share


def eps_adaptive(eps: float, total: float, k: int, part: float, parts: int) -> float:
    """Slack of one bisection of a block of weight ``part`` that will become ``parts`` of ``k`` blocks; their product keeps eps."""
    if parts <= 1 or part <= 0:
        return 0.0
    depth = max(1, math.ceil(math.log2(parts)))
    return max(0.0, ((1 + eps) * total / k * parts / part) ** (1 / depth) - 1)


def ceil2(x: float) -> int:
    """The least power of two that is not below x."""
    return 1 << max(0, math.ceil(x) - 1).bit_length() if x > 1 else 1


def floor2(x: int) -> int:
    return 1 << (int(x).bit_length() - 1)


def level_blocks(n: int, c: int, k: int, finest: bool = False) -> int:
    """Blocks that a level of n nodes is to have."""
    return k if finest else max(min(k, 2), min(k, ceil2(n / c)))


def cluster_cap(eps: float, total: int, k: int, c: int, n_input: int, n_now: int) -> float:
    """Largest cluster: slack times the average block, whose number halves while the level is small for it."""
    blocks = min(k, n_input / c)
    while blocks > 1 and n_now <= blocks * c / 2:
        blocks /= 2
    return eps * total / max(blocks, 1)


def split_count(f: int) -> tuple[int, int]:
    return f // 2, f - f // 2


def heavy_light(k: int) -> tuple[int, int]:
    """With floor2(k) blocks: how many still split in two, and how many are final."""
    return k - floor2(k), 2 * floor2(k) - k


def split_counts(k: int, rounds: int) -> list[int]:
    out = [k]
    for _ in range(rounds):
        out = [x for f in out for x in (split_count(f) if f > 1 else (f,))]
    return out


def block_cap(total: float, k: int, eps: float, heaviest: float, f):
    """Limit of a block that will become f final blocks; for a number or a Column."""
    if isinstance(f, Column):
        return F.greatest(F.lit(1 + eps) * total * f / k, F.lit(total) * f / k + F.lit(heaviest))
    return max((1 + eps) * total * f / k, total * f / k + heaviest)


def relative_gain(d, c):
    """A cut reduction weighed by node weight: times it for gains, divided by it for losses."""
    if isinstance(d, Column):
        return F.when(d >= 0, (d * c).cast("double")).otherwise(d / c)
    return d * c if d >= 0 else d / c


def predicted_cost(n: float, p: float, k: float, c: float) -> float:
    """Idealised time of the one-cycle scheme on p cores; assumes unit weights, halving levels, bounded degree."""
    return n / p * max(1.0, math.log2(max(k * c / n, 1e-300))) + math.log2(n) ** 2


def predicted_cost_direct(n: float, p: float, k: float, c: float) -> float:
    """Direct k-way: the coarsest graph has k * c nodes, and one core splits it recursively."""
    return n / p + k * c * math.log2(max(k, 2)) + math.log2(n) ** 2


def predicted_cost_recursive(n: float, p: float, k: float, c: float) -> float:
    """Recursive bisection: one full cycle a depth."""
    return math.log2(max(k, 2)) * (n / p + math.log2(n) ** 2)
