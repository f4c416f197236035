"""Choices by cost, made before a plan is built.

They are rewrites Catalyst cannot make: from rows to sufficient statistics, between epochs on the
driver and on the cluster, and between a table of decoders and solving for the patterns that occur.
"""

from __future__ import annotations

import math

from padgrad.functions.fixedpoint import PRIMES
from padgrad.operators.gradcode import straggler_patterns

#: Cells that the driver may hold for local epochs (0.8 GB of doubles).
LOCAL_CELLS = 100_000_000


def use_moments(n: int, d: int, c: int, epochs: int) -> bool:
    """Moments pay once, rows pay in every epoch."""
    return epochs * 2 * n * d * c > n * d * d + epochs * d * d * c


def moment_tasks(partitions: int, data_bytes: int, d: int, c: int, devices_a_task: int = 1, share: float = 0.05) -> int:
    """Tasks of the moment pass: so few that partial sums (an upper triangle for each device that a task meets) are at most ``share`` of the data."""
    most = int(share * data_bytes / (4 * d * (d + 1 + 2 * c) * devices_a_task))
    return max(1, min(partitions, most))


def epoch_engine(devices: int, d: int, c: int) -> str:
    return "local" if devices * d * (d + c) <= LOCAL_CELLS else "spark"


def lane_bits(d: int, k: int = 48, f: int = 24, code_bits: int = 5, largest: int = 16) -> int:
    """Bits of the widest integer of a lifted run: data, code and model, summed over d."""
    return (k - f + 8) + (k + math.ceil(math.log2(max(d, 2)) / 2) + 5) + (f + code_bits) + largest


def lanes_suffice(d: int, k: int = 48, f: int = 24) -> bool:
    return lane_bits(d, k, f) < sum(p.bit_length() for p in PRIMES) - len(PRIMES)


def decoder_plan(devices: int, alpha: int, limit: int = 100_000) -> str:
    return "table" if straggler_patterns(devices, alpha) <= limit else "on_demand"
