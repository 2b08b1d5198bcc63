"""Cost and memory model, and the choice of reduction and placement that follows from it."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Cost:
    flops_per_task: float
    bytes_per_task: float
    keyfree_numbers: float
    keyed_numbers: float


def cost_model(n: int, dims: list[int], ranks: list[int], p: int, tasks: int) -> Cost:
    """Operations, memory and numbers moved of one evaluation of n cells over ``tasks`` tasks."""
    factors = sum(d * r for d, r in zip(dims, ranks, strict=True))
    size = factors + p * sum(ranks)
    return Cost(n * p * p / tasks, 8.0 * (factors + p * p + n * len(dims) / tasks), float(tasks * size), float(n * sum(ranks)))


@dataclass(frozen=True)
class Plan:
    reduce: str
    placement: str
    depth: int


def choose(n: int, dims: list[int], ranks: list[int], p: int, tasks: int, task_bytes: float = 1e9) -> Plan:
    """Key-free while whole gradients fit a task; beyond that cells are anchored at the largest mode, and with several huge modes the
    gradient is keyed after combining within partitions."""
    sizes = sorted((8.0 * d * r for d, r in zip(dims, ranks, strict=True)), reverse=True)
    depth = 1 if tasks <= 64 else 2 if tasks <= 4096 else 3
    if sum(sizes) * 2 <= task_bytes:
        return Plan("keyfree", "any", depth)
    if sum(sizes[1:]) * 2 <= task_bytes:
        return Plan("keyfree", "anchored", depth)
    return Plan("keyed", "any", depth)
