"""Grid geometry and balancing settings."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class GridSpec:
    """A ``side`` x ``side`` grid over [x_lo, x_lo + width) x [y_lo, y_lo + height); edge cells are open ended."""

    x_lo: float = 0.0
    y_lo: float = 0.0
    width: float = 256.0
    height: float = 100.0
    side: int = 64

    @property
    def cell_width(self) -> float:
        return self.width / self.side

    @property
    def cell_height(self) -> float:
        return self.height / self.side


@dataclass(frozen=True)
class BalanceConfig:
    """Settings of the balancing rounds.

    ``policy`` is lazy (the governor decides), always or never; ``loop`` is
    closed (the governor sees accepted arrivals) or open; ``merge_every`` is a
    number of rounds, 0 for never.  ``executor`` says what a point costs its
    machine: a check of every query of its tile (scan), or a descent of the
    machine's index and a check of the queries over its cell (index).
    ``capacity`` are checks a round, ``memory`` queries that a machine can hold.
    """

    machines: int = 8
    beta: int = 20
    decay: float = 0.5
    policy: str = "lazy"
    loop: str = "closed"
    split: str = "binary"
    order: str = "cost"
    merge_every: int = 0
    capacity: float | None = None
    executor: str = "scan"
    memory: int | None = None


EVENTS = GridSpec()
MACHINES = 8
