"""Budgets and the ledger of what a plan has cost."""

from __future__ import annotations

import time
from dataclasses import dataclass, field


@dataclass
class Ledger:
    """models proposed, model-iterations, scans of the training data, round trips, passes over held-out
    data, the training data read (in whole tables), seconds."""

    models: int = 0
    model_iterations: int = 0
    scans: int = 0
    round_trips: int = 0
    held_out_scans: int = 0
    tables_read: float = 0.0
    started: float = field(default_factory=time.monotonic)

    @property
    def seconds(self) -> float:
        return time.monotonic() - self.started

    def charge(self, model_iterations: int, scans: int, share: float = 1.0) -> None:
        """``share``: of the training data that each of the scans has read."""
        self.model_iterations += model_iterations
        self.scans += scans
        self.round_trips += 2 * scans
        self.tables_read += scans * share

    def charge_held_out(self, scans: int = 1) -> None:
        self.held_out_scans += scans
        self.round_trips += 2 * scans

    def as_dict(self) -> dict[str, float]:
        return {"models": self.models, "model_iterations": self.model_iterations, "scans": self.scans, "round_trips": self.round_trips, "held_out_scans": self.held_out_scans, "tables_read": self.tables_read, "seconds": self.seconds}


@dataclass(frozen=True)
class Budget:
    """Any subset of limits; the first that is used up ends the plan."""

    models: int | None = None
    model_iterations: int | None = None
    scans: int | None = None
    seconds: float | None = None
    target_error: float | None = None

    def exhausted(self, ledger: Ledger, best_error: float | None = None) -> bool:
        spent = ((self.models, ledger.models), (self.model_iterations, ledger.model_iterations), (self.scans, ledger.scans), (self.seconds, ledger.seconds))
        if any(limit is not None and used >= limit for limit, used in spent):
            return True
        return self.target_error is not None and best_error is not None and best_error <= self.target_error

    def room(self, ledger: Ledger, each_iterations: int) -> int | None:
        """Models that may still be started (each needs so many iterations), None for no limit."""
        room = []
        if self.models is not None:
            room.append(self.models - ledger.models)
        if self.model_iterations is not None:
            room.append((self.model_iterations - ledger.model_iterations) // each_iterations)
        return max(0, min(room)) if room else None
