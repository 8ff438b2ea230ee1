"""Proposers: model-search methods behind one interface."""

from .base import Observation, Proposer, make, register
from . import directions, forest, gaussian_process, grid, parzen, simplex, uniform  # noqa: F401  each registers itself

__all__ = ["Observation", "Proposer", "make", "register"]
