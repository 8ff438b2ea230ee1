"""The registered queries: methods, variants, baselines, measures, workloads and operators."""

from __future__ import annotations

from . import experiments, methods, published, streams, surrounding  # noqa: F401  register their entries
from .methods import flagship
from .registry import ORACLES, QUERIES, Query


__all__ = ["flagship", "oracle_sql", "queries"]


def queries() -> dict[str, Query]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
