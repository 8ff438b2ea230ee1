"""Cost model: floating-point work, bytes, roofline, overheads, money and the choice of a regime."""

from __future__ import annotations

import math
from dataclasses import dataclass


@dataclass(frozen=True)
class Machine:
    """Rates of one machine: peak in GFLOP/s, memory bandwidth in GB/s, network in GB/s."""

    peak: float = 110.0
    bandwidth: float = 60.0
    network: float = 1.0
    delay: float = 0.2


def data_bytes(rows: float, features: float, width: int = 8) -> float:
    return rows * features * width


def flops(rows: float, features: float, models: int) -> float:
    """Two matrix products per iteration, each 2 n d k."""
    return 4.0 * rows * features * models


def network_bytes(features: float, models: int, partitions: int) -> float:
    """Partial gradients of one iteration; independent of the number of rows."""
    return 8.0 * features * models * partitions


def intensity(models: int, scans_per_step: int = 1) -> float:
    """FLOP per byte read, when a step reads the matrix once or twice."""
    return 4.0 * models / (8.0 * scans_per_step)


def balance(peak: float, bandwidth: float) -> float:
    """FLOP per double at which computing and reading take equally long."""
    return peak / (bandwidth / 8.0)


def roofline(models: int, scans_per_step: int, machine: Machine) -> float:
    """Attainable GFLOP/s."""
    return min(machine.peak, machine.bandwidth * intensity(models, scans_per_step))


def balance_batch(machine: Machine, scans_per_step: int) -> float:
    """Batch size at which the bound turns from reading to computing."""
    return machine.peak / (machine.bandwidth * intensity(1, scans_per_step))


def overhead_ms(delay_ms: float, models: int) -> float:
    """Scheduling delay per model and iteration when a pass is shared."""
    return delay_ms / models


def round_trips(updates: int) -> int:
    return 2 * updates


def models_per_hour(models: int, seconds: float) -> float:
    return 3600.0 * models / seconds


def speedup(rate: float, unbatched: float) -> float:
    """Truncated to two decimals, the way the published table is."""
    return math.floor(rate / unbatched * 100) / 100


def dollars(nodes: int, hours: float, price_per_node_hour: float) -> float:
    return nodes * hours * price_per_node_hour


def estimate(configurations: int, scans_each: int, seconds_per_scan: float, batch: int = 1, survivors: float = 1.0, partial: int | None = None) -> dict[str, float]:
    """Scans and seconds of a plan: every model ``partial`` scans, the surviving share all of them."""
    partial = scans_each if partial is None else partial
    per_model = partial + survivors * (scans_each - partial)
    scans = configurations * per_model / batch
    return {"model_scans": configurations * per_model, "scans": scans, "seconds": scans * seconds_per_scan}


def saved_share(pruned_share: float, partial: int, full: int) -> float:
    """Share of scans saved when so large a share of models stops after ``partial`` of ``full``."""
    return pruned_share * (1 - partial / full)


def iteration_seconds(rows: float, features: float, models: int, nodes: int, machine: Machine) -> float:
    work = max(data_bytes(rows, features) / nodes / (machine.bandwidth * 1e9), flops(rows, features, models) / nodes / (machine.peak * 1e9))
    return machine.delay + work + network_bytes(features, models, nodes) / (machine.network * 1e9)


def choose_regime(rows: float, features: float, configurations: int, iterations: int, slots: int, nodes: int, machine: Machine, executor_bytes: float, batch: int = 10) -> str:
    """'local' (data broadcast, one model per task) or 'distributed' (shared scans)."""
    size = data_bytes(rows, features)
    if size > executor_bytes:
        return "distributed"
    waves = math.ceil(configurations / slots)
    local = size / (machine.network * 1e9) + waves * iterations * flops(rows, features, 1) / (machine.peak * 1e9 / max(1, slots // nodes))
    shared = math.ceil(configurations / batch) * iterations * iteration_seconds(rows, features, batch, nodes, machine)
    return "local" if local < shared else "distributed"
