"""Planners: from labelled blocks, a model space and a budget to a plan (a trained model)."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import cost
from ..operators import shared_scan
from ..operators.block_descent import BlockDescent, principal, states, step_all, step_kept
from ..operators.local_fanout import LocalData, packed_bytes
from ..operators.random_features import Components, Projection
from .bandit import Eliminator, SuccessiveHalving, Trial
from .budget import Budget, Ledger
from .search import Observation, make
from .space import Config, ModelSpace


#: Bytes of packed blocks up to which the cost model may choose local training.
LOCAL_BYTES = 64 << 20


@dataclass
class Record:
    """A row of the history."""

    model_id: int
    round: int
    config: Config
    iters_done: int
    status: str
    train_loss: float
    valid_error: float
    seconds: float

    @property
    def quality(self) -> float:
        return 1.0 - self.valid_error


@dataclass
class PlanResult:
    config: Config | None
    column: shared_scan.Column | None
    valid_error: float
    test_error: float
    partial: bool
    ledger: Ledger
    history: list[Record] = field(default_factory=list)
    regime: str = "distributed"

    def history_frame(self, spark, run_id: str = "run") -> DataFrame:
        rows = [(run_id, r.model_id, r.round, r.config.family, r.config.row()["params"], r.config.row()["cats"], r.iters_done, r.status, r.train_loss, r.valid_error, r.quality, r.seconds) for r in self.history]
        return spark.createDataFrame(rows, "run_id string, model_id bigint, round int, family string, params map<string,double>, cats map<string,string>, iters_done int, status string, train_loss double, valid_error double, quality double, seconds double")


def column_of(config: Config, model_id: int, d: int, classes: int, seed: int, first_stage: tuple[np.ndarray, np.ndarray] | None = None) -> shared_scan.Column:
    """The trainer's column for a configuration of one of the preset families.

    ``first_stage``: mean and principal components, for families whose inputs are the leading ones."""
    family, projection = config.family, None
    rate = float(config.get("rate", 0.3))
    if family == "logistic_rff":
        family, projection = "logistic", Projection(d, int(config["size"]), seed, float(config["noise"]))
    elif family.endswith("_components"):
        family, projection = family.removesuffix("_components"), Components(*first_stage, int(config["components"]))
    return shared_scan.start(shared_scan.Column(model_id, family, rate, float(config.get("l2", 0.0)), projection), d, classes)


@dataclass
class KernelModel:
    """A kernel SVM of one ridge value; models of one projection have their descent in common."""

    model_id: int
    descent: BlockDescent
    l2: float
    iterations: int = 0

    @property
    def weights(self) -> np.ndarray:
        return self.descent.weights[self.l2]

    def column(self, rate: float = 0.0) -> shared_scan.Column:
        """The same model as a column without bias, for scoring."""
        w = np.vstack((np.zeros((1, self.weights.shape[1])), self.weights))
        return shared_scan.Column(self.model_id, "svm", rate, self.l2, self.descent.projection, w, self.iterations)


KERNELS = ("gaussian", "cauchy")


class _Training:
    """Advances the models of a round: gradient columns by shared scans, or locally when all data fit
    a task; kernel models by blocks of features, the projections of a round in one pass."""

    def __init__(self, blocks: DataFrame, classes: int, *, kernel: str, step: str, regime: str, first_share: float, stop: int, ledger: Ledger, seed: int, kernel_features: int | None, models: int, max_iters: int):
        self.d = dimensions(blocks)
        self.blocks, self.classes, self.kernel, self.step, self.ledger, self.seed = blocks, classes, kernel, step, ledger, seed
        self.train, self.valid, self.test = (blocks.filter(F.col("split") == s) for s in ("train", "valid", "test"))
        self.tasks = blocks.rdd.getNumPartitions()
        self.first_share, self.stop = first_share, stop
        # a share of the first stop's data is a share of the blocks
        some = F.pmod(F.xxhash64(F.col("block_id")), F.lit(1000)) < round(1000 * first_share)
        self.some = self.train if first_share >= 1 else self.train.filter(some)
        if first_share < 1 and not self.some.limit(1).count():  # few blocks: none may be in the share
            self.some, self.first_share = self.train, 1.0
        self.features = kernel_features or min(204_800, max(256, 16 * self.d))
        self.descents: dict[tuple, BlockDescent] = {}
        self.principal: tuple[np.ndarray, np.ndarray] | None = None
        size = packed_bytes(blocks) if regime != "distributed" else 0
        if regime == "auto":
            slots, rows = blocks.sparkSession.sparkContext.defaultParallelism, size / (8 * max(1, self.d))
            # a core of the machine in the cost model's units
            chosen = cost.choose_regime(rows, self.d, models, max_iters, slots, max(1, slots // 8), cost.Machine(), LOCAL_BYTES)
            regime = chosen if first_share >= 1 else "distributed"
        self.local = LocalData(blocks) if regime == "local" else None
        self.regime = regime

    def make(self, config: Config, model_id: int) -> shared_scan.Column | KernelModel:
        if config.family in KERNELS:
            key, l2 = (config.family, float(config["scale"]), float(config["skew"])), float(config["l2"])
            if key not in self.descents or self.descents[key].passes:
                projection = Projection(self.d, self.features, self.seed, key[1], key[0], key[2])
                self.descents[key] = BlockDescent(projection, max(2, self.classes), [], block=min(512, -(-self.features // 2)))
            descent = self.descents[key]
            if l2 not in descent.weights:
                descent.l2s.append(l2)
                descent.weights[l2] = np.zeros((descent.projection.size, descent.columns))
            return KernelModel(model_id, descent, l2)
        if config.family.endswith("_components") and self.principal is None:
            mean, vectors, _ = principal(self.blocks)
            self.principal = (mean, vectors)
            self.ledger.charge(0, 1)
        return column_of(config, model_id, self.d, self.classes, self.seed, self.principal)

    def advance(self, models: list, left: list[int], steps: int) -> tuple[dict[int, float], dict[int, float]]:
        """(training loss, validation error) by model number after up to ``steps`` more iterations each."""
        loss: dict[int, float] = {}
        error: dict[int, float] = {}
        columns = [(m, n) for m, n in zip(models, left, strict=True) if not isinstance(m, KernelModel)]
        kernels = [(m, n) for m, n in zip(models, left, strict=True) if isinstance(m, KernelModel)]
        if columns and self.local:
            own = [m for m, _ in columns]
            for (m, n), (v, e) in zip(columns, self.local.advance(own, [min(steps, n) for _, n in columns], classes=self.classes, kernel=self.kernel, step=self.step), strict=True):
                loss[m.model_id], error[m.model_id] = v, e
            for t in range(steps):
                self.ledger.charge(sum(n > t for _, n in columns), 1 if any(n > t for _, n in columns) else 0)
            self.ledger.charge_held_out()
        elif columns:
            young = [(m, n) for m, n in columns if m.iterations < self.stop and self.first_share < 1]
            old = [c for c in columns if c not in young]
            for group, data, share in ((young, self.some, self.first_share), (old, self.train, 1.0)):
                for t in range(steps if group else 0):
                    own = [m for m, n in group if n > t]
                    if not own:
                        break
                    p = shared_scan.scan(data, own, self.classes, kernel=self.kernel, tasks=self.tasks)
                    for k, m in enumerate(own):
                        if p.rows.get("train"):
                            loss[m.model_id] = float(p.loss[k] / p.rows["train"])
                            shared_scan.update(m, p.grads[k], p.rows["train"], step=self.step)
                        else:
                            m.iterations += 1  # nothing to learn from; the plan still ends
                    self.ledger.charge(len(own), 1, share)
            result = shared_scan.scan(self.valid, [m for m, _ in columns], self.classes, kernel=self.kernel, tasks=self.tasks)
            error |= {m.model_id: result.error(k) for k, (m, _) in enumerate(columns)}
            self.ledger.charge_held_out()
        if kernels:
            kept = all(m.descent.keeps for m, _ in kernels)
            for t in range(steps):
                own = [m for m, n in kernels if n > t]
                if not own:
                    break
                due = list({id(m.descent): m.descent for m in own}.values())
                if kept:
                    passes = int(step_kept(self.blocks, due, self.tasks))
                else:
                    step_all(self.blocks, due, self.tasks)
                    passes = 1
                for m in own:
                    m.iterations += 1
                self.ledger.charge(len(own), passes)
            each = list({id(m.descent): m.descent for m, _ in kernels}.values())
            # with kept sums the objective is known, so only the validation rows are read
            seen = self.valid if kept else self.blocks.filter("split <> 'test'")
            found = {id(d): s for d, s in zip(each, states(seen, each, self.tasks), strict=True)}
            self.ledger.charge_held_out()
            for m, _ in kernels:
                s = found[id(m.descent)][m.l2]
                loss[m.model_id], error[m.model_id] = m.descent.objective(m.l2) if kept else s["objective"], s["valid_error"]
        return loss, error

    def test_error(self, column: shared_scan.Column) -> float:
        """The test split is read once, for the chosen model."""
        self.ledger.charge_held_out()
        return shared_scan.scan(self.test, [column], self.classes, tasks=self.tasks).error(0, "test")

    def close(self) -> None:
        if self.local:
            self.local.close()


def dimensions(blocks: DataFrame) -> int:
    row = blocks.selectExpr("cast(octet_length(x) / 8 / n as int) as d").first()
    return row["d"] if row else 0


def plan_sequential(blocks: DataFrame, space: ModelSpace, budget: Budget, *, proposer: str = "grid", max_iters: int = 100, classes: int = 1, seed: int = 0) -> PlanResult:
    """The baseline: one model after the other, each trained to the end, the best kept."""
    return plan_adaptive(blocks, space, budget, proposer=proposer, partial_iters=max_iters, max_iters=max_iters, batch_size=1, bandit=None, classes=classes, seed=seed)


def plan_adaptive(
    blocks: DataFrame,
    space: ModelSpace,
    budget: Budget,
    *,
    proposer: str = "parzen",
    partial_iters: int = 10,
    max_iters: int = 100,
    batch_size: int = 10,
    bandit: Eliminator | SuccessiveHalving | None = None,
    classes: int = 1,
    seed: int = 0,
    kernel: str = "gemm",
    step: str = "plain",
    on_improve: Callable[[Record], None] | None = None,
    prior: list[Observation] | None = None,
    regime: str = "distributed",
    first_share: float = 1.0,
    kernel_features: int | None = None,
) -> PlanResult:
    """Search, shared scans and early termination together; each of them can be switched off.

    A round fills the free places of the batch, advances the batch by ``partial_iters`` scans,
    charges the budget, records every model and lets the bandit rule sort them.  Survivors keep
    their weights.  ``prior``: observations of earlier plans, shown to the proposer (warm start).
    ``regime``: 'distributed' (shared scans), 'local' (the data are broadcast, a round is one job;
    raises when they are larger than ``local_fanout.MAX_BYTES``) or 'auto' (by the cost model).
    ``first_share``: share of the training blocks that models see until their first stop.
    ``kernel_features``: random features of a kernel SVM (by default 16 times the inputs, 256 at least).
    """
    ledger, history = Ledger(), []
    limit = budget.models or max(1, (budget.model_iterations or 100 * max_iters) // max_iters)
    searcher = make(proposer, space, limit, seed)
    training = _Training(blocks, classes, kernel=kernel, step=step, regime=regime, first_share=first_share, stop=partial_iters, ledger=ledger, seed=seed, kernel_features=kernel_features, models=limit, max_iters=max_iters)
    active: list[tuple[shared_scan.Column | KernelModel, Config]] = []
    observed: dict[Config, float | None] = {}
    best: Record | None = None
    best_finished: tuple[Record, shared_scan.Column | KernelModel] | None = None
    best_observed: tuple[Record, shared_scan.Column | KernelModel] | None = None
    rounds, ended = 0, False
    while True:
        room = budget.room(ledger, partial_iters)
        slots = batch_size - len(active)
        slots = min(slots, room) if room is not None else slots
        if not ended and slots > 0:
            seen = [*(prior or []), *(Observation(c, e) for c, e in observed.items())]
            fresh = searcher.propose(slots, seen)
            ended = not fresh
            for config in fresh:
                active.append((training.make(config, ledger.models), config))
                observed.setdefault(config, None)
                ledger.models += 1
        if not active:
            break
        rounds += 1
        left = [max_iters - c.iterations for c, _ in active]
        advance = min(partial_iters, max(left))
        if budget.model_iterations is not None:
            advance = min(advance, max(1, (budget.model_iterations - ledger.model_iterations) // len(active)))
        loss, errors = training.advance([c for c, _ in active], left, advance)
        earlier = [r.quality for r in history]
        trials = []
        for c, config in active:
            fine = np.isfinite(c.weights).all()
            error = errors.get(c.model_id, float("nan")) if fine else float("nan")
            done = c.iterations >= max_iters
            record = Record(c.model_id, rounds, config, c.iterations, "finished" if done and fine else ("running" if fine else "diverged"), loss.get(c.model_id, float("nan")), error, ledger.seconds)
            history.append(record)
            observed[config] = error if fine else 1.0
            trials.append(Trial(c.model_id, c.iterations, 1.0 - error, done and fine))
            if fine and (best_observed is None or error < best_observed[0].valid_error):
                best_observed = (record, c)
            if fine and done and (best_finished is None or error < best_finished[0].valid_error):
                best_finished = (record, c)
            if fine and (best is None or error < best.valid_error):
                best = record
                if on_improve:
                    on_improve(record)
        verdict = (bandit or Eliminator(slack=float("inf"))).sort(trials, earlier)
        for r in history[-len(trials) :]:
            if r.status == "running" and any(t.model_id == r.model_id for t in verdict.dropped):
                r.status = "pruned"
        alive = {t.model_id for t in verdict.active}
        active = [(c, config) for c, config in active if c.model_id in alive]
        if budget.exhausted(Ledger(0, ledger.model_iterations, ledger.scans, ledger.round_trips, 0, ledger.started), best.valid_error if best else None):
            break
    chosen = best_finished or best_observed
    training.close()
    if chosen is None:
        return PlanResult(None, None, float("nan"), float("nan"), True, ledger, history, training.regime)
    record, model = chosen
    column = model.column() if isinstance(model, KernelModel) else model
    return PlanResult(record.config, column, record.valid_error, training.test_error(column), best_finished is None, ledger, history, training.regime)
