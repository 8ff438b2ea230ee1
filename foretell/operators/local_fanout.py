"""Small data: the packed blocks are broadcast and every task trains one model to the end."""

from __future__ import annotations

import pickle
from collections.abc import Iterator, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.blas import single_thread
from . import shared_scan

#: Bytes of blocks that may be broadcast.
MAX_BYTES = 256 << 20


class LocalData:
    """Packed blocks of a checked size, broadcast; rounds of training run on them without passes."""

    def __init__(self, blocks: DataFrame, most: int = MAX_BYTES):
        size = packed_bytes(blocks)
        if size > most:
            raise ValueError(f"{size} bytes of blocks; local training takes {most}")
        self.spark = blocks.sparkSession
        rows = [(r["split"], np.frombuffer(bytes(r["x"]), np.float64).reshape(r["n"], -1).copy(), np.asarray(r["y"])) for r in blocks.select("split", "block_id", "n", "x", "y").orderBy("block_id", "split").collect()]
        self.shared = self.spark.sparkContext.broadcast(rows)

    def advance(self, columns: Sequence[shared_scan.Column], iterations: Sequence[int], *, classes: int = 1, kernel: str = "gemm", step: str = "plain") -> list[tuple[float, float]]:
        """Train every column by its number of iterations, in one job of as many tasks as there are slots.
        Returns (training loss, validation error) by column; the columns are changed in place."""
        data, slots = self.shared, max(1, min(len(columns), self.spark.sparkContext.defaultParallelism))
        dealt = [list(range(k, len(columns), slots)) for k in range(slots)]
        state = [(list(columns[i] for i in own), [iterations[i] for i in own]) for own in dealt]

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            single_thread()
            for frame in frames:
                for k in frame["id"]:
                    own, left = state[int(k)]
                    loss = np.full(len(own), np.nan)
                    for t in range(max(left, default=0)):
                        now = [i for i in range(len(own)) if left[i] > t]
                        task = shared_scan.Task([own[i] for i in now], classes, kernel)
                        for split, x, y in data.value:
                            if split == "train":
                                task.add(split, x, y)
                        for g, i in enumerate(now):
                            loss[i] = task.loss[g] / max(1, task.rows.get("train", 0))
                            if task.rows.get("train"):
                                shared_scan.update(own[i], task.grads[g], task.rows["train"], step=step)
                            else:
                                own[i].iterations += 1  # nothing to learn from
                    task = shared_scan.Task(own, classes, kernel)
                    for split, x, y in data.value:
                        if split == "valid":
                            task.add(split, x, y)
                    n = task.rows.get("valid", 0)
                    error = task.wrong["valid"] / n if n else np.full(len(own), np.nan)
                    yield pd.DataFrame({"k": [int(k)], "state": [pickle.dumps((own, loss, error))]})

        out: list[tuple[float, float]] = [(float("nan"), float("nan"))] * len(columns)
        for row in self.spark.range(slots).repartitionById(slots, F.col("id").cast("int")).mapInPandas(run, "k int, state binary").collect():
            own, loss, error = pickle.loads(bytes(row["state"]))
            for j, i in enumerate(dealt[row["k"]]):
                columns[i].weights, columns[i].iterations, columns[i].memory = own[j].weights, own[j].iterations, own[j].memory
                out[i] = (float(loss[j]), float(error[j]))
        return out

    def close(self) -> None:
        self.shared.destroy()


def packed_bytes(blocks: DataFrame) -> int:
    return int(blocks.selectExpr("coalesce(sum(octet_length(x)), 0) as b").first()["b"])


def local_fanout(blocks: DataFrame, columns: Sequence[shared_scan.Column], iterations: int, *, classes: int = 1) -> DataFrame:
    """model_id, iters_done, train_loss, valid_error, test_error, weights; raises when the blocks
    are larger than ``MAX_BYTES`` (shared scans are the way then)."""
    spark = blocks.sparkSession
    data, models = LocalData(blocks).shared, list(columns)

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        single_thread()
        for frame in frames:
            for i in frame["id"]:
                c = models[int(i)]
                for t in range(iterations + 1):
                    task = shared_scan.Task([c], classes, "gemm")
                    for split, x, y in data.value:
                        task.add(split, x, y)
                    if t < iterations:
                        shared_scan.update(c, task.grads[0], task.rows["train"])
                err = {s: float(task.wrong[s][0] / task.rows[s]) for s in task.rows}
                yield pd.DataFrame([{"model_id": c.model_id, "iters_done": c.iterations, "train_loss": float(task.loss[0] / task.rows["train"]), "valid_error": err.get("valid"), "test_error": err.get("test"), "weights": c.weights.ravel().tolist()}])

    return spark.range(len(models)).repartition(max(1, len(models))).mapInPandas(run, "model_id bigint, iters_done int, train_loss double, valid_error double, test_error double, weights array<double>")
