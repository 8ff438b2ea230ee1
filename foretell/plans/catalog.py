"""Plan catalog: plans stored under the fingerprint of what they answer."""

from __future__ import annotations

import hashlib
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .planner import PlanResult
from .score import Plan
from .search import Observation
from .space import Config, Integer, ModelSpace

SCHEMA = "fingerprint string, target string, predictors array<string>, plan string, valid_error double, test_error double, baseline_error double, created double, dropped boolean"


def fingerprint(target: str, predictors: list[str] | None, relation: DataFrame, version: str = "") -> str:
    """Of the clause and the relation: its canonical plan and the version of its data (``version``, or
    path, length and time of change of the files that the plan reads)."""
    canonical = relation._jdf.queryExecution().analyzed().canonicalized().toString()
    return hashlib.sha256("\n".join([target, ",".join(predictors or ["*"]), canonical, version or data_version(relation)]).encode()).hexdigest()


def data_version(relation: DataFrame) -> str:
    """Digest of the state of all files under a relation; empty for relations without files."""
    leaves, out = relation._jdf.queryExecution().analyzed().collectLeaves(), []
    for i in range(leaves.size()):
        leaf = leaves.apply(i)
        if not leaf.getClass().getSimpleName().startswith("LogicalRelation") or "HadoopFsRelation" not in leaf.relation().getClass().getName():
            continue
        # listed anew: the relation keeps the files as they were when it was made; one text for all of them
        location = leaf.relation().location()
        location.refresh()
        out.append(location.allFiles().mkString("\n"))
    return hashlib.sha256("\n".join(out).encode()).hexdigest() if out else ""


class Catalog:
    """Append-only Parquet; the last row of a fingerprint holds."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path

    def _rows(self) -> DataFrame:
        try:
            return self.spark.read.schema(SCHEMA).parquet(self.path)
        except Exception as e:  # noqa: BLE001  Spark raises AnalysisException for a folder not yet written
            if "PATH_NOT_FOUND" not in str(e):
                raise
            return self.spark.createDataFrame([], SCHEMA)

    def _append(self, key: str, plan: Plan | None, dropped: bool) -> None:
        p = plan
        row = (key, p.target if p else None, p.predictors if p else None, p.to_json() if p else None, p.valid_error if p else None, p.test_error if p else None, p.baseline_error if p else None, time.time(), dropped)
        self.spark.createDataFrame([row], SCHEMA).coalesce(1).write.mode("append").parquet(self.path)

    def store(self, key: str, plan: Plan) -> None:
        self._append(key, plan, False)

    def drop(self, key: str) -> None:
        self._append(key, None, True)

    def lookup(self, key: str) -> Plan | None:
        row = self._rows().filter(F.col("fingerprint") == key).orderBy(F.desc("created")).limit(1).collect()
        return Plan.from_json(row[0]["plan"]) if row and not row[0]["dropped"] else None

    def remember(self, result: PlanResult) -> None:
        """Append a plan's history, from which later plans start."""
        result.history_frame(self.spark).withColumn("created", F.lit(time.time())).coalesce(1).write.mode("append").parquet(f"{self.path}_history")

    def prior(self, space: ModelSpace, most: int = 200) -> list[Observation]:
        """What the latest plans saw of configurations of this space, at most ``most`` of them."""
        try:
            rows = self.spark.read.parquet(f"{self.path}_history")
        except Exception as e:  # noqa: BLE001  as above
            if "PATH_NOT_FOUND" not in str(e):
                raise
            return []
        names = {f.name: set(f.parameters) for f in space.families}
        last = rows.filter(F.col("family").isin(*names) & F.col("status").isin("finished", "pruned", "diverged")).orderBy(F.desc("created"), "model_id").limit(most).collect()
        out = []
        for r in last:
            values = {**r["params"], **r["cats"]}
            if set(values) == names[r["family"]]:
                own = space.family(r["family"]).parameters
                config = Config(r["family"], tuple((k, int(values[k]) if isinstance(p, Integer) else values[k]) for k, p in own.items()))
                out.append(Observation(config, 1.0 if r["valid_error"] != r["valid_error"] else r["valid_error"]))
        return out

    def list(self) -> DataFrame:
        last = self._rows().groupBy("fingerprint").agg(F.max_by(F.struct("target", "predictors", "valid_error", "test_error", "baseline_error", "dropped"), "created").alias("r"))
        return last.select("fingerprint", "r.*").filter("not dropped").drop("dropped")
