"""Incremental propagation over a stream of edge deltas.

Every micro-batch is a step: its deltas are netted, the state is repaired and pushed
on, and graph and state are written as a new version.  A small file names the
version of each batch, so a batch that is replayed is found done and left out.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dgprop.operators.filters import FilterSpec
from dgprop.operators.graph import apply_deltas, net_deltas
from dgprop.operators.propagate import init_state, push
from dgprop.operators.update import repair


@dataclass
class StreamUpdater:
    """Keeps the propagated state of a stream in versions under ``path``."""

    path: str
    features: DataFrame
    specs: list[FilterSpec]
    rmax: float
    dim: int
    late: str = "apply"

    def committed(self) -> dict[int, int]:
        """The version of each batch that is done, and the last step it held."""
        spark = self.features.sparkSession
        try:
            return {r["batch"]: r["last_step"] for r in spark.read.schema("batch bigint, last_step int").parquet(f"{self.path}/commits").collect()}
        except Exception as e:  # no batch has been written yet
            if "PATH_NOT_FOUND" in str(e):
                return {}
            raise

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        """For foreachBatch: events with seq, ts_us, kind, src, dst, w and step."""
        done = self.committed()
        if batch_id in done:
            return
        spark = batch.sparkSession
        if self.late == "drop" and done:
            batch = batch.filter(F.col("step") >= max(done.values()))
        last = batch.agg(F.coalesce(F.max("step"), F.lit(max(done.values(), default=0)))).head()[0]
        # Late events are exact for now and later: the identity depends on the present graph only.
        deltas = net_deltas(batch.withColumn("step", F.lit(0)))
        if done:
            v = max(done)
            edges, state = spark.read.parquet(f"{self.path}/edges/v={v}"), spark.read.parquet(f"{self.path}/state/v={v}")
        else:
            edges, state = spark.createDataFrame([], "src bigint, dst bigint, w double"), None
        after = apply_deltas(edges, deltas)
        start = init_state(self.features, after, self.specs, self.dim) if state is None else repair(state, deltas, edges, self.features, self.specs, self.dim)
        result = push(after, start, self.specs, self.rmax, self.dim)
        after.write.mode("overwrite").parquet(f"{self.path}/edges/v={batch_id}")
        result.state.write.mode("overwrite").parquet(f"{self.path}/state/v={batch_id}")
        spark.createDataFrame([(batch_id, last)], "batch bigint, last_step int").write.mode("append").parquet(f"{self.path}/commits")

    def state(self) -> DataFrame:
        return self.features.sparkSession.read.parquet(f"{self.path}/state/v={max(self.committed())}")
