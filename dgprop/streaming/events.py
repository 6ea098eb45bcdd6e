"""Event-time operators on streams of graph events."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from dgprop.plans.lineage import ensure_checkpoint_dir


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream of files: event_id, ts (with zone), user_id, event_type, value, props."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    # A pattern that only this file matches: a file source wants a folder or a pattern.
    raw = spark.readStream.schema(schema).parquet(f"{sf_dir}/events.parque[t]")
    return raw.withColumn("ts", F.timestamp_micros(F.expr("timestampdiff(MICROSECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', ts)")))


def run_to_table(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over all there is and read back what it wrote."""
    import uuid

    spark = stream.sparkSession
    ensure_checkpoint_dir(spark)
    base = f"{spark.sparkContext.getCheckpointDir()}/stream-{uuid.uuid4().hex}"
    if mode == "append":
        run = stream.writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
        run.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{base}/out")

    def keep(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/out")

    stream.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{base}/out")


class LastSeen(StatefulProcessor):
    """Per user the number of events and the latest one, kept as state."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("last", "n bigint, last bigint")

    def handleInputRows(self, key: tuple, rows: Iterator[pd.DataFrame], timerValues: object) -> Iterator[pd.DataFrame]:  # noqa: N802
        n, last = self.state.get() if self.state.exists() else (0, -1)
        for df in rows:
            n, last = n + len(df), max(last, int(df["event_id"].max()))
        self.state.update((n, last))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "last": [last]})

    def close(self) -> None:
        pass
