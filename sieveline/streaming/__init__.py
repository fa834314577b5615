"""The stateless operators on streams, and a stateful batched fold.

Maps, filters, splits and unnests are ordinary columns and run on streaming frames as they
are. Folds keep a state a key; resolve runs batch by batch against a mapping table.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..store import shared_dir


def event_stream(spark: SparkSession, path: str) -> DataFrame:
    """A folder or file of events as a stream; event time as a timestamp, so that watermarks hold."""
    static = spark.read.parquet(path)
    name = path.rstrip("/").rpartition("/")
    folder, pattern = (name[0], name[2])
    stream = spark.readStream.schema(static.schema).option("pathGlobFilter", pattern).parquet(folder)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over what is there now and read the sink: the batch result of a streaming plan."""
    spark = stream.sparkSession
    folder = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    if mode == "append":
        stream.writeStream.format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{folder}/out")

    def keep(batch: DataFrame, number: int) -> None:
        # In complete mode each batch holds the whole result; the last one stays.
        batch.write.mode("overwrite").parquet(f"{folder}/out")

    stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{folder}/out")


def drain_deliveries(parts: list[DataFrame], plan: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Run a plan over parts that arrive one after another, each in a run of its own.

    State and watermark pass from run to run through the checkpoint, so what is late does not
    depend on the order in which a file source lists its files. Appends the rows that are final.
    """
    spark = parts[0].sparkSession
    folder = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    for part in parts:
        part.write.mode("append").parquet(f"{folder}/in")
        stream = plan(spark.readStream.schema(parts[0].schema).parquet(f"{folder}/in"))
        stream.writeStream.format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{folder}/out")


def fold_counts(stream: DataFrame, key: str) -> DataFrame:
    """Stateful fold of a stream: per key the running count and sum, updated batch by batch."""
    import pandas as pd

    def step(keys, frames, state):
        n, total = state.get if state.exists else (0, 0.0)
        for f in frames:
            n, total = n + len(f), total + float(f["value"].sum())
        state.update((n, total))
        yield pd.DataFrame({key: [keys[0]], "n": [n], "total": [round(total, 6)]})

    kind = stream.schema[key].dataType.simpleString()
    return stream.groupBy(key).applyInPandasWithState(step, f"{key} {kind}, n long, total double", "n long, total double", "update", "NoTimeout")


def resolve_batches(stream: DataFrame, key: str, canonical: Callable, table: str) -> None:
    """foreachBatch resolve: values not yet in the mapping table are canonicalised and appended."""
    spark = stream.sparkSession

    def run(batch: DataFrame, number: int) -> None:
        new = batch.select(F.col(key).alias("value")).distinct()
        try:
            known = spark.read.parquet(table).select("value")
            new = new.join(known, "value", "left_anti")
        except Exception as e:
            if type(e).__name__ != "AnalysisException":
                raise
        new.select("value", canonical(F.col("value")).alias("canonical")).write.mode("append").parquet(table)

    stream.writeStream.foreachBatch(run).option("checkpointLocation", f"{table}-state").trigger(availableNow=True).start().awaitTermination()
