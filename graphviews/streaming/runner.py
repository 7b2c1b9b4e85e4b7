"""Running streams to their end, and feeding micro-batches to a network.

Timestamps without a zone take no watermark, so they are cast first.  Native
operators end in a table of the shared folder that each micro-batch replaces or adds
to; the network takes each micro-batch as a change set under its batch number, so a
repeated batch changes nothing.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphviews.maintenance.changes import ChangeSet
from graphviews.maintenance.network import Network
from graphviews.sources.shared import new_path


def table_stream(spark: SparkSession, sf_dir: str, name: str, files: int | None = None) -> DataFrame:
    """A table's files as a stream with an explicit schema; files: at most so many in a micro-batch."""
    schema = spark.read.parquet(f"{sf_dir}/{name}.parquet").schema
    reader = spark.readStream.schema(schema)
    if files:
        reader = reader.option("maxFilesPerTrigger", files)
    return reader.option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir)


def folder_stream(spark: SparkSession, path: str, schema, files: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)


def timed(events: DataFrame, delay: str = "1 hour", column: str = "ts") -> DataFrame:
    """events with a zoned timestamp and a watermark."""
    return events.withColumn(column, F.col(column).cast("timestamp")).withWatermark(column, delay)


def finished(stream: DataFrame, mode: str, each: Callable[[DataFrame, int], None]) -> None:
    """Run a stream over what is there now, each micro-batch through a function."""
    spark = stream.sparkSession
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", new_path(spark, "stream")).foreachBatch(each)
    writer.trigger(availableNow=True).start().awaitTermination()


def last_result(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """The result table after the last micro-batch: complete mode replaces it, other modes add rows."""
    spark = stream.sparkSession
    path = new_path(spark, "result")
    made: list[str] = []

    def each(batch: DataFrame, number: int) -> None:
        where = f"{path}/{number}"
        batch.write.mode("overwrite").parquet(where)  # a repeated batch writes the same place
        if mode == "complete":
            made.clear()
        if where not in made:
            made.append(where)

    finished(stream, mode, each)
    if not made:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(*made)


def maintain(stream: DataFrame, table: str, network: Network) -> None:
    """Each micro-batch of new rows refreshes the network."""
    columns = [c for c in network.graph.tables[table].columns if c != "__w"]
    finished(stream, "append", lambda batch, number: network.refresh(ChangeSet.inserts(**{table: batch.select(*columns)}), f"{table}-{number}") and None)


def corrected(stream: DataFrame, time: str, keys: list[str], delay: str) -> DataFrame:
    """Counts by keys where rows behind the watermark are not lost: they are the correction of a later batch.

    The main path counts rows up to the newest time seen less the delay; what comes
    later than that goes to a side table, and the result is the sum of both.
    """
    spark = stream.sparkSession
    path = new_path(spark, "corrected")
    state = {"newest": None, "made": []}

    def each(batch: DataFrame, number: int) -> None:
        newest = state["newest"]
        late = F.lit(False) if newest is None else F.coalesce(F.col(time) < F.lit(newest) - F.expr(f"interval {delay}"), F.lit(False))
        counted = batch.groupBy(*keys, late.alias("late")).agg(F.count(F.lit(1)).alias("n"), F.max(time).alias("top"))
        counted.write.mode("overwrite").parquet(f"{path}/{number}")
        state["made"].append(f"{path}/{number}")
        top = spark.read.parquet(f"{path}/{number}").agg(F.max("top").alias("t")).first()["t"]
        state["newest"] = max(x for x in (newest, top) if x is not None) if top or newest else None

    finished(stream, "append", each)
    rows = spark.read.parquet(*state["made"])
    return rows.groupBy(*keys).agg(F.sum("n").alias("n"), F.sum(F.when(F.col("late"), F.col("n")).otherwise(0)).alias("late"))
