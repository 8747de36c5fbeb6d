"""Reading the tables as streams, and draining a stream into a table."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fadegossip.plans import ensure_checkpoint_dir


def read_stream(spark: SparkSession, sf_dir: str, name: str, **options) -> DataFrame:
    """A table as a file stream; timestamps without zone become instants, so that a watermark can stand on them."""
    path = f"{sf_dir}/{name}.parquet"
    df = spark.readStream.schema(spark.read.parquet(path).schema).options(**options).parquet(f"{path[:-1]}[{path[-1]}]")  # as a pattern, a table may be one file or a folder of files
    return df.withColumns({c: F.col(c).cast("timestamp") for c, kind in df.dtypes if kind == "timestamp_ntz"})


def folder(spark: SparkSession) -> str:
    """A new folder where all executors see it."""
    ensure_checkpoint_dir(spark)
    return f"{spark.sparkContext._jsc.sc().getCheckpointDir().get()}/stream-{uuid.uuid4().hex}"


def drain(df: DataFrame, mode: str = "append") -> DataFrame:
    """Runs what is available and returns the result as a table.

    append: the rows of all batches. complete, update: each batch goes to its own folder by its number, so that a
    retried batch replaces itself; complete keeps the last, update the last row of each batch order (see keep_last).
    """
    spark, at = df.sparkSession, folder(df.sparkSession)
    if mode == "append":
        writer = df.writeStream.format("parquet").option("path", f"{at}/rows")
    else:
        writer = df.writeStream.foreachBatch(lambda batch, n: batch.withColumn("batch", F.lit(n)).write.mode("overwrite").parquet(f"{at}/rows/{n:08d}"))
    writer.outputMode(mode).option("checkpointLocation", f"{at}/log").trigger(availableNow=True).start().awaitTermination()
    if mode == "append":
        return spark.read.schema(df.schema).parquet(f"{at}/rows")
    rows = spark.read.parquet(f"{at}/rows/*")
    if mode == "complete":
        rows = rows.where(F.col("batch") == rows.agg(F.max("batch")).first()[0]).drop("batch")
    return rows


def keep_last(rows: DataFrame, keys: list[str]) -> DataFrame:
    """Of an update stream's rows, those of the last batch that named each key."""
    rest = [c for c in rows.columns if c not in keys and c != "batch"]
    return rows.groupBy(*keys).agg(F.max_by(F.struct(*rest), "batch").alias("x")).select(*keys, *[F.col(f"x.{c}").alias(c) for c in rest])
