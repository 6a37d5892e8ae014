"""Where scored documents go."""

from __future__ import annotations

from pyspark.sql import DataFrame


def write_scored(df: DataFrame, path: str, format: str = "parquet", partition_by: tuple[str, ...] = (), mode: str = "errorifexists") -> None:
    """Files of ``df``, in a folder per value of the partition columns (a verdict or language, say)."""
    writer = df.write.format(format).mode(mode)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def write_table(df: DataFrame, name: str, partition_by: tuple[str, ...] = (), mode: str = "errorifexists") -> None:
    writer = df.write.mode(mode)
    (writer.partitionBy(*partition_by) if partition_by else writer).saveAsTable(name)


def batch_sink(path: str, format: str = "parquet"):
    """For ``foreachBatch``: each micro-batch goes to a folder of its own number, so a repeated batch replaces itself."""

    def write(df: DataFrame, batch_id: int) -> None:
        df.write.format(format).mode("overwrite").save(f"{path}/batch={batch_id}")

    return write
