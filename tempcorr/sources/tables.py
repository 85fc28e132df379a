"""Sources and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load_text(spark: SparkSession, path: str, fmt: str, schema: str) -> DataFrame:
    """CSV or JSON; rows that don't fit the schema have their text in _bad."""
    reader = spark.read.schema(f"{schema}, _bad string").option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_bad")
    return (reader.option("header", "true") if fmt == "csv" else reader).format(fmt).load(path)


def stream(spark: SparkSession, path: str, schema, max_files: int = 100) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).parquet(path)


def save_windows(df: DataFrame, path: str) -> None:
    """Windows by layer; writing a layer again replaces it alone."""
    df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("layer").parquet(path)


def sink_windows(df: DataFrame, path: str, checkpoint: str):
    """A stream of windows; each batch has a folder of its own, so that a repeated batch replaces itself."""
    return df.writeStream.option("checkpointLocation", checkpoint).foreachBatch(lambda b, i: b.write.mode("overwrite").parquet(f"{path}/batch={i}")).start()
