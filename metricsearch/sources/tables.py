"""Reading and writing tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

READERS = ("parquet", "orc", "json", "csv", "text")


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A given table, with only the columns asked for in the scan."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_any(spark: SparkSession, path: str, form: str, schema=None, **options) -> DataFrame:
    if form not in READERS:
        raise ValueError(f"no reader for {form!r}")
    reader = spark.read.format(form).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def write_any(df: DataFrame, path: str, form: str, mode: str = "errorifexists", by: list[str] | None = None, **options) -> None:
    """Write a table; with ``mode='parts'`` only the partitions that ``df`` has are replaced."""
    if form not in (*READERS, "noop"):
        raise ValueError(f"no writer for {form!r}")
    writer = df.write.format(form).options(**options)
    if mode == "parts":
        writer, mode = writer.option("partitionOverwriteMode", "dynamic"), "overwrite"
    (writer.partitionBy(*by) if by else writer).mode("overwrite" if form == "noop" else mode).save(path if form != "noop" else None)


def sink_noop(df: DataFrame) -> None:
    """Run a plan to its end and keep nothing."""
    write_any(df, "", "noop")
