"""Reading tables and features, writing models, histories and assignments."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A Parquet table, with only the named columns where any are named."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_any(spark: SparkSession, path: str, fmt: str = "parquet", schema=None, **options) -> DataFrame:
    """Parquet, ORC, JSON or CSV with a declared schema; ``table`` reads a catalog table."""
    if fmt == "table":
        return spark.read.table(path)
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write_any(df: DataFrame, path: str, fmt: str = "parquet", partition_by: tuple[str, ...] = (), **options) -> None:
    df.write.mode("overwrite").format(fmt).options(**options).partitionBy(*partition_by).save(path)


def write_assignments(assigned: DataFrame, path: str) -> None:
    """Assignments in one folder per regime, so that a reader of one regime scans only its files."""
    assigned.repartition("node").write.mode("overwrite").partitionBy("node").parquet(path)


def run_to_nowhere(df: DataFrame) -> None:
    """Runs the whole plan and keeps nothing: what timings use."""
    df.write.format("noop").mode("overwrite").save()
