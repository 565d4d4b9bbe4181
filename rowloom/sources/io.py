"""Reading tables and writing reordered ones."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table, with its timestamps as TIMESTAMP (they are stored without zone; sessions use UTC)."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_any(spark: SparkSession, path: str, kind: str = "parquet", schema: str | None = None, **options) -> DataFrame:  # noqa: ANN003
    """Parquet, CSV, JSON, ORC or text; formats without a schema of their own want one."""
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def values(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def write_ordered(df: DataFrame, path: str, rows_per_file: int = 131_072, kind: str = "parquet", partition_by: list[str] | None = None) -> None:
    """Files in position order, `rows_per_file` rows each, so that footers' minima and maxima prune."""
    dealt = df.repartitionByRange("pos").sortWithinPartitions("pos")
    writer = dealt.write.format(kind).option("maxRecordsPerFile", rows_per_file).mode("overwrite")
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def write_bucketed(df: DataFrame, table: str, by: str, buckets: int = 16) -> None:
    """A catalog table bucketed and sorted by one column, for joins without a shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, by).sortBy(by).saveAsTable(table)


def sink_noop(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def stored_bytes(spark: SparkSession, path: str) -> int:
    """Bytes of the data files under a path, by Spark's own file metadata."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.parquet").load(path)
    return int(files.select("length").agg(F.sum("length")).first()[0] or 0)


def parquet_bytes(df: DataFrame, path: str, cols: list[str], codec: str = "snappy") -> int:
    """Bytes on disk of `cols` written as Parquet in position order."""
    dealt = df.repartitionByRange("pos").sortWithinPartitions("pos").select(*cols)
    dealt.write.mode("overwrite").option("compression", codec).parquet(path)
    return stored_bytes(df.sparkSession, path)
