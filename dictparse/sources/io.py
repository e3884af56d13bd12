"""Reading tables and files, writing factor tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, table: str, columns: list[str] | None = None) -> DataFrame:
    """A table of a data folder, with only the wanted columns read."""
    df = spark.read.parquet(f"{sf_dir.rstrip('/')}/{table}.parquet")
    return df.select(*columns) if columns else df


def read_texts(spark: SparkSession, path: str) -> DataFrame:
    """(id, text) of whole text files, id being the file's path."""
    return spark.read.text(path, wholetext=True).select(F.input_file_name().alias("id"), F.col("value").alias("text"))


def read_bytes(spark: SparkSession, path: str) -> DataFrame:
    """(id, text) of whole files of any kind, each byte as one character."""
    return spark.read.format("binaryFile").load(path).select(F.col("path").alias("id"), F.decode("content", "ISO-8859-1").alias("text"))


def load_any(spark: SparkSession, path: str, fmt: str, schema: str, **options) -> DataFrame:
    """JSON, CSV, ORC or Parquet with a given schema."""
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def write_factors(factors: DataFrame, path: str, ids: list[str], mode: str = "overwrite") -> None:
    """Parquet by scheme, factors of a text together and in order; writing a scheme again replaces only its own part."""
    rows = factors.repartition(*ids).sortWithinPartitions(*ids, "block_id", "x")
    rows.write.mode(mode).option("partitionOverwriteMode", "dynamic").partitionBy("scheme").parquet(path)


def discard(df: DataFrame) -> None:
    """Computes all rows and keeps none."""
    df.write.format("noop").mode("overwrite").save()


def register(spark: SparkSession, sf_dir: str) -> None:
    """All tables as views for SQL."""
    for t in TABLES:
        load(spark, sf_dir, t).createOrReplaceTempView(t)


def stream_events(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """Events as a stream of Parquet files: a folder of them, or a single file, which is taken by name from its folder."""
    schema = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
    reader = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch)
    place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    if place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(place).isDirectory():
        return reader.parquet(path)
    folder, _, name = path.rstrip("/").rpartition("/")
    return reader.option("pathGlobFilter", name).parquet(folder)
