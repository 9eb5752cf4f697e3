"""Sources and sinks: the given tables, edge lists in several formats, and where models, traces and reports go."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EDGE_SCHEMA = "src int, dst int, w double"
EXPERT_SCHEMA = "report_id long, category string"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def edge_list(spark: SparkSession, path: str, kind: str = "csv", header: bool = True) -> DataFrame:
    """EDGES from CSV, JSON lines, ORC or Parquet, by an explicit schema: nothing is inferred."""
    reader = spark.read.schema(EDGE_SCHEMA)
    return reader.option("header", header).csv(path) if kind == "csv" else getattr(reader, {"json": "json", "orc": "orc", "parquet": "parquet"}[kind])(path)


def expert_labels(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(EXPERT_SCHEMA).option("header", True).csv(path)


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The log with a zoned ``ts`` and the number ``k`` of its properties."""
    raw = table(spark, sf_dir, "events")
    return raw.withColumns({"ts": F.col("ts").cast("timestamp"), "k": F.get_json_object("props", "$.k").cast("int")})


def event_stream(spark: SparkSession, folder: str, files_per_trigger: int = 1, pattern: str = "*.parquet") -> DataFrame:
    """The log as a stream of the Parquet files of a folder whose names match ``pattern``."""
    schema = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", pattern).parquet(folder)
    return raw.withColumns({"ts": F.col("ts").cast("timestamp"), "k": F.get_json_object("props", "$.k").cast("int")})


def write_model(edges: DataFrame, path: str, run_id: str) -> None:
    """A learned graph, partitioned by run: reading one run prunes the others."""
    edges.withColumn("run_id", F.lit(run_id)).write.mode("append").partitionBy("run_id").parquet(path)


def write_trace(trace: DataFrame, path: str, run_id: str) -> None:
    trace.withColumn("run_id", F.lit(run_id)).write.mode("append").partitionBy("run_id").parquet(path)


def write_reports(paths: DataFrame, path: str) -> None:
    """Alarms as JSON lines."""
    paths.select(F.to_json(F.struct(*paths.columns)).alias("value")).write.mode("append").text(path)


def bucketed(frame: DataFrame, name: str, key: str, buckets: int) -> None:
    """A table bucketed by its join key, so that later joins on it need no shuffle."""
    frame.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)
