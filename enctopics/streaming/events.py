"""Tables as streams of files: windows that close, duplicates within a watermark, joins with tables and other streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from enctopics.session import new_path
from enctopics.sources.sinks import Versions

#: How late a row may come.
LATE = "1 hour"


def arriving(spark: SparkSession, path: str, files_per_trigger: int | None = None) -> DataFrame:
    """A Parquet table, a folder or a single file, file by file or all that is there at once."""
    reader = spark.readStream.schema(spark.read.parquet(path).schema)
    path = path.rstrip("/")
    pattern = f"{path[:-1]}[{path[-1]}]"  # as a plain path a single file is refused
    return (reader.option("maxFilesPerTrigger", files_per_trigger) if files_per_trigger else reader).parquet(pattern)


def timed(stream: DataFrame, at: str = "ts", late: str = LATE) -> DataFrame:
    return stream.withColumn(at, F.col(at).cast("timestamp")).withWatermark(at, late)


def closed_windows(events: DataFrame, by: str, width: str = "1 hour", at: str = "ts") -> DataFrame:
    """start, by, n: each window once, when the watermark has passed its end; rows that come after are dropped."""
    return events.groupBy(F.window(at, width).alias("w"), by).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), by, "n")


def once(events: DataFrame, *by: str) -> DataFrame:
    """The first row with each key, and further ones only after the watermark has left it behind."""
    return events.dropDuplicatesWithinWatermark([*by])


def followed(events: DataFrame, others: DataFrame, by: str, name: str, within: str, at: str = "ts") -> DataFrame:
    """by, first, next: rows of two streams with one key, the second later by no more than within; state is held no longer."""
    a = events.select(F.col(by).alias("__a"), F.col(name).alias("first"), F.col(at).alias("__at"))
    b = others.select(F.col(by).alias("__b"), F.col(name).alias("next"), F.col(at).alias("__then"))
    near = (F.col("__a") == F.col("__b")) & (F.col("__then") > F.col("__at")) & (F.col("__then") <= F.col("__at") + F.expr(f"INTERVAL {within}"))
    return a.join(b, near).select(F.col("__a").alias(by), "first", "next")


def appended(stream: DataFrame) -> DataFrame:
    """All rows that a stream in append mode gives until no file is left."""
    spark = stream.sparkSession
    out = new_path(spark, "stream")
    stream.writeStream.format("parquet").outputMode("append").option("checkpointLocation", new_path(spark, "marks")).trigger(availableNow=True).start(out).awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def complete(stream: DataFrame) -> DataFrame:
    """The result of a stream in complete mode after its last file; a micro-batch that runs again writes its version again."""
    spark = stream.sparkSession
    versions = Versions(spark, new_path(spark, "running"))
    keep = lambda df, batch_id: versions.write(batch_id, rows=df)
    stream.writeStream.foreachBatch(keep).outputMode("complete").option("checkpointLocation", new_path(spark, "marks")).trigger(availableNow=True).start().awaitTermination()
    return spark.createDataFrame([], stream.schema) if versions.latest() is None else versions.read("rows")
