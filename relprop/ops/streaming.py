"""Streaming: windows over late data, duplicates, maintained neighbour aggregates, joins and scoring."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType


def shared_folder(spark) -> str:
    """The folder named in spark.checkpoint.dir; one of this machine only where Spark runs on this machine alone."""
    import tempfile

    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isDefined():
        return sc._jsc.sc().getCheckpointDir().get()
    folder = sc.getConf().get("spark.checkpoint.dir")
    if not folder and not sc.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    return folder or tempfile.mkdtemp(prefix="ckpt-")


def stream_table(spark: SparkSession, path: str, schema: StructType, ts: str | None = None, late: str = "1 day", max_files: int | None = None) -> DataFrame:
    """A Parquet folder as a stream.  ``ts`` is cast to an instant (a watermark needs one) and gets a watermark."""
    reader = spark.readStream.schema(schema)
    df = (reader.option("maxFilesPerTrigger", max_files) if max_files else reader).parquet(path)
    return df.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, late) if ts else df


def windowed_features(stream: DataFrame, key: str, ts: str, value: str, kind: str = "tumbling", size: str = "1 day", slide: str = "6 hours") -> DataFrame:
    """key, start, end, n, total: per key and tumbling, sliding or session window."""
    w = {"tumbling": lambda: F.window(ts, size), "sliding": lambda: F.window(ts, size, slide), "session": lambda: F.session_window(ts, size)}[kind]()
    g = stream.groupBy(key, w.alias("w")).agg(F.count("*").alias("n"), F.sum(value).alias("total"))
    return g.select(key, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "total")


def dedup_stream(stream: DataFrame, key: str) -> DataFrame:
    return stream.dropDuplicatesWithinWatermark([key])


def incremental_stats(stream: DataFrame, fk: str, value: str) -> DataFrame:
    """key, n, total, low, high maintained per referenced row; means follow from them.  All four merge."""
    return stream.filter(F.col(fk).isNotNull()).groupBy(F.col(fk).alias("key")).agg(F.count("*").alias("n"), F.sum(value).alias("total"), F.min(value).alias("low"), F.max(value).alias("high"))


def enrich_stream(stream: DataFrame, static: DataFrame, column: str, key: str) -> DataFrame:
    """Forward edge of a stream: the referenced static row."""
    return stream.join(static, F.col(column) == F.col(key), "left")


def attribution(left: DataFrame, right: DataFrame, key: str, left_ts: str, right_ts: str, within: str) -> DataFrame:
    """Stream-stream interval join: a right row of the same key within an interval after a left row."""
    r = right.select(F.col(key).alias("_k"), *[F.col(c).alias(f"r_{c}") for c in right.columns if c != key])
    return left.join(r, (F.col(key) == F.col("_k")) & (F.col(f"r_{right_ts}") >= F.col(left_ts)) & (F.col(f"r_{right_ts}") <= F.col(left_ts) + F.expr(f"interval {within}"))).drop("_k")


def run_available(df: DataFrame, name: str, mode: str, checkpoint: str, parts: int | None = None) -> DataFrame:
    """Process what is there into a memory table and return it: for tests and small batches."""
    spark = df.sparkSession
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def run_to_files(df: DataFrame, folder: str, checkpoint: str) -> DataFrame:
    """Process what is there into Parquet files of ``folder`` and return them: rows of an append stream pass by the driver."""
    q = df.writeStream.format("parquet").outputMode("append").option("checkpointLocation", checkpoint).trigger(availableNow=True).start(folder)
    q.awaitTermination()
    return df.sparkSession.read.schema(df.schema).parquet(folder)


def score_stream(stream: DataFrame, key: str, score, sink) -> object:
    """For each batch: rescore the targets it touches.  ``score``: keys -> scored frame; ``sink``: frame, batch number."""

    def each(batch: DataFrame, number: int) -> None:
        keys = batch.select(key).filter(F.col(key).isNotNull()).distinct()
        sink(score(keys), number)

    return stream.writeStream.foreachBatch(each)
