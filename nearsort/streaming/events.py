"""Windows, duplicates, joins and incremental pairs over streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..operators import pairs
from ..operators.layout import ordered, tag
from ..operators.partitioners import Partitioner
from ..plans.durable import fresh


def read_stream(spark: SparkSession, path: str) -> DataFrame:
    """Parquet files as a stream; ``path`` may name one file or a folder."""
    schema = spark.read.parquet(path).schema
    if _is_folder(spark, path):
        return spark.readStream.schema(schema).parquet(path)
    folder, _, name = path.rpartition("/")
    return spark.readStream.schema(schema).option("pathGlobFilter", name).parquet(folder)


def read_events(spark: SparkSession, path: str) -> DataFrame:
    """Events with an event time; times without a zone are taken in the session's."""
    return read_stream(spark, path).withColumn("ts", F.col("ts").cast("timestamp"))


def _is_folder(spark: SparkSession, path: str) -> bool:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()


def run_once(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """All available input, through to a Parquet sink in shared storage, read back."""
    spark = stream.sparkSession
    out = fresh(spark, name)
    query = stream.writeStream.format("parquet").outputMode(mode).option("path", f"{out}/data").option("checkpointLocation", f"{out}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{out}/data")


def tumbling_counts(events: DataFrame, width: str = "1 hour", delay: str = "10 minutes", slide: str | None = None) -> DataFrame:
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.withWatermark("ts", delay).groupBy(w, "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def session_counts(events: DataFrame, gap: str = "30 minutes", delay: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", delay).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select(F.col("session_window.start").alias("start"), "user_id", "n")


def first_of_duplicates(events: DataFrame, keys: list[str], delay: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(keys)


def within(a: DataFrame, b: DataFrame, delta: str = "10 minutes") -> DataFrame:
    """Stream-stream join: events of b at most ``delta`` after one of a, same user."""
    x = a.withWatermark("ts", "10 minutes").select("user_id", F.col("event_id").alias("left_id"), F.col("ts").alias("t1"))
    y = b.withWatermark("ts", "10 minutes").select(F.col("user_id").alias("user"), F.col("event_id").alias("right_id"), F.col("ts").alias("t2"))
    return x.join(y, F.expr(f"user_id = user and t2 > t1 and t2 <= t1 + interval {delta}")).select("left_id", "right_id", "t1", "t2")


def late_rows(query) -> int:  # noqa: ANN001
    """Rows that a finished or running query dropped behind its watermark."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])


class IncrementalPairs:
    """Entities arrive in batches; each batch is merged into the ordered store and gives the pairs with a new row.

    The store lies by partition. A batch reads the partitions that it has rows in, and on both sides as many more as it takes to have
    w - 1 rows there; ranks among these give the true distances of all pairs with a new row. A pair is valid when given: rows that come
    later may push its two apart. A batch that is replayed finds its own rows in the store and replaces its former output, so nothing doubles.
    """

    def __init__(self, spark: SparkSession, partitioner: Partitioner, w: int, folder: str | None = None):
        self.spark, self.partitioner, self.w = spark, partitioner, w
        self.folder = folder or fresh(spark, "pairs")

    def _around(self, store: DataFrame, touched: set[int]) -> list[int]:
        """Partitions that pairs of the touched ones can reach into; one count a partition comes to the driver."""
        rows = {r.p: r.n for r in store.groupBy("p").agg(F.count("*").alias("n")).collect()}
        need = set(touched)
        for p in touched:
            for step in (-1, 1):
                seen, q = 0, p + step
                while seen < self.w - 1 and 0 <= q < self.partitioner.parts:
                    need.add(q)
                    seen, q = seen + rows.get(q, 0), q + step
        return sorted(need)

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        rows = tag(batch.select("id", "k"), self.partitioner).withColumn("batch", F.lit(batch_id).cast("long"))
        rows.write.mode("overwrite").partitionBy("p").parquet(f"{self.folder}/store/b={batch_id}")
        store = self.spark.read.schema("id " + batch.schema["id"].dataType.simpleString() + ", k " + batch.schema["k"].dataType.simpleString() + ", batch long, b int, p int").parquet(f"{self.folder}/store").where(F.col("b") <= batch_id)
        touched = {r.p for r in store.where(F.col("b") == batch_id).select("p").distinct().collect()}
        some = store.where(F.col("p").isin(self._around(store, touched)))
        near = pairs.bucket(ordered(some.select("id", "k", "batch"), self.partitioner), self.w, ("id", "batch"))
        fresh_pairs = near.where(F.greatest("left_batch", "right_batch") == batch_id).select("left_id", "right_id", "distance")
        fresh_pairs.write.mode("overwrite").parquet(f"{self.folder}/out/b={batch_id}")

    def run(self, entities: DataFrame) -> DataFrame:
        """Feed a stream of (id, k) to its end; all pairs given so far."""
        query = entities.writeStream.foreachBatch(self).option("checkpointLocation", f"{self.folder}/state").trigger(availableNow=True).start()
        query.awaitTermination()
        return self.results()

    def results(self) -> DataFrame:
        return self.spark.read.parquet(f"{self.folder}/out").select("left_id", "right_id", "distance")
