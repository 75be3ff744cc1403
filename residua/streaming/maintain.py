"""Maximum flow kept up to date from a stream of capacity changes, and the stream operators around it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..graph import FlowState
from ..lineage import folder
from ..solvers import DYNAMIC

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream, with a zoned timestamp that watermarks accept."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", 1).option("pathGlobFilter", "events.parquet").parquet(sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))


def changes(events: DataFrame, n: int = 14) -> DataFrame:
    """Events read as capacity changes of a network of ``n`` vertices."""
    rows = events.select((F.col("user_id") % n).alias("src"), (F.col("event_id") % n).alias("dst"), (1 + F.floor("value") % 100).cast("long").alias("new_cap"), F.col("event_id").alias("seq"), "ts")
    return rows.where("src <> dst")


def last_of_batch(batch: DataFrame) -> DataFrame:
    return batch.groupBy("src", "dst").agg(F.max_by("new_cap", F.struct("ts", "seq")).alias("new_cap")).withColumn("seq", F.lit(0).cast("long"))


class Maintainer:
    """``foreachBatch`` sink that keeps a saved state current. The batch id is stored with the state, so a replayed batch does nothing."""

    def __init__(self, path: str, program: str = "dyn_data"):
        self.path, self.program = path, program

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        mark = f"{self.path}/done"
        known = spark.read.parquet(mark).agg(F.max("batch_id")).first()[0] if exists(spark, mark) else -1
        if batch_id <= known:
            return
        at = spark.read.parquet(mark).orderBy(F.desc("batch_id")).first().state if known >= 0 else f"{self.path}/state-base"
        result = DYNAMIC[self.program](FlowState.load(spark, at), last_of_batch(batch))
        new = f"{self.path}/state-{batch_id}"
        result.state.save(new)
        spark.createDataFrame([(batch_id, new, result.value)], "batch_id long, state string, value long").write.mode("append").parquet(mark)


def keep_current(stream: DataFrame, state: FlowState, program: str = "dyn_data", at: str | None = None) -> DataFrame:
    """Runs a stream of changes ``(src, dst, new_cap, seq, ts)`` into a state; the maximum flow after each batch: ``(batch_id, state, value)``."""
    at = at or folder(stream.sparkSession)
    state.save(f"{at}/state-base")
    writer = stream.writeStream.foreachBatch(Maintainer(at, program)).trigger(availableNow=True)
    writer.option("checkpointLocation", f"{at}-checkpoint").start().awaitTermination()
    return stream.sparkSession.read.parquet(f"{at}/done")


def confirmed(announced: DataFrame, confirmations: DataFrame, within: str = "1 day", late: str = "3650 days") -> DataFrame:
    """Stream-stream join: announcements ``(key, ts)`` with the confirmations of their key that come up to ``within`` later."""
    a = announced.select("key", F.col("seq").alias("announced"), F.col("ts").alias("from")).withWatermark("from", late)
    b = confirmations.select(F.col("key").alias("other"), F.col("seq").alias("confirmed"), F.col("ts").alias("at")).withWatermark("at", late)
    return a.join(b, (F.col("key") == F.col("other")) & F.expr(f"at >= from and at <= from + interval {within}")).select("key", "announced", "confirmed")


def exists(spark: SparkSession, path: str) -> bool:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(p)


def run_to_table(stream: DataFrame, mode: str = "append", at: str | None = None, keys: tuple[str, ...] = ()) -> DataFrame:
    """Everything available now, written as Parquet with a checkpoint beside it, as a table.

    A batch overwrites its own folder, so a replayed one changes nothing; in 'complete' mode the last batch is the result,
    in 'update' mode the last row of each of the ``keys``.
    """
    spark = stream.sparkSession
    at, kind = at or folder(spark), stream.schema
    done: list[int] = []

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{at}/batch={number}")
        done.append(number)

    writer = stream.writeStream.foreachBatch(write).outputMode(mode).trigger(availableNow=True)
    writer.option("checkpointLocation", f"{at}-checkpoint").start().awaitTermination()
    if not done:
        return spark.createDataFrame([], kind)
    if mode == "update":
        rest = [c for c in kind.names if c not in keys]
        rows = spark.read.schema(T.StructType([*kind, T.StructField("batch", T.LongType())])).parquet(at)
        return rows.groupBy(*keys).agg(F.max_by(F.struct(*rest), "batch").alias("last")).select(*keys, "last.*")
    return spark.read.schema(kind).parquet(*[f"{at}/batch={k}" for k in (done if mode != "complete" else done[-1:])])
