"""Scoring of streams: stateless scores, windows with lateness, deduplication, running state, replay."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def with_lateness(df: DataFrame, delay: str, at: str = "ts") -> DataFrame:
    """Event time as a timestamp with a watermark."""
    return df.withColumn(at, F.col(at).cast("timestamp")).withWatermark(at, delay)


def score_windows(df: DataFrame, kind: str, size: str, slide: str | None = None, value: str = "value", at: str = "ts") -> DataFrame:
    """Counts and sums by tumbling, sliding or session window."""
    w = F.session_window(at, size) if kind == "session" else F.window(at, size, slide)
    keys = [w.alias("w"), "user_id"] if kind == "session" else [w.alias("w")]
    return df.groupBy(*keys).agg(F.count("*").alias("n"), F.sum(F.floor(F.col(value) * 100)).alias("cents")).select(
        F.col("w.start").alias("start"), F.col("w.end").alias("end"), *(["user_id"] if kind == "session" else []), "n", "cents"
    )


def dedup(df: DataFrame, key: str) -> DataFrame:
    return df.dropDuplicatesWithinWatermark([key])


def _shared(spark) -> str:
    """The folder that driver and executors share; on a local master a temporary one."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    made = tempfile.mkdtemp(prefix="replay-")
    atexit.register(shutil.rmtree, made, ignore_errors=True)
    return f"file://{made}"


def replay(df: DataFrame, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Run a bounded stream to its end and return what it gave, as a table in the shared folder.

    ``append`` goes to files with a log of what is whole.  In the other modes each micro-batch is a folder of its
    own: all of them are the result of ``update``, the last one that of ``complete``.
    """
    spark = df.sparkSession
    path = f"{_shared(spark)}/replay-{uuid.uuid4().hex}"
    place = checkpoint or f"{path}-state"
    if mode == "append":
        df.writeStream.format("parquet").option("path", path).option("checkpointLocation", place).trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(df.schema).parquet(path)
    seen: list[int] = []

    def keep(batch: DataFrame, k: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={k}")
        seen.append(k)

    df.writeStream.outputMode(mode).option("checkpointLocation", place).trigger(availableNow=True).foreachBatch(keep).start().awaitTermination()
    if not seen:
        return spark.createDataFrame([], df.schema)
    chosen = seen[-1:] if mode == "complete" else seen
    return spark.read.schema(df.schema).parquet(*[f"{path}/batch={k}" for k in chosen])


def sink_scores(df: DataFrame, path: str, checkpoint: str, current=None):
    """Each micro-batch overwrites its own folder, so a batch that runs twice is stored once.

    ``current()``, called for every micro-batch, gives the scorer to use, so a new model takes effect without a restart.
    """
    def store(batch: DataFrame, k: int) -> None:
        (current()(batch) if current else batch).write.mode("overwrite").parquet(f"{path}/batch={k}")

    return df.writeStream.option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(store).start()


def enrich(stream: DataFrame, dim: DataFrame, on) -> DataFrame:
    """Stream rows with those of a static table, which is read anew for each micro-batch; no state is kept."""
    return stream.join(dim, on)


def stateful_counts(df: DataFrame, key: str = "user_id", idle_ms: int | None = None) -> DataFrame:
    """Running count and sum of each key, kept as state.

    A key that is silent for ``idle_ms`` (processing time) is forgotten; without it state stays, as a stream
    that is replayed to its end must not wait for time to pass.
    """
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def update(keys, batches, state: GroupState):
        import pandas as pd

        if state.hasTimedOut:
            state.remove()
            return
        n, total = state.get if state.exists else (0, 0)
        for b in batches:
            n += len(b)
            total += int((b["value"] * 100).astype("int64").sum())
        state.update((n, total))
        if idle_ms:
            state.setTimeoutDuration(idle_ms)
        yield pd.DataFrame({key: [keys[0]], "n": [n], "cents": [total]})

    return df.groupBy(key).applyInPandasWithState(update, f"{key} long, n long, cents long", "n long, total long", "update", GroupStateTimeout.ProcessingTimeTimeout if idle_ms else GroupStateTimeout.NoTimeout)
