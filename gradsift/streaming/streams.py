"""Streams of training data: rating, selection, windows over traces, joins, state per source.

Stateless parts (rating, percentiles from a snapshot's cuts, hash inclusion) give the same
rows on a replay. Event times must be timestamps with a zone to take a watermark; events
store them without, so they are cast first.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQueryListener
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql import types as T

from gradsift.functions.hashing import hash_uniform
from gradsift.operators.pruning import ShiftedGaussian, density
from gradsift.operators.ranking import approx_percentile_of
from gradsift.sources.staging import shared_dir


def file_stream(spark: SparkSession, path: str, per_trigger: int = 1) -> DataFrame:
    """A Parquet file or folder as a stream of files."""
    schema = spark.read.parquet(path).schema
    folder, _, name = path.rpartition("/")
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).option("pathGlobFilter", name if "." in name else "*").parquet(folder if "." in name else path)


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    source = spark.readStream.schema(schema).parquet(f"{sf_dir}/events.parquet*")
    return source.withColumn("ts", F.col("ts").cast("timestamp"))


def stream_rate(sdf: DataFrame, raw: Column) -> DataFrame:
    return sdf.withColumn("score", raw)


def stream_select(sdf: DataFrame, cuts: list[float], id_col: str, cfg: ShiftedGaussian = ShiftedGaussian(), scale: float = 0.4, seed: int = 42, version: str = "0") -> DataFrame:
    """Inclusion by hash with probability min(1, scale g(pct)); rows carry the cuts' version."""
    placed = approx_percentile_of(sdf, "score", cuts)
    keep = hash_uniform(id_col, seed) < F.least(F.lit(1.0), F.lit(scale) * density(F.col("pct"), cfg))
    return placed.where(keep).withColumn("cuts_version", F.lit(version))


def stream_window_loss(sdf: DataFrame, kind: str, size: str = "1 day", slide: str = "12 hours", gap: str = "30 minutes", delay: str = "1 day", keys: tuple[str, ...] = ("event_type",)) -> DataFrame:
    """Rows and mean value by window and keys; late rows beyond the delay are dropped."""
    marked = sdf.withWatermark("ts", delay)
    if kind == "tumbling":
        w = F.window("ts", size)
    elif kind == "sliding":
        w = F.window("ts", size, slide)
    elif kind == "session":
        w = F.session_window("ts", gap)
    else:
        raise ValueError(f"no window kind {kind!r}")
    return marked.groupBy(w.alias("w"), *keys).agg(F.count(F.lit(1)).alias("n"), F.avg("value").alias("mean_value")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *keys, "n", "mean_value")


class LateRows(StreamingQueryListener):
    """Rows that came behind the watermark and were dropped, by stream (query id).

    The counts are those of the operators that hold state, in every batch: where rows are
    aggregated before the exchange, late ones of a key and batch may count as one. Register it
    with spark.streams.addListener; a stream's counts go on after a restart in the session.
    """

    def __init__(self) -> None:
        self.dropped: dict[str, int] = {}

    def onQueryStarted(self, event) -> None:
        self.dropped.setdefault(str(event.id), 0)

    def onQueryProgress(self, event) -> None:
        name, lost = str(event.progress.id), sum(o.numRowsDroppedByWatermark for o in event.progress.stateOperators)
        self.dropped[name] = self.dropped.get(name, 0) + lost

    def onQueryIdle(self, event) -> None:
        pass

    def onQueryTerminated(self, event) -> None:
        pass


def stream_dedup(sdf: DataFrame, id_cols: list[str], delay: str = "1 day") -> DataFrame:
    return sdf.withWatermark("ts", delay).dropDuplicatesWithinWatermark(id_cols)


def stream_static_join(sdf: DataFrame, static: DataFrame, on: list[str]) -> DataFrame:
    return sdf.join(static, on, "left")


def stream_join_loss(emitted: DataFrame, reported: DataFrame, within: str = "1 hour", delay: str = "1 day") -> DataFrame:
    """Samples (user_id, ts) with losses reported for them within a time; both sides are bounded by it."""
    a = emitted.select(F.col("user_id"), F.col("event_id").alias("emitted_id"), F.col("ts").alias("emitted_at")).withWatermark("emitted_at", delay)
    b = reported.select(F.col("user_id").alias("_user"), F.col("event_id").alias("reported_id"), F.col("ts").alias("reported_at"), F.col("value").alias("loss")).withWatermark("reported_at", delay)
    near = (F.col("user_id") == F.col("_user")) & (F.col("reported_at") >= F.col("emitted_at")) & F.expr(f"reported_at <= emitted_at + INTERVAL {within}")
    return a.join(b, near).drop("_user")


class _SourceSketch(StatefulProcessor):
    """Count, sum and the largest scores of a source; the state has a fixed size."""

    KEEP = 32

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("sketch", T.StructType([T.StructField("n", T.LongType()), T.StructField("total", T.DoubleType()), T.StructField("top", T.ArrayType(T.DoubleType()))]))

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        n, total, top = self.state.get() if self.state.exists() else (0, 0.0, [])
        top = list(top)
        for f in rows:
            n, total = n + len(f), total + float(f["score"].sum())
            top = sorted([*top, *f["score"].tolist()], reverse=True)[: self.KEEP]
        self.state.update((n, total, top))
        yield pd.DataFrame({"source": [key[0]], "n": [n], "mean_score": [total / n], "best": [top[0]]})

    def close(self) -> None:
        pass


def stateful_source_sketch(sdf: DataFrame) -> DataFrame:
    """sdf: source, score. After each batch, a row for each source that it touched.

    Needs spark.sql.streaming.stateStore.providerClass set to the RocksDB provider.
    """
    return sdf.groupBy("source").transformWithStateInPandas(_SourceSketch(), "source string, n long, mean_score double, best double", "Update", "None")


def each_batch_once(path: str) -> Callable[[DataFrame, int], None]:
    """A foreachBatch sink that writes a batch to a folder of its number, so a replay replaces it."""

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return write


def online_rater(path: str, update: Callable[[DataFrame, list[float]], list[float]], start: list[float]) -> Callable[[DataFrame, int], None]:
    """A foreachBatch step for the rater; parameters are rows keyed by the batch number.

    A replayed batch starts from the parameters before it and overwrites its own row.
    """

    def step(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        mu = start
        if number:
            try:
                mu = spark.read.parquet(f"{path}/step={number - 1}").first()["mu"]
            except Exception as e:
                raise RuntimeError(f"the parameters of step {number - 1} are gone") from e
        new = update(batch, list(mu))
        spark.createDataFrame([(number, [float(x) for x in new])], "number long, mu array<double>").coalesce(1).write.mode("overwrite").parquet(f"{path}/step={number}")

    return step


def drain(sdf: DataFrame, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Runs a stream over what is there and returns the result as a table.

    Each batch is a folder of the shared directory, which a replay overwrites; in complete
    mode the last one is the result. Nothing passes the driver.
    """
    spark = sdf.sparkSession
    root = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    last = [-1]

    def write(batch: DataFrame, number: int) -> None:
        last[0] = number
        batch.write.mode("overwrite").parquet(f"{root}/rows/batch={number}")

    query = sdf.writeStream.foreachBatch(write).outputMode(mode).trigger(availableNow=True)
    query.option("checkpointLocation", checkpoint or f"{root}/state").start().awaitTermination()
    if last[0] < 0:
        return spark.createDataFrame([], sdf.schema)
    found = spark.read.schema(sdf.schema)
    return found.parquet(f"{root}/rows/batch={last[0]}" if mode == "complete" else f"{root}/rows").select(*sdf.columns)
