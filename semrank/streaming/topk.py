"""Streaming forms: a running top-K, top-K per window, and a bin filter with state."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.streaming.query import StreamingQuery

from ..operators import topk
from ..operators.rankers import ListRequest, Ranker
from ..schema import ITEMS, RankParams


def file_stream(spark: SparkSession, sf_dir: str, name: str, files_per_trigger: int = 1) -> DataFrame:
    """A table's files as a stream, with the table's own schema. A table is one file, or a folder of them."""
    table = f"{sf_dir}/{name}.parquet"
    schema = spark.read.parquet(table).schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger)
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(table)
    if path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(path).isDirectory():
        return stream.parquet(table)
    return stream.option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir)


def _state(spark: SparkSession, path: str, version: int) -> DataFrame:
    return spark.read.schema(ITEMS).parquet(f"{path}/v={version}") if version >= 0 else spark.createDataFrame([], ITEMS)


def running_topk(stream: DataFrame, k: int, ranker: Ranker, state_dir: str, params: RankParams | None = None) -> StreamingQuery:
    """Keeps the top k of every scope over all that has arrived; stream: items. The state is a table per batch, so a batch
    that runs twice reads the same state and writes the same one. With a perfect ranker top-k of (A and B) is top-k of (top-k of A, and B)."""
    params = params or RankParams()

    def step(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        pool = _state(spark, state_dir, number - 1).unionByName(batch)
        best = topk.select(pool, k, ranker, params, seed=number).rows
        pool.join(best.select("scope", "id"), ["scope", "id"], "left_semi").write.mode("overwrite").parquet(f"{state_dir}/v={number}")

    return stream.writeStream.foreachBatch(step).option("checkpointLocation", f"{state_dir}/checkpoint").trigger(availableNow=True).start()


def latest_topk(spark: SparkSession, state_dir: str, query: StreamingQuery) -> DataFrame:
    """The state after the query's last batch."""
    return _state(spark, state_dir, query.lastProgress["batchId"] if query.lastProgress else -1)


def windowed(stream: DataFrame, time: str, window: str, slide: str | None = None, gap: str | None = None, delay: str = "1 hour") -> tuple[DataFrame, F.Column]:
    """The stream with a watermark, and the window column: tumbling, sliding, or by session gap."""
    return stream.withWatermark(time, delay), F.session_window(time, gap) if gap else F.window(time, window, slide or window)


def _best(rows: pd.DataFrame, k: int) -> pd.DataFrame:
    return rows.sort_values(["value", "id"], ascending=[False, True], na_position="last").head(k)


def windowed_topk(stream: DataFrame, k: int, key: str, time: str, id_col: str, value: str, window: str, slide: str | None = None, delay: str = "1 hour") -> DataFrame:
    """(key, start, rank, id, value): the k best of each closed window; ties by id, values that are null or NaN last.

    Until a window closes its state is one row with at most k pairs of id and value. Rows count as late by their window's
    end, as they do in an aggregation over windows.
    """
    marked, w = windowed(stream, time, window, slide, delay=delay)
    kinds = {c: stream.schema[c].dataType.simpleString() for c in (key, id_col, value)}
    rows = marked.select(F.col(key).alias("key"), w.alias("w"), F.col(id_col).alias("id"), F.col(value).alias("value")).select("key", F.unix_micros("w.start").alias("start"), F.unix_millis("w.end").alias("end"), F.window_time("w").alias("at"), "id", "value")

    def step(group: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = pd.DataFrame({"id": [], "value": []})
        if state.exists:
            ids, values = state.get
            held = pd.DataFrame({"id": list(ids), "value": list(values)})
        if state.hasTimedOut:
            state.remove()
            yield pd.DataFrame({"key": [group[0]] * len(held), "start": [group[1]] * len(held), "rank": range(1, len(held) + 1), "id": held["id"], "value": held["value"]})
            return
        for part in parts:
            new = part[["id", "value"]]
            held = _best(pd.concat([held, new]) if len(held) else new, k)
        state.update((held["id"].tolist(), [None if pd.isna(x) else x for x in held["value"].tolist()]))
        state.setTimeoutTimestamp(int(group[2]))

    out = f"key {kinds[key]}, start bigint, rank bigint, id {kinds[id_col]}, value {kinds[value]}"
    held = f"ids array<{kinds[id_col]}>, top array<{kinds[value]}>"
    best = rows.groupBy("key", "start", "end").applyInPandasWithState(step, out, held, "append", GroupStateTimeout.EventTimeTimeout)
    return best.withColumn("start", F.timestamp_micros("start")).withColumnRenamed("key", key)


def to_table(stream: DataFrame, path: str, mode: str = "append") -> DataFrame:
    """Runs the stream over what is there and returns what it wrote as Parquet."""
    spark = stream.sparkSession
    query = stream.writeStream.format("parquet").outputMode(mode).option("path", f"{path}/out").option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/out")


def each_batch(stream: DataFrame, path: str, write: Callable[[DataFrame, int], None], mode: str = "update") -> None:
    stream.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).start().awaitTermination()


class _BinProcessor(StatefulProcessor):
    """Buffers the documents of a scope; a full bin is ranked and its survivors go on, a timer flushes what is left."""

    def __init__(self, ranker: Ranker, size: int, survivors: int, flush_ms: int | None):
        self.ranker, self.size, self.survivors, self.flush_ms = ranker, size, survivors, flush_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.buffer = handle.getListState("buffer", "id bigint, payload string, score double")

    def _rank(self, key: tuple, rows: list[tuple]) -> pd.DataFrame:
        ids = [r[0] for r in rows]
        order = self.ranker.rank([ListRequest(f"{key[0]}:{min(ids)}", ids, [r[1] for r in rows], [r[2] for r in rows])])[0] if len(rows) > 1 else [0]
        best = [rows[p] for p in order[: self.survivors]]
        return pd.DataFrame({"scope": [key[0]] * len(best), "id": [b[0] for b in best], "n_items": [len(rows)] * len(best)})

    def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802
        held = [tuple(x) for x in self.buffer.get()] if self.buffer.exists() else []
        for part in rows:
            clean = part[["id", "payload", "score"]].astype(object).where(part[["id", "payload", "score"]].notna(), None)
            for r in clean.itertuples(index=False):
                held.append((int(r[0]), r[1], r[2]))
                if len(held) == self.size:
                    yield self._rank(key, held)
                    held = []
        self.buffer.clear()
        if held:
            self.buffer.put(held)
        if held and self.flush_ms is not None:
            for t in list(self.handle.listTimers()):
                self.handle.deleteTimer(t)
            self.handle.registerTimer(timerValues.getCurrentProcessingTimeInMs() + self.flush_ms)
        yield pd.DataFrame({"scope": pd.Series(dtype="int64"), "id": pd.Series(dtype="int64"), "n_items": pd.Series(dtype="int64")})

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:  # noqa: N802
        held = [tuple(x) for x in self.buffer.get()]
        self.buffer.clear()
        if held:
            yield self._rank(key, held)

    def close(self) -> None:
        pass


def stream_filter(stream: DataFrame, size: int, survivors: int, ranker: Ranker, flush_ms: int | None = None) -> DataFrame:
    """(scope, id, n_items) of survivors. stream: items. Needs a state store that keeps lists (RocksDB).

    flush_ms: a partial bin that waited so long is ranked as it is; that needs a trigger by processing time, since a
    query with timers never runs out of batches. Without it a partial bin waits for more documents.
    """
    return stream.groupBy("scope").transformWithStateInPandas(
        statefulProcessor=_BinProcessor(ranker, size, survivors, flush_ms), outputStructType="scope bigint, id bigint, n_items bigint", outputMode="Append", timeMode="None" if flush_ms is None else "ProcessingTime"
    )


def batch_windows(df: DataFrame, k: int, key: str, time: str, id_col: str, value: str, window: str) -> DataFrame:
    """What ``windowed_topk`` gives once all windows are closed."""
    x = df.withColumn("start", F.window(time, window)["start"])
    w = W.partitionBy(key, "start").orderBy(F.desc_nulls_last(F.when(~F.isnan(value), F.col(value))), id_col)
    return x.withColumn("rank", F.row_number().over(w).cast("long")).filter(F.col("rank") <= k).select(key, "start", "rank", F.col(id_col).alias("id"), F.col(value).alias("value"))


def late_rows(query: StreamingQuery) -> int:
    """Rows that came after the watermark had passed them, over the query's recent batches."""
    return sum(o["numRowsDroppedByWatermark"] for p in query.recentProgress for o in p["stateOperators"])
