"""Streams: encode with a frozen model, suppress near repeats, and aggregate by windows."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from codematch.operators.encode import encode
from codematch.operators.model import CodeModel


def encode_stream(vectors: DataFrame, model: CodeModel) -> DataFrame:
    """Codes of a stream of (id, vec); the same narrow stage as in batch, against a frozen model."""
    return encode(vectors, model)


def append_codes(vectors: DataFrame, model: CodeModel, path: str, checkpoint: str):
    """A running query that appends each micro-batch's codes in the order of cells; a restart goes on from the checkpoint."""

    def put(batch: DataFrame, number: int) -> None:
        # named by the batch: a batch that is repeated replaces its own files
        batch.repartitionByRange("c1", "c2").sortWithinPartitions("c1", "c2").write.mode("overwrite").parquet(f"{path}/batch={number}")

    return encode_stream(vectors, model).writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def events_stream(spark: SparkSession, path: str, schema, late: str = "10 minutes") -> DataFrame:
    """A file stream of events with a watermark; ts is cast, as watermarks need a timestamp with a zone."""
    return spark.readStream.schema(schema).parquet(path).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def windowed_counts(events: DataFrame, width: str, slide: str | None = None) -> DataFrame:
    """(start, event_type, n) by tumbling or sliding windows; rows later than the watermark are dropped."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.groupBy(w, "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def suppress_near_repeats(codes: DataFrame, m: int, t: int, keep: int = 200, ttl_ms: int = 600_000) -> DataFrame:
    """(id) of the items of a stream of (id, c1, c2, fine, ts) that match no remembered item in more than t codes.

    State is kept by cell: the last `keep` items at most, for ttl_ms of event time; so it is
    bounded by cells and not by the stream. Items of other cells are not compared.
    """

    def run(key, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        known = []
        if state.exists:
            flat, at = state.get
            known = [(flat[i * m : (i + 1) * m], x) for i, x in enumerate(at)]
        out = []
        for rows in batches:
            for r in rows.sort_values(["ts", "id"]).itertuples():
                now, fine = int(r.ts.timestamp() * 1000), [int(x) for x in r.fine]
                known = [k for k in known if now - k[1] <= ttl_ms][-keep:]
                if not any(sum(a == b for a, b in zip(k[0], fine, strict=True)) > t for k in known):
                    out.append(int(r.id))
                known.append((fine, now))
        known = known[-keep:]
        state.update(([x for k in known for x in k[0]], [k[1] for k in known]))
        state.setTimeoutTimestamp(max(state.getCurrentWatermarkMs() + ttl_ms, (known[-1][1] if known else 0) + ttl_ms))
        yield pd.DataFrame({"id": pd.Series(out, dtype="int64")})

    return codes.groupBy("c1", "c2").applyInPandasWithState(run, "id long", "fine array<int>, at array<long>", "append", GroupStateTimeout.EventTimeTimeout)
