"""Structured Streaming around the clusterers: one micro-batch (or one event-time window) is one batch of the stream.

foreachBatch may run a micro-batch again after a failure. A step is skipped if its batch number was committed before, and all
its writes go to partitions named by that number, so a replay changes nothing.
"""

from __future__ import annotations

import json
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery, StreamingQueryListener

from fadestream.functions import vectors as V
from fadestream.functions.kernels import fading, nearest
from fadestream.operators.distance import block
from fadestream.operators.engine import FadingClusterer, StepResult
from fadestream.operators.lloyd import LocalWindow, lloyd
from fadestream.operators.seeding import local_kmpp
from fadestream.operators.starts import POLICIES, fresh_centres, past_centres


def file_stream(spark, path: str, schema: str, files_per_trigger: int = 1) -> DataFrame:  # noqa: ANN001
    """Arriving files; with one file a trigger, a file is a batch."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def fit_stream(points: DataFrame, clusterer: FadingClusterer, checkpoint: str, on_step: Callable[[StepResult], None] | None = None, **trigger) -> StreamingQuery:  # noqa: ANN003
    """Step the clusterer for each micro-batch of points (point_id, x). A clusterer with a store resumes where it stopped."""
    done = clusterer.resume() if clusterer.store is not None else None
    state = {"done": -1 if done is None else done}

    def step(batch: DataFrame, epoch: int) -> None:
        if epoch <= state["done"]:
            return
        result = clusterer.step(batch, epoch)
        state["done"] = epoch
        if result is not None and on_step is not None:
            on_step(result)

    return points.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


def fit_event_time(events: DataFrame, ts: str, width_seconds: int, t_max: int, sink: Callable[[DataFrame, int], None], late: Callable[[DataFrame, int], None], checkpoint: str, **trigger) -> StreamingQuery:  # noqa: ANN003
    """Event-time batches: batch_seq is the number of the row's own window. Rows of windows that are still retained go to sink with
    that number, whenever they come; rows of windows that have left (t_max behind the newest seen) go to late. The newest window
    seen is written beside the checkpoint after each micro-batch, in two folders taken in turn, so late rows stay late after a
    restart and a micro-batch that runs again is routed as it was."""
    newest = {"epoch": None, "seq": None}
    folder = f"{checkpoint.rstrip('/')}/newest_window"

    def restored(spark: SparkSession, epoch: int) -> int | None:
        try:
            marks = spark.read.schema("epoch long, seq long").parquet(folder)
        except AnalysisException as e:
            if e.getCondition() != "PATH_NOT_FOUND":
                raise
            return None
        return marks.where(F.col("epoch") < epoch).agg(F.max("seq")).first()[0]

    def route(batch: DataFrame, epoch: int) -> None:
        tagged = batch.withColumn("batch_seq", F.floor(F.unix_timestamp(F.col(ts).cast("timestamp")) / width_seconds).cast("long")).persist()
        top = tagged.agg(F.max("batch_seq")).first()[0]
        before = newest["seq"] if newest["epoch"] == epoch - 1 else restored(batch.sparkSession, epoch)
        if top is not None:
            left = F.lit(False) if before is None else F.col("batch_seq") <= before - t_max
            sink(tagged.where(~left), epoch)
            late(tagged.where(left), epoch)
            before = top if before is None else max(top, before)
        mark = batch.sparkSession.range(1).select(F.lit(epoch).cast("long").alias("epoch"), F.lit(before).cast("long").alias("seq"))
        mark.write.mode("overwrite").parquet(f"{folder}/turn={epoch % 2}")
        newest.update(epoch=epoch, seq=before)
        tagged.unpersist()

    return events.writeStream.foreachBatch(route).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


KEYED_OUT = "key string, batch_seq long, k int, n long, c array<double>, faded_error double, iterations int"


def _packed(points: DataFrame, key: str) -> DataFrame:
    """key, d, xs: the points of a key in an Arrow batch as one row of bytes. A group goes to its function in chunks of rows, each with
    the key's whole state, so groups should have few rows."""
    rows = points.select(F.col(key).cast("string").alias("key"), "x")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            d = len(b.column(1)[0])
            x, told = block(b.column(1), d), b.column(0).dictionary_encode(null_encoding="encode")
            at = told.indices.to_numpy()
            xs = [x[at == i].tobytes() for i in range(len(told.dictionary))]
            yield pa.RecordBatch.from_arrays([told.dictionary, pa.array([d] * len(xs), pa.int32()), pa.array(xs, pa.binary())], names=["key", "d", "xs"])

    return rows.mapInArrow(run, "key string, d int, xs binary")


def fit_keyed(points: DataFrame, key: str, k: int, rho: float, t_max: int, start: str = "pair", seed: int = 0) -> DataFrame:
    """One fading model a key, in keyed state; every micro-batch in which a key has rows is a batch of that key's stream.

    State holds the points of the key that the next batch finds retained (t_max - 1 batches) and its last model. One exchange by key, no
    driver step.
    """
    schema = "seq long, models string, seqs binary, xs binary"  # numbers as bytes: a list of lists costs an object a coordinate

    def step(group: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:  # noqa: ANN001
        parts = [np.frombuffer(xs).reshape(-1, d) for f in frames for d, xs in zip(f["d"], f["xs"], strict=True)]
        seq, model, seqs, xs = state.get if state.exists else (-1, "", b"", b"")
        if not parts:
            return
        new = np.concatenate(parts)
        new = new[np.lexsort(new.T[::-1])]
        seq += 1
        sizes, x = np.frombuffer(seqs, dtype=np.int64).reshape(-1, 2), np.frombuffer(xs).reshape(-1, new.shape[1])
        x, seqs = np.concatenate([x, new]), np.concatenate([np.repeat(sizes[:, 0], sizes[:, 1]), np.full(len(new), seq)])
        rng = np.random.default_rng([seed, seq, _crc(group[0])])
        window = LocalWindow(x, seqs)
        weights = lambda s: fading(s, seq, rho)
        newest = LocalWindow(new, np.full(len(new), seq))
        if model:
            before = np.array(json.loads(model))
            sums = window.passes([before])[0]
            past = past_centres(before, sums, seq, rho, t_max, False)
            fresh, _ = fresh_centres(newest, local_kmpp(new, k, rng))
            c0 = POLICIES[start]().start(past, fresh, float(past.w.sum() + len(new)), rng).c
        else:
            c0 = local_kmpp(new, k, rng)
        r = lloyd(window, c0, weights)
        keep = seqs > seq + 1 - t_max
        sizes = np.column_stack(np.unique(seqs[keep], return_counts=True)).astype(np.int64)
        state.update((seq, json.dumps(r.centroids.tolist()), sizes.tobytes(), np.ascontiguousarray(x[keep]).tobytes()))
        n = r.sums.n.sum(axis=0)
        yield pd.DataFrame(
            {"key": [str(group[0])] * k, "batch_seq": [seq] * k, "k": range(k), "n": n.astype(int), "c": r.centroids.tolist(), "faded_error": [r.errors[-1]] * k, "iterations": [r.iterations] * k}
        )

    return _packed(points, key).groupBy("key").applyInPandasWithState(step, KEYED_OUT, schema, "append", "NoTimeout")


def _crc(text: object) -> int:
    import zlib

    return zlib.crc32(str(text).encode())


def score_stream(points: DataFrame, centroids: np.ndarray) -> DataFrame:
    """points with k and d2 under a fixed model: stays in generated code."""
    near = V.nearest_struct(F.col("x"), centroids)
    return points.withColumn("__n", near).select(*points.columns, F.col("__n.k").alias("k"), F.col("__n.d2").alias("d2"))


def drift_ratio(batch: np.ndarray, window: np.ndarray, centroids: np.ndarray) -> float:
    """Error of a new batch under the present model over that of the window, less 1."""
    return float(nearest(batch, centroids)[1].mean() / nearest(window, centroids)[1].mean() - 1)


def deduplicated(events: DataFrame, ts: str, key: str, delay: str) -> DataFrame:
    """First row of each key within the watermark's delay."""
    stamped = events.withColumn(ts, F.col(ts).cast("timestamp"))
    return stamped.withWatermark(ts, delay).dropDuplicatesWithinWatermark([key])


def with_late_labels(events: DataFrame, labels: DataFrame, key: str, ts: str, label_ts: str, delay: str) -> DataFrame:
    """Stream-stream join: labels that arrive within `delay` after their event."""
    e = events.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, delay)
    lab = labels.withColumn(label_ts, F.col(label_ts).cast("timestamp")).withWatermark(label_ts, delay)
    on = (e[key] == lab[key]) & (lab[label_ts] >= e[ts]) & (lab[label_ts] <= e[ts] + F.expr(f"INTERVAL {delay}"))
    return e.join(lab, on).drop(lab[key])


class Progress(StreamingQueryListener):
    """Collects rows and durations of every finished micro-batch."""

    def __init__(self) -> None:
        self.rows: list[dict] = []

    def onQueryStarted(self, event) -> None:  # noqa: ANN001, N802
        pass

    def onQueryProgress(self, event) -> None:  # noqa: ANN001, N802
        p = event.progress
        self.rows.append({"batch": p.batchId, "rows": p.numInputRows, "ms": p.durationMs.get("triggerExecution", 0)})

    def onQueryIdle(self, event) -> None:  # noqa: ANN001, N802
        pass

    def onQueryTerminated(self, event) -> None:  # noqa: ANN001, N802
        pass
