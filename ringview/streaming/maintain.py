"""Streams of changes into maintained views; windows as key variables; streaming baselines."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Sequence

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupStateTimeout

from ringview.operators.engine import Engine
from ringview.operators.relation import SIGN


class StreamMaintainer:
    """Applies micro-batches of relations to an engine, each batch number of a stream once: the store commits it with the
    views, so after a restart a batch that comes again is passed over.  Changes commute, so late rows are later changes;
    no watermark is needed for the views themselves."""

    def __init__(self, engine: Engine, on_batch: Callable[[Engine, int], object] | None = None):
        self.engine, self.on_batch = engine, on_batch

    def start(self, relation: str, stream: DataFrame, checkpoint: str, available_now: bool = True, **trigger) -> StreamingQuery:
        def batch(df: DataFrame, number: int) -> None:
            if self.engine.apply(relation, df if SIGN in df.columns else df.withColumn(SIGN, F.lit(1)), (relation, number)):
                self.engine.store.force()  # the views are brought up to date while the micro-batch is there
                if self.on_batch:
                    self.on_batch(self.engine, number)

        writer = stream.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint)
        return (writer.trigger(availableNow=True) if available_now else writer.trigger(**trigger)).start()


def windowed(df: DataFrame, ts: str, length: str, slide: str | None = None, name: str = "win") -> DataFrame:
    """The window's start as one more key variable; a row is in each sliding window that has it."""
    return df.withColumn(name, F.window(F.col(ts).cast("timestamp"), length, slide or length)["start"])


def expired(df: DataFrame, name: str, before) -> DataFrame:
    """Rows of windows that are over, as deletes."""
    return df.where(F.col(name) < F.lit(before)).withColumn(SIGN, F.lit(-1))


def sessions(df: DataFrame, ts: str, gap: str, keys: Sequence[str], delay: str | None = None) -> DataFrame:
    """(keys, start, end, n) of sessions, batch or stream."""
    df = df.withColumn("__ts", F.col(ts).cast("timestamp"))
    df = df.withWatermark("__ts", delay) if delay else df
    return df.groupBy(*keys, F.session_window("__ts", gap).alias("s")).agg(F.count("*").alias("n")).select(*keys, F.col("s.start").alias("start"), F.col("s.end").alias("end"), "n")


def deduplicated(stream: DataFrame, id_cols: Sequence[str], ts: str, delay: str) -> DataFrame:
    """Changes that arrive twice within the delay count once; the watermark only bounds this state."""
    return stream.withColumn("__ts", F.col(ts).cast("timestamp")).withWatermark("__ts", delay).dropDuplicatesWithinWatermark(list(id_cols)).drop("__ts")


def support_transitions(stream: DataFrame, keys: Sequence[str]) -> DataFrame:
    """(keys, __m): +1 when a key's count leaves zero, -1 when it returns; the count is the stream's state."""
    kinds = dict(stream.dtypes)
    schema = ", ".join([*(f"{k} {kinds[k]}" for k in keys), f"{SIGN} int"])

    def step(key: tuple, batches: Iterable[pd.DataFrame], state) -> Iterable[pd.DataFrame]:
        old = state.get[0] if state.exists else 0
        new = old + int(sum(b[SIGN].sum() for b in batches))
        state.update((new,))
        if (old == 0) != (new == 0):
            yield pd.DataFrame([[*key, 1 if new else -1]], columns=[*keys, SIGN])

    return stream.groupBy(*keys).applyInPandasWithState(step, schema, "n long", "append", GroupStateTimeout.NoTimeout)


def joined_streams(streams: Sequence[DataFrame], on: Sequence[str]) -> DataFrame:
    """The contrast: a left-deep join of streams, aggregated at the root."""
    out = streams[0]
    for s in streams[1:]:
        out = out.join(s, list(on))
    return out
