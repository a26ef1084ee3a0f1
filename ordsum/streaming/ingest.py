"""Streams into maps: batched, idempotent updates, and a keyed running sum."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ordsum.sources.store import VersionStore


def ingest(stream: DataFrame, store: VersionStore, checkpoint: str, h=None, order: str | None = None):
    """Each micro-batch (k, v) becomes one version; a replayed batch changes nothing.

    Repeated keys of a batch are folded by h in the order of column `order` (of the values, where none
    is named); without h the last of that order stays. A store whose keys have several entries takes every row. Batches are known by the checkpoint's place and
    their number, so a second stream, or one begun anew with another checkpoint, is not taken for a replay."""
    last = order or "v"

    def one(batch: DataFrame, batch_id: int) -> None:
        if store.snapshot().many:
            rows = batch.select("k", "v")
        elif h is None:
            rows = batch.groupBy("k").agg(F.max_by("v", F.struct(last, "v")).alias("v"))
        else:
            listed = F.transform(F.array_sort(F.collect_list(F.struct(F.col(last).alias("o"), "v"))), lambda x: x["v"])
            tail = F.slice(listed, F.lit(2), F.greatest(F.size(listed), F.lit(1)))
            rows = batch.groupBy("k").agg(F.aggregate(tail, F.element_at(listed, 1), lambda s, x: h(s, x)).alias("v"))
        if not rows.isEmpty():
            store.insert_many(rows, h, tag=(checkpoint, batch_id))

    return stream.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def running_sums(stream: DataFrame) -> DataFrame:
    """(user_id, n, total) after each micro-batch, with the sum kept as state. stream: user_id, v."""

    def step(key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, total = state.get if state.exists else (0, 0)
        for b in batches:
            n, total = n + len(b), total + int(b["v"].sum())
        state.update((n, total))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "total": [total]})

    return stream.groupBy("user_id").applyInPandasWithState(step, "user_id bigint, n bigint, total bigint", "n bigint, total bigint", "update", "NoTimeout")


def late_filtered(stream: DataFrame, ts: str, delay: str, every: str) -> DataFrame:
    """Counts per window, rows later than the watermark dropped."""
    return stream.withWatermark(ts, delay).groupBy(F.window(ts, every)).count()
