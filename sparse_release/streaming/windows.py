"""Releases of windows of an event stream: each closed window once, with noise that a retried batch repeats."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.prf import uniform
from ..operators.domain import Domain
from ..operators.summaries import Plan, filter_threshold


def window_counts(events: DataFrame, domain: Domain, ts: str = "ts", length: str = "1 day", slide: str | None = None, late: str = "2 hours", session_key: str | None = None) -> DataFrame:
    """(window_start, window_end, cell_id, v) of tumbling, sliding or session windows; rows later than the watermark are dropped by the engine. The same plan runs on a batch."""
    rows = domain.encode(events)
    rows = rows.withWatermark(ts, late) if rows.isStreaming else rows
    if session_key is not None:
        w, keys = F.session_window(ts, length), [session_key]
    else:
        w, keys = F.window(ts, length, slide) if slide else F.window(ts, length), []
    out = rows.groupBy(w.alias("w"), *keys, "cell_id").agg(F.count(F.lit(1)).alias("v"))
    return out.select(F.col("w.start").alias("window_start"), F.col("w.end").alias("window_end"), *keys, "cell_id", "v")


def _slot(ts: str, length_s: int) -> str:
    """SQL: the number of a row's window, whatever the session's time zone."""
    return f"timestampdiff(SECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', CAST({ts} AS TIMESTAMP_NTZ)) div {length_s}"


def release_window(cells: DataFrame, plan: Plan, window: str, cut: int, tau: float) -> DataFrame:
    """One window's filtered sample; its noise depends on seed, window and cell only."""
    own = Plan(**{**plan.__dict__, "release": f"{plan.release}/{window}"})
    return filter_threshold(cells, own, cut, tau).selectExpr(f"'{window}' AS window_start", "cell_id", "value", "weight")


def release_windows(counts: DataFrame, plan: Plan, first: int, windows: int, length_s: int, cut: int, tau: float) -> DataFrame:
    """All closed tumbling windows of a batch in one plan: (window, cell_id, value, weight). A window and a cell are one cell of a larger domain, stated by the first window's
    start (seconds since 1970), how many there are and their length; so empty windows are released as well, and a window's draws are its own. counts: window (seconds),
    cell_id and v, each pair once."""
    inside = counts.where(f"window >= {first} AND window < {first + windows * length_s}").selectExpr(f"(window - {first}) div {length_s} * {plan.m} + cell_id AS cell_id", "v")
    out = filter_threshold(inside, Plan(**{**plan.__dict__, "m": plan.m * windows}), cut, tau)
    return out.selectExpr(f"{first} + cell_id div {plan.m} * {length_s} AS window", f"cell_id % {plan.m} AS cell_id", "value", "weight")


def publish_windows(counts: DataFrame, plan: Plan, cut: int, tau: float, path: str, checkpoint: str, spend: Callable[[str], None] | None = None, once: bool = True) -> StreamingQuery:
    """Writes each closed window's release to path/window_start=...; a batch that is retried writes the same rows over. counts: a streaming frame from window_counts."""

    def publish(batch: DataFrame, batch_id: int) -> None:
        batch = batch.persist()
        try:
            # closed windows of one trigger: a handful, by the watermark's progress
            for row in batch.select(F.date_format("window_start", "yyyy-MM-dd'T'HH-mm-ss").alias("w")).distinct().collect():
                if spend is not None:
                    spend(f"{plan.release}/{row.w}")
                # session windows of several keys may begin together; a release has each cell once
                cells = batch.where(F.date_format("window_start", "yyyy-MM-dd'T'HH-mm-ss") == row.w).groupBy("cell_id").agg(F.sum("v").alias("v"))
                release_window(cells, plan, row.w, cut, tau).drop("window_start").repartitionByRange("cell_id").sortWithinPartitions("cell_id").write.mode("overwrite").parquet(f"{path}/window_start={row.w}")
        finally:
            batch.unpersist()

    writer = counts.writeStream.outputMode("append").foreachBatch(publish).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if once else writer).start()


def bound_stream(events: DataFrame, person: str, rows: int, ts: str = "ts", length_s: int = 86_400, late: str = "2 hours") -> DataFrame:
    """At most `rows` events of each person in each window, in order of arrival: state is a count for each person and open window."""
    columns = events.columns

    def keep(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        have = state.get[0] if state.exists else 0
        for b in batches:
            part = b.head(max(0, rows - have))
            have += len(part)
            yield part[columns]
        state.update((have,))
        state.setTimeoutTimestamp(max(state.getCurrentWatermarkMs() + 1, (int(key[1]) + 1) * length_s * 1000))

    dealt = events.withWatermark(ts, late).withColumn("_w", F.expr(_slot(ts, length_s)))
    return dealt.groupBy(person, "_w").applyInPandasWithState(keep, events.schema, "n int", "append", GroupStateTimeout.EventTimeTimeout)


def bound_batch(events: DataFrame, person: str, rows: int, key: str, seed: str | int = 1, ts: str = "ts", length_s: int = 86_400) -> DataFrame:
    """The same bound on a batch, by hashed draws instead of arrival."""
    from pyspark.sql import Window

    w = Window.partitionBy(person, F.expr(_slot(ts, length_s))).orderBy(F.expr(uniform(seed, "bound", person, key)), key)
    return events.withColumn("_rank", F.row_number().over(w)).where(F.col("_rank") <= rows).drop("_rank")
