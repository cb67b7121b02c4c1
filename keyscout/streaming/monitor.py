"""Keys on streams: conflict monitors, watermarked duplicate filters, run counters and upkeep of a key set."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyscout.functions.masks import bits, mask_of
from keyscout.operators.discover import DiscoveryOptions, DiscoveryResult, discover_keys


def event_time(df: DataFrame, column: str) -> DataFrame:
    """Watermarks need a timestamp with time zone; a plain one is taken as UTC session time."""
    return df.withColumn(column, F.col(column).cast("timestamp"))


def key_conflicts(stream: DataFrame, columns: Sequence[str]) -> DataFrame:
    """Projections that have occurred more than once so far (update or complete mode)."""
    return stream.groupBy(*columns).agg(F.count("*").alias("n_rows")).where("n_rows > 1")


def conflicts_by_window(stream: DataFrame, columns: Sequence[str], time_column: str, width: str, slide: str | None = None, late: str = "10 minutes", session: bool = False) -> DataFrame:
    """Rows per projection and tumbling, sliding or session window, where there is more than one."""
    timed = event_time(stream, time_column).withWatermark(time_column, late)
    window = F.session_window(time_column, width) if session else F.window(time_column, width, slide) if slide else F.window(time_column, width)
    return timed.groupBy(window.alias("w"), *columns).agg(F.count("*").alias("n_rows")).where("n_rows > 1").select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *columns, "n_rows")


def first_by_key(stream: DataFrame, columns: Sequence[str], time_column: str, late: str = "10 minutes") -> DataFrame:
    """Rows whose projection has not been seen within the watermark (bounded state)."""
    return event_time(stream, time_column).withWatermark(time_column, late).dropDuplicatesWithinWatermark(list(columns))


def run_counters(stream: DataFrame, column: str) -> DataFrame:
    """(value, run, new_pairs) after every batch: a run of c rows that grows to d adds c..d-1 agreeing pairs.

    The sum of new_pairs over all batches is the column's agreeing-pair count, so its
    place against the budget stays known while rows arrive.
    """
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def grow(key, frames: Iterator, state: GroupState):
        import pandas as pd

        before = state.get[0] if state.exists else 0
        after = before + sum(len(f) for f in frames)
        state.update((after,))
        yield pd.DataFrame({"value": [key[0]], "run": [after], "new_pairs": [(after * (after - 1) - before * (before - 1)) // 2]})

    text = stream.select(F.col(column).cast("string").alias("value"))
    return text.groupBy("value").applyInPandasWithState(grow, "value string, run long, new_pairs long", "run long", "update", GroupStateTimeout.NoTimeout)


class KeySetMaintainer:
    """Minimal keys of a growing table, refreshed per micro-batch.

    Rows only arrive, so true masks stay true: the edges of the last result are kept,
    and a batch matters only if a known key now has a conflict.  Then discovery runs
    again; otherwise the keys stand.  ``rows`` is the table all batches are appended to.
    """

    def __init__(self, path: str, options: DiscoveryOptions | None = None):
        self.path, self.options = path, options or DiscoveryOptions()
        self.result: DiscoveryResult | None = None
        self.refreshed = 0

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        batch.write.mode("append").parquet(self.path)
        table = spark.read.parquet(self.path)
        if self.result is not None and all(self._holds(table, batch, k) for k in self.result.keys):
            return
        self.refreshed += 1
        self.result = discover_keys(table, self.options)

    def _holds(self, table: DataFrame, batch: DataFrame, key: int) -> bool:
        """Only projections that occur in the batch can have become duplicates."""
        if not key:
            return False
        columns = [self.result.names[i] for i in bits(key)]
        touched = batch.select(*[F.col(c).alias(f"_{i}") for i, c in enumerate(columns)]).distinct()
        on = F.lit(True)
        for i, c in enumerate(columns):
            on = on & F.col(c).eqNullSafe(F.col(f"_{i}"))
        return not table.join(touched, on, "left_semi").groupBy(*columns).count().where("count > 1").limit(1).count()


def known_masks(result: DiscoveryResult, columns: Sequence[str]) -> int:
    return mask_of(columns, result.names)
