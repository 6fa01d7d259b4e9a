"""Keeping views and run segments current from a stream of events."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from runstore.catalog import SCHEMAS, file_system
from runstore.spec import ViewDefinition
from runstore.plans import views


def open_events(spark: SparkSession, folder: str, name: str = "events", files: int = 1) -> DataFrame:
    """A file stream over a table's Parquet file(s), a few files a batch."""
    return spark.readStream.schema(SCHEMAS[name]).option("maxFilesPerTrigger", files).option("pathGlobFilter", f"{name}*.parquet").parquet(folder)


def run_batches(stream: DataFrame, each: Callable[[DataFrame, int], None], checkpoint: str) -> None:
    """Process all there is, batch by batch, and end."""
    q = stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()


class MaintainedView:
    """A view kept by micro-batches: each batch's groups are stored under its id, so a batch that runs again replaces itself.

    Every `every` batches what came before is folded into one snapshot, named by
    the last batch in it; readers merge the newest snapshot with later batches only.
    """

    def __init__(self, catalog, definition: ViewDefinition, derive: Callable[[DataFrame], DataFrame] = lambda df: df, every: int = 16):
        self.catalog, self.definition, self.derive, self.every = catalog, definition, derive, every
        self.path = catalog.path(f"maintained-{definition.name}")

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        delta = views.delta_of(self.definition, self.derive(batch))
        delta.write.mode("overwrite").parquet(f"{self.path}/batch={batch_id}")
        if batch_id % self.every == self.every - 1:
            self.compact(batch_id)

    def _ids(self, kind: str) -> list[int]:
        fs, at = file_system(self.catalog.spark, self.path)
        names = [f.getPath().getName() for f in fs.listStatus(at)] if fs.exists(at) else []
        return sorted(int(n.split("=")[1]) for n in names if n.startswith(f"{kind}="))

    def _folders(self) -> list[str]:
        snapshot = max(self._ids("snapshot"), default=None)
        later = [f"{self.path}/batch={k}" for k in self._ids("batch") if snapshot is None or k > snapshot]
        return [*([f"{self.path}/snapshot={snapshot}"] if snapshot is not None else []), *later]

    def compact(self, upto: int) -> None:
        """Fold all batches up to one into a snapshot; what it replaces is deleted after it stands."""
        self.rows().write.mode("overwrite").parquet(f"{self.path}/snapshot={upto}")
        for kind in ("batch", "snapshot"):
            for k in self._ids(kind):
                if k < upto or (kind == "batch" and k == upto):
                    fs, at = file_system(self.catalog.spark, f"{self.path}/{kind}={k}")
                    fs.delete(at, True)

    def rows(self) -> DataFrame:
        """The view now: the newest snapshot and later batches, merged."""
        df = self.catalog.spark.read.parquet(*self._folders())
        return views.merged(self.definition, df.limit(0), df)


def dropped_late(query) -> int:
    """Rows that a finished or running stream query dropped because they came behind its watermark."""
    return sum(s.get("numRowsDroppedByWatermark", 0) for p in query.recentProgress for s in p["stateOperators"])


def append_segment(catalog, sort_cols: list[str], path: str) -> Callable[[DataFrame, int], None]:
    """A batch function that stores the batch's distinct sort prefixes with counts: a segment of a run design."""
    def each(batch: DataFrame, batch_id: int) -> None:
        batch.groupBy(*sort_cols).agg(F.count("*").alias("c")).write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return each


def read_segments(catalog, path: str) -> DataFrame:
    return catalog.spark.read.option("basePath", path).parquet(f"{path}/*").drop("batch")


def windowed(events: DataFrame, kind: str, lateness: str = "1 day") -> DataFrame:
    """Counts and sums of events by type in tumbling or sliding windows or in sessions; works on streams and batches."""
    df = events.select("event_type", F.col("ts").cast("timestamp").alias("ts"), F.col("value").cast("decimal(18,2)").alias("value")).withWatermark("ts", lateness)
    w = {"tumbling": F.window("ts", "1 day"), "sliding": F.window("ts", "2 days", "1 day"), "session": F.session_window("ts", "30 minutes")}[kind]
    out = df.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    ntz = lambda c: F.col(c).cast("timestamp_ntz")
    return out.select(ntz("w.start").alias("w_start"), ntz("w.end").alias("w_end"), "event_type", "n", F.col("total").cast("double").alias("total"))


def without_duplicates(events: DataFrame, lateness: str = "1 day") -> DataFrame:
    """Events once by id, within the watermark on streams."""
    df = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", lateness)
    return df.dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else df.dropDuplicates(["event_id"])


def join_within(a: DataFrame, b: DataFrame, seconds: int, lateness: str = "1 day") -> DataFrame:
    """Pairs of events of one user, the second within `seconds` after the first; state is bounded by watermarks."""
    x = a.select(F.col("user_id").alias("u"), F.col("event_id").alias("first_id"), F.col("ts").cast("timestamp").alias("t1")).withWatermark("t1", lateness)
    y = b.select(F.col("user_id").alias("w"), F.col("event_id").alias("second_id"), F.col("ts").cast("timestamp").alias("t2")).withWatermark("t2", lateness)
    near = F.expr(f"u = w and t2 > t1 and t2 <= t1 + interval {seconds} seconds")
    return x.join(y, near).select("first_id", "second_id", F.col("u").alias("user_id"))


def open_runs(events: DataFrame, key: str, value: str) -> DataFrame:
    """Runs of a value per key as a stream: the open run stays in state until its value changes."""
    kinds = dict(events.dtypes)

    def step(k: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        pdf = pd.concat(list(batches)).sort_values("event_id")
        v, c = state.get if state.exists else (None, 0)
        out = []
        for x in pdf[value]:
            if c and x != v:
                out.append((k[0], v, c))
                c = 0
            v, c = x, c + 1
        state.update((v, c))
        yield pd.DataFrame(out, columns=["k", "v", "c"])

    return events.groupBy(key).applyInPandasWithState(step, f"k {kinds[key]}, v {kinds[value]}, c long", f"v {kinds[value]}, c long", "append", GroupStateTimeout.NoTimeout)
