"""Day-by-day linkage over streams.

Parties arrive as files of events, oldest first. A day's bins are padded and
released once, when a later day has been seen; rows that come after that go to
a late table and are never released, as a second release would cost a second
budget. Noise depends on seed, party and bin only, so a replayed batch releases
the same counts.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from veil.sources.shared import shared_path

#: Modification time of the first laid out file and the step between files, in milliseconds.
FIRST_MS, STEP_MS = 1_700_000_000_000, 1_000


def lay_out(df: DataFrame, path: str) -> str:
    """Write the partitions of ``df`` as files whose modification times follow the partitions' order.

    A file stream reads files by modification time; parallel tasks finish in
    any order, and a file that comes too early moves the watermark past the
    rows of those before it.
    """
    df.write.parquet(path)
    spark = df.sparkSession
    jvm = spark.sparkContext._jvm
    folder = jvm.org.apache.hadoop.fs.Path(path)
    fs = folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    files = sorted((f.getPath() for f in fs.listStatus(folder) if f.getPath().getName().startswith("part-")), key=lambda p: p.getName())
    for k, p in enumerate(files):
        fs.setTimes(p, FIRST_MS + k * STEP_MS, -1)
    times = [fs.getFileStatus(p).getModificationTime() for p in files]
    if times != sorted(times):
        raise RuntimeError(f"files below {path} have no modification times in their order")
    return path


def read_events(spark: SparkSession, path: str, schema: str, files_per_trigger: int = 1) -> DataFrame:
    """File stream with a declared schema, a bounded number of files per batch."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def drain(df: DataFrame, mode: str, label: str) -> DataFrame:
    """Run a streaming plan over all available input and return what it wrote.

    Files in the shared folder hold output and progress, so a restart goes on
    where it stopped. ``complete`` results are kept as the last batch's table.
    Raises if the watermark dropped rows.
    """
    spark = df.sparkSession
    out, progress = shared_path(spark, label), shared_path(spark, label + "-progress")
    writer = df.writeStream.outputMode(mode).option("checkpointLocation", progress).trigger(availableNow=True)
    if mode == "append":
        query = writer.format("parquet").option("path", out).start()
    else:

        def keep(batch: DataFrame, _: int) -> None:
            batch.write.mode("overwrite").parquet(out)

        query = writer.foreachBatch(keep).start()
    query.awaitTermination()
    dropped = sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])
    if dropped:
        raise RuntimeError(f"the watermark dropped {dropped} rows")
    return spark.read.schema(df.schema).parquet(out)


def split_late(batch: DataFrame, released: DataFrame, day: str = "day") -> tuple[DataFrame, DataFrame]:
    """Rows of days not yet released, and late rows."""
    return batch.join(released, day, "left_anti"), batch.join(released, day, "left_semi")


class DailyRelease:
    """Counts per bin of closed days, each released once; idempotent by batch and day.

    ``pad(counts, days)`` turns ``day, bin, n_real`` of the days to release into
    ``day, bin, n_noisy``. ``run`` drives it from a stream by ``foreachBatch``:
    every batch is taken in, then all days before the latest one seen are
    released in one plan. State is kept as tables in the shared folder.
    """

    SCHEMAS = {"open": "day long, bin long, batch long", "late": "day long, bin long, batch long", "released": "day long, bin long, n_noisy long, closed long"}

    def __init__(self, spark: SparkSession, pad: Callable[[DataFrame, DataFrame], DataFrame], label: str = "daily"):
        self.spark, self.pad, self.label = spark, pad, label
        self.root = shared_path(spark, label)

    def _read(self, name: str) -> DataFrame:
        try:
            return self.spark.read.schema(self.SCHEMAS[name]).parquet(f"{self.root}/{name}")
        except Exception as e:  # nothing written yet
            if "PATH_NOT_FOUND" in str(e):
                return self.spark.createDataFrame([], self.SCHEMAS[name])
            raise

    def _done(self, but: int | None = None) -> DataFrame:
        return self._read("released").filter(F.lit(but is None) | (F.col("closed") != F.lit(but))).select("day").distinct()

    def ingest(self, batch: DataFrame, batch_id: int) -> None:
        """Append a batch; rows of released days go to the late table. A replay of a batch replaces it."""
        done = self._done(batch_id)
        for name, rows in zip(("open", "late"), split_late(batch.select("day", "bin"), done)):
            rows.write.mode("overwrite").parquet(f"{self.root}/{name}/batch={batch_id}")

    def close(self, before: int, closing: int) -> None:
        """Release all days before a bound that no other closing released, in one plan; a replay of a closing replaces it."""
        rows = self._read("open").filter(F.col("day") < before)
        ready = rows.join(self._done(closing), "day", "left_anti")
        counts = ready.groupBy("day", "bin").agg(F.count("*").alias("n_real"))
        noisy = self.pad(counts, ready.select("day").distinct()).select(F.col("day").cast("long").alias("day"), "bin", "n_noisy")
        noisy.write.mode("overwrite").parquet(f"{self.root}/released/closed={closing}")

    def run(self, stream: DataFrame) -> DailyRelease:
        """Drain a stream of ``day, bin`` rows."""

        def step(batch: DataFrame, batch_id: int) -> None:
            self.ingest(batch, batch_id)
            latest = self._read("open").agg(F.max("day").alias("d")).first()["d"]
            if latest is not None:
                self.close(latest, batch_id)

        writer = stream.writeStream.foreachBatch(step).option("checkpointLocation", shared_path(self.spark, f"{self.label}-progress"))
        writer.trigger(availableNow=True).start().awaitTermination()
        return self

    def finish(self) -> DailyRelease:
        """Release what is still open, when no more rows will come."""
        self.close(1 << 62, -1)
        return self

    def released(self) -> DataFrame:
        return self._read("released").select("day", "bin", "n_noisy")

    def late(self) -> DataFrame:
        return self._read("late").select("day", "bin")


def budget_stream(requests: DataFrame, cap: int) -> DataFrame:
    """Stream of budget requests ``party, seq, eps`` (integer units) with ``granted`` and ``spent``.

    Each party's spending is kept as state. Requests are taken in the order of
    ``seq`` within a batch; the first one that would exceed ``cap`` closes the
    party's ledger, and it and all later ones are refused.
    """

    def step(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        spent, closed = state.get if state.exists else (0, False)
        rows = pd.concat(list(frames)).sort_values("seq")
        granted, after = [], []
        for eps in rows["eps"]:
            closed = closed or spent + eps > cap
            spent += 0 if closed else int(eps)
            granted.append(not closed)
            after.append(spent)
        state.update((spent, closed))
        yield pd.DataFrame({"party": key[0], "seq": rows["seq"], "eps": rows["eps"], "granted": granted, "spent": after})

    out, kept = "party string, seq long, eps long, granted boolean, spent long", "spent long, closed boolean"
    return requests.groupBy("party").applyInPandasWithState(step, out, kept, "append", "NoTimeout")
