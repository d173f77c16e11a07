"""The maintenance pass as a job of its own, away from the query path."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from factlake.operators import maintenance as M
from factlake.params import Params
from factlake.streaming.feedback import folder


def maintenance_job(units: DataFrame, edges: DataFrame, queue: DataFrame, at, home: str, done: DataFrame | None = None, p: Params | None = None, build: Callable[[DataFrame], DataFrame] | None = None) -> str:
    """One pass over what is queued and not done, as a new snapshot in ``home``: units, edges, messages and done.

    The snapshot is complete before its folder is named to readers, so a lost job leaves the old one
    valid; the same job run again overwrites its own folder with the same rows.
    """
    todo = queue.select("unit_id").distinct()
    todo = M.pending(todo, done) if done is not None else todo
    out, e, messages = M.run_cycle(units, edges, todo, at, p or Params(), build=build)
    for name, df in (("units", out), ("edges", e), ("messages", messages), ("done", todo if done is None else done.select("unit_id").unionAll(todo))):
        df.write.mode("overwrite").parquet(f"{home}/{name}")
    return home


def latest(spark: SparkSession, home: str) -> str | None:
    """Folder of the last complete pass in ``home``, by the log of passes; None before the first."""
    try:
        row = spark.read.schema("pass long, folder string").parquet(f"{home}/log").orderBy(F.desc("pass")).first()
    except AnalysisException:
        return None
    return row["folder"] if row else None


def on_changes(spark: SparkSession, stream: DataFrame, units: DataFrame, edges: DataFrame, at, home: str | None = None, build: Callable[[DataFrame], DataFrame] | None = None) -> str:
    """Runs the job on every batch of a stream of changed ids; each pass starts from the last one's snapshot.

    All state lies in ``home``: a restart goes on where the log of passes ends, and a batch that is run again
    starts from the pass before it and replaces its own snapshot. Returns ``home``.
    """
    home = home or folder(spark)

    def step(rows: DataFrame, n: int) -> None:
        before = latest(spark, home) if n else None
        if before == f"{home}/pass-{n}":  # this batch again
            before = f"{home}/pass-{n - 1}"
        read = lambda name, first: spark.read.parquet(f"{before}/{name}").select(first.columns) if before else first
        done = spark.read.parquet(f"{before}/done") if before else None
        at_ = maintenance_job(read("units", units), read("edges", edges), rows, at, f"{home}/pass-{n}", done, build=build)
        spark.createDataFrame([(n, at_)], "pass long, folder string").coalesce(1).write.mode("overwrite").parquet(f"{home}/log/batch={n}")

    stream.writeStream.foreachBatch(step).option("checkpointLocation", f"{home}/state").trigger(availableNow=True).start().awaitTermination()
    return home
