"""A change feed that maintains sketches eagerly, a trigger at a time."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from skipsketch.plans.algebra import M
from skipsketch.session import Session


def feed(session: Session, table: str, stream: DataFrame, checkpoint: str, available_now: bool = True, after: Callable[[int, dict], None] | None = None) -> StreamingQuery:
    """Commit each micro-batch of signed rows (the table's columns and ``__m``) as a version and maintain every sketch that reads it.

    A batch that is delivered again after a failure is recognised by its number and not applied twice.  Late
    rows are ordinary inserts of a later version; nothing is dropped by a watermark.
    """
    done: set[int] = set()

    def apply(batch: DataFrame, number: int) -> None:
        if number in done:
            return
        batch.persist()
        try:
            changes = session.update_delta({table: batch})
        finally:
            batch.unpersist()
        done.add(number)
        if after:
            after(number, changes)

    writer = stream.writeStream.foreachBatch(apply).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if available_now else writer).start()


def windowed(stream: DataFrame, time: str, length: str, slide: str | None = None) -> DataFrame:
    """Rows with the start of their tumbling or sliding windows as a plain group key, ready for maintenance."""
    w = F.window(F.col(time), length, slide or length)
    return stream.select("*", w["start"].alias("window_start"))


def signed_stream(stream: DataFrame, sign: int = 1) -> DataFrame:
    return stream.withColumn(M, F.lit(sign).cast("long"))
