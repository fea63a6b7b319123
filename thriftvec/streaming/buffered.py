"""Buffered adds, tombstones and hot objects on streams.

A node is visible in exactly one of buffer and graph: buffer rows carry the batch they came with, and the index the last
batch that was drained into it; a search reads buffer rows of later batches only. Writes are idempotent per batch.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.encoders import Encoder, encode
from ..operators.exact import knn_exact, top_k
from ..sources.storage import shared_folder

MUTATION = "op string, node_id long, text string, ts timestamp"


def mutations(events: DataFrame) -> DataFrame:
    """events -> op, node_id, text, ts: signup inserts, error deletes, other types are accesses; the node is props.k."""
    op = F.when(F.col("event_type") == "signup", "insert").when(F.col("event_type") == "error", "delete").otherwise("access")
    node = F.get_json_object("props", "$.k").cast("long")
    return events.select(op.alias("op"), node.alias("node_id"), F.concat_ws(" ", F.lit("object"), "event_type", node.cast("string")).alias("text"), F.col("ts").cast("timestamp").alias("ts"))


@dataclass
class BufferedIndex:
    """A vector table with a buffer in front: add (batch or stream), search, drain."""

    spark: SparkSession
    encoder: Encoder
    base: DataFrame  # node_id, v
    folder: str = ""
    drained_upto: int = -1
    deleted: DataFrame | None = None
    _batch: int = field(default=-1)

    def __post_init__(self):
        self.folder = self.folder or shared_folder(self.spark)

    def add(self, rows: DataFrame, batch_id: int | None = None) -> int:
        """Append rows(node_id, text) as one batch; a batch written again replaces itself."""
        self._batch = batch_id if batch_id is not None else self._batch + 1
        rows.select("node_id", "text").write.mode("overwrite").parquet(f"{self.folder}/batch_id={self._batch}")
        return self._batch

    def add_stream(self, stream: DataFrame, checkpoint: str):
        """foreachBatch sink for a stream of (op, node_id, text, ts)."""
        def sink(df: DataFrame, batch_id: int) -> None:
            self.add(df.where("op = 'insert'"), batch_id)
            self._mark(df.where("op = 'delete'"))

        return stream.writeStream.foreachBatch(sink).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()

    def _mark(self, ids: DataFrame) -> None:
        ids = self.spark.createDataFrame(ids.select("node_id").distinct().toArrow()) if not ids.isStreaming else ids
        self.deleted = ids if self.deleted is None else self.deleted.unionByName(ids).distinct()

    def buffer(self) -> DataFrame:
        """Rows not drained yet: the latest batch of each node."""
        if self._batch < 0:
            return self.spark.createDataFrame([], "node_id long, text string")
        b = self.spark.read.schema("node_id long, text string, batch_id int").parquet(self.folder).where(F.col("batch_id") > self.drained_upto)
        return b.groupBy("node_id").agg(F.max_by("text", F.struct("batch_id", "text")).alias("text"))

    def search(self, queries: DataFrame, k: int) -> DataFrame:
        """Exact over base and buffer; a node in the buffer hides its older form in the base."""
        fresh = encode(self.buffer(), self.encoder, "node_id")
        old = self.base.join(fresh.select("node_id"), "node_id", "left_anti")
        both = old.select("node_id", "v").unionByName(fresh)
        if self.deleted is not None:
            both = both.join(self.deleted, "node_id", "left_anti")
        return knn_exact(both, queries, k)

    def drain(self) -> None:
        """Move the buffer into the base and record how far; both happen in one step for a search."""
        from ..sources.storage import stored

        fresh = encode(self.buffer(), self.encoder, "node_id")
        merged = stored(self.base.join(fresh.select("node_id"), "node_id", "left_anti").select("node_id", "v").unionByName(fresh))
        self.base, self.drained_upto = merged, self._batch


def hot_objects(accesses: DataFrame, window: str = "1 day", late: str = "1 hour") -> DataFrame:
    """accesses(ts, node_id), stream or table -> accesses of each node by window, behind a watermark."""
    a = accesses.withWatermark("ts", late) if accesses.isStreaming else accesses
    return a.groupBy(F.window("ts", window).alias("w"), "node_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "node_id", "n")


__all__ = ["BufferedIndex", "MUTATION", "hot_objects", "mutations", "top_k"]
