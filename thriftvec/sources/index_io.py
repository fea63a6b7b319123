"""Saved indexes: a sink that writes one table per access path, a reader, and a Python data source over them."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType

from ..functions.encoders import Encoder
from ..operators.search import VectorIndex

SCHEMAS = {
    "adjacency": "node_id long, nbrs array<long>, shard int",
    "codes": "node_id long, code binary",
    "codebook": "sub int, code int, centroid array<float>",
    "centres": "cell int, centroid array<double>",
    "meta": "key string, value string",
}
FORMAT_VERSION = 1


def save(index: VectorIndex, path: str) -> None:
    """Neighbour lists sorted by node inside each shard's files, codes apart, so that a traversal never reads text."""
    a = index.adjacency.select("node_id", "nbrs", F.col("shard").cast("int").alias("shard"))
    a.repartition("shard").sortWithinPartitions("shard", "node_id").write.mode("overwrite").partitionBy("shard").parquet(f"{path}/adjacency")
    if index.codes is not None:
        index.codes.sortWithinPartitions("node_id").write.mode("overwrite").parquet(f"{path}/codes")
        index.codebook.coalesce(1).write.mode("overwrite").parquet(f"{path}/codebook")
    if index.centres is not None:
        index.centres.coalesce(1).write.mode("overwrite").parquet(f"{path}/centres")
    rows = [(k, json.dumps(v)) for k, v in (index.meta | {"has_codes": index.codes is not None, "has_centres": index.centres is not None}).items()]
    index.spark.createDataFrame(rows, SCHEMAS["meta"]).coalesce(1).write.mode("overwrite").parquet(f"{path}/meta")


def load(spark: SparkSession, path: str, objects: DataFrame, encoder: Encoder) -> VectorIndex:
    """An index over objects(node_id, text); another encoder than the one it was built with is an error."""
    def read(name: str) -> DataFrame:
        return spark.read.schema(SCHEMAS[name]).parquet(f"{path}/{name}")

    meta = {r["key"]: json.loads(r["value"]) for r in read("meta").collect()}
    if meta.get("format_version") != FORMAT_VERSION:
        raise ValueError(f"format version {meta.get('format_version')} is not {FORMAT_VERSION}")
    if meta["encoder_id"] != encoder.id:
        raise ValueError(f"the index was built with {meta['encoder_id']}, not with {encoder.id}")
    adj = read("adjacency")
    edges = adj.select(F.col("node_id").alias("u"), F.explode("nbrs").alias("v"))
    return VectorIndex(spark, objects, adj, read("codes") if meta["has_codes"] else None, read("codebook") if meta["has_codes"] else None, encoder, meta, read("centres") if meta["has_centres"] else None, edges=edges)


class _Part(InputPartition):
    def __init__(self, file: str):
        self.file = file


class IndexSource(DataSource):
    """spark.read.format("thriftvec").option("table", "adjacency").load(path): a saved index's table, a task per file.

    For local or mounted paths; elsewhere read the Parquet tables with `load`.
    """

    @classmethod
    def name(cls) -> str:
        return "thriftvec"

    def schema(self) -> str:
        return SCHEMAS[self.options.get("table", "adjacency")]

    def reader(self, schema: StructType) -> DataSourceReader:
        return _Reader(self.options, schema)


class _Reader(DataSourceReader):
    def __init__(self, options: dict, schema: StructType):
        self.table, self.path, self.names = options.get("table", "adjacency"), options["path"], [f.name for f in schema.fields]

    def partitions(self) -> list[InputPartition]:
        import pyarrow.dataset as ds

        return [_Part(f) for f in ds.dataset(f"{self.path.removeprefix('file:')}/{self.table}", format="parquet", partitioning="hive").files]

    def read(self, partition: _Part):
        import pyarrow.dataset as ds
        import pyarrow.parquet as pq

        part = dict(x.split("=", 1) for x in partition.file.split("/") if "=" in x)
        file = pq.ParquetFile(partition.file)
        del ds
        for batch in file.iter_batches():
            cols = {n: (batch.column(n).to_pylist() if n in batch.schema.names else [int(part[n])] * batch.num_rows) for n in self.names}
            yield from zip(*cols.values(), strict=True)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(IndexSource)


def read_jsonl(spark: SparkSession, path: str, schema: str = "doc_id long, text string") -> DataFrame:
    return spark.read.schema(schema).json(path)


def read_csv(spark: SparkSession, path: str, schema: str = "doc_id long, text string") -> DataFrame:
    return spark.read.schema(schema).option("header", True).option("multiLine", True).option("escape", '"').csv(path)


def read_text(spark: SparkSession, path: str) -> DataFrame:
    """One object per file: path, text."""
    return spark.read.option("wholetext", True).text(path).select(F.input_file_name().alias("path"), F.col("value").alias("text"))
