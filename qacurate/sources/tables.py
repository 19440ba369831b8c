"""Readers and writers around the tables: a chat-record source, format round trips, manifests."""

from __future__ import annotations

import json
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType

from qacurate.staging import fresh_path


class ChatFile(InputPartition):
    def __init__(self, lines: list[str]) -> None:
        self.lines = lines


class ChatReader(DataSourceReader):
    def __init__(self, options: dict[str, str]) -> None:
        self.lines = json.loads(options["records"])
        self.parts = int(options.get("parts", "2"))

    def partitions(self) -> list[InputPartition]:
        return [ChatFile(self.lines[k :: self.parts]) for k in range(self.parts)]

    def read(self, partition: ChatFile) -> Iterator[tuple]:
        for line in partition.lines:
            r = json.loads(line)
            for turn, m in enumerate(r["messages"]):
                yield r["qid"], turn, m["role"], m.get("content")


class ChatSource(DataSource):
    """Chat records given as JSON lines in an option: a row per turn. For small hand-made sets."""

    @classmethod
    def name(cls) -> str:
        return "chat"

    def schema(self) -> str:
        return "qid string, turn int, role string, content string"

    def reader(self, schema: StructType) -> DataSourceReader:
        return ChatReader(self.options)


def read_records(records: DataFrame) -> DataFrame:
    """Turns of a column ``record`` of chat records as JSON lines, by the reader of the chat source."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        reader = ChatReader({"records": "[]"})
        for batch in batches:
            rows = list(reader.read(ChatFile(batch.column("record").to_pylist())))
            columns = [pa.array([r[k] for r in rows], kind) for k, kind in enumerate((pa.string(), pa.int32(), pa.string(), pa.string()))]
            yield pa.RecordBatch.from_arrays(columns, names=["qid", "turn", "role", "content"])

    return records.mapInArrow(run, "qid string, turn int, role string, content string")


def read_chat(spark: SparkSession, path: str) -> DataFrame:
    """Turns of chat records stored as JSON lines, by Spark's own reader."""
    schema = "qid string, messages array<struct<role string, content string>>"
    return spark.read.schema(schema).json(path).select("qid", F.posexplode("messages").alias("turn", "m")).select("qid", "turn", "m.role", "m.content")


def round_trip(df: DataFrame, fmt: str, **options: str) -> DataFrame:
    """The table written in a format and read again with its schema."""
    path = fresh_path(df.sparkSession, fmt)
    df.write.format(fmt).options(**options).save(path)
    return df.sparkSession.read.format(fmt).schema(df.schema).options(**options).load(path)


def write_partitioned(df: DataFrame, by: str, per_file: int = 1_000_000) -> str:
    path = fresh_path(df.sparkSession, "partitioned")
    df.repartition(by).write.partitionBy(by).option("maxRecordsPerFile", per_file).parquet(path)
    return path


def manifest(df: DataFrame, columns: list[str]) -> DataFrame:
    """(n, digest): row count and an order-free content hash, to check a written table against its source."""
    return df.select(F.xxhash64(*columns).cast("decimal(38,0)").alias("h")).agg(F.count(F.lit(1)).alias("n"), F.sum("h").alias("digest"))
