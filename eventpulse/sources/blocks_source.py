"""A data source that delivers the blocks of a stored stream of posts, in batch and as a stream."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceStreamReader, InputPartition

SCHEMA = "post_id bigint, ts timestamp, region string, text string"


def block_batches(path: str, block: int) -> Iterator:
    """The record batches of a block: the Parquet files of its folder, on any file system that Arrow opens by its address."""
    import pyarrow as pa
    import pyarrow.dataset as ds
    from pyarrow import fs

    store, root = fs.FileSystem.from_uri(path if "://" in path or path.startswith("/") else path.replace(":", "://", 1))
    found = ds.dataset(f"{root}/{block:06d}", filesystem=store, format="parquet")
    kinds = pa.schema([("post_id", pa.int64()), ("ts", pa.timestamp("us", "UTC")), ("region", pa.string()), ("text", pa.string())])
    for b in found.to_batches(columns=kinds.names):
        yield pa.RecordBatch.from_arrays([b.column(f.name).cast(f.type) for f in kinds], schema=kinds)


class BlockSource(DataSource):
    """``spark.read.format("post_blocks")`` with options path and blocks: the folders 000000 to ``blocks`` - 1 that
    :func:`eventpulse.streaming.replay.write_replay` has left there; also as a stream."""

    @classmethod
    def name(cls) -> str:
        return "post_blocks"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options["path"], int(self.options["blocks"]))

    def streamReader(self, schema) -> DataSourceStreamReader:
        return _StreamReader(self.options["path"], int(self.options["blocks"]))


class _Reader(DataSourceReader):
    def __init__(self, path: str, blocks: int):
        self.path, self.blocks = path, blocks

    def partitions(self):
        return [InputPartition(b) for b in range(self.blocks)]

    def read(self, partition):
        return block_batches(self.path, partition.value)


class _StreamReader(DataSourceStreamReader):
    """A block with each batch, until all are out."""

    def __init__(self, path: str, blocks: int):
        self.path, self.blocks, self.at = path, blocks, 0

    def initialOffset(self) -> dict:
        return {"block": 0}

    def latestOffset(self) -> dict:
        self.at = min(self.at + 1, self.blocks)
        return {"block": self.at}

    def partitions(self, start: dict, end: dict):
        return [InputPartition(b) for b in range(start["block"], end["block"])]

    def read(self, partition):
        return block_batches(self.path, partition.value)

    def commit(self, end: dict) -> None:
        pass
