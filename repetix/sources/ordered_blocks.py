"""A data source of big files as ordered blocks of bytes, batch and streaming."""

from __future__ import annotations

import os
from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceStreamReader, InputPartition

SCHEMA = "file string, block bigint, bytes binary"


class BlockRange(InputPartition):
    def __init__(self, file: str, first: int, stop: int, size: int):
        self.file, self.first, self.stop, self.size = file, first, stop, size


def _files(path: str) -> list[str]:
    if os.path.isfile(path):
        return [path]
    return sorted(os.path.join(path, f) for f in os.listdir(path) if not f.startswith((".", "_")))


def _read(partition: BlockRange) -> Iterator[tuple]:
    with open(partition.file, "rb") as f:
        f.seek(partition.first * partition.size)
        for block in range(partition.first, partition.stop):
            yield partition.file, block, f.read(partition.size)


class BlockReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.size = options["path"], int(options.get("block_bytes", 1 << 20))
        self.blocks_a_task = int(options.get("blocks_a_task", 64))

    def partitions(self) -> list[BlockRange]:
        out = []
        for file in _files(self.path):
            blocks = -(-os.path.getsize(file) // self.size)
            out += [BlockRange(file, b, min(blocks, b + self.blocks_a_task), self.size) for b in range(0, blocks, self.blocks_a_task)]
        return out

    def read(self, partition: BlockRange) -> Iterator[tuple]:
        return _read(partition)


class BlockStreamReader(DataSourceStreamReader):
    """Micro-batches are the blocks that have come since the last one, in the order of the files; executors read them."""

    def __init__(self, options: dict):
        self.path, self.size = options["path"], int(options.get("block_bytes", 1 << 20))

    def initialOffset(self) -> dict:
        return {"block": 0}

    def latestOffset(self) -> dict:
        return {"block": len(self._blocks())}

    def _blocks(self) -> list[tuple[str, int]]:
        return [(f, b) for f in _files(self.path) for b in range(-(-os.path.getsize(f) // self.size))]

    def partitions(self, start: dict, end: dict) -> list[BlockRange]:
        return [BlockRange(f, b, b + 1, self.size) for f, b in self._blocks()[start["block"] : end["block"]]]

    def read(self, partition: BlockRange) -> Iterator[tuple]:
        return _read(partition)


class OrderedBlocks(DataSource):
    """spark.read.format("ordered_blocks").load(path); for files that every executor can open by path."""

    @classmethod
    def name(cls) -> str:
        return "ordered_blocks"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> BlockReader:
        return BlockReader(self.options)

    def streamReader(self, schema) -> BlockStreamReader:
        return BlockStreamReader(self.options)
