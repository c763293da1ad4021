"""A source whose reading parallelism and speed are limited, as when readers are tied to accelerators."""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from slicegrad.functions.ship import ship_by_value

ship_by_value(__name__)


class Range(InputPartition):
    def __init__(self, low: int, high: int):
        self.low, self.high = low, high


class LimitedReader(DataSourceReader):
    def __init__(self, options):
        self.rows, self.readers, self.pause_ms = int(options.get("rows", 100)), int(options.get("readers", 1)), float(options.get("pausems", options.get("pauseMs", 0)))

    def partitions(self):
        cut = [self.rows * k // self.readers for k in range(self.readers + 1)]
        return [Range(a, b) for a, b in zip(cut[:-1], cut[1:])]

    def read(self, partition):
        import time

        for i in range(partition.low, partition.high):
            if self.pause_ms:
                time.sleep(self.pause_ms / 1000)
            yield (i, [((i * 31 + j * 7) % 97) / 97.0 for j in range(64)])


class LimitedPictures(DataSource):
    """Options: rows, readers, pauseMs (a row)."""

    @classmethod
    def name(cls):
        return "limited_pictures"

    def schema(self):
        return "pic long, px array<double>"

    def reader(self, schema):
        return LimitedReader(self.options)
