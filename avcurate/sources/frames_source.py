"""A Spark data source of synthetic frames, for load tests without files."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class FrameSource(DataSource):
    """format("frames") with options clips, frames, side: a square that moves over a dark image."""

    @classmethod
    def name(cls) -> str:
        return "frames"

    def schema(self) -> str:
        return "clip_id long, frame_no int, pixels array<float>, height int, width int, channels int"

    def reader(self, schema):
        return _Reader(self.options)


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.clips, self.frames, self.side = (int(options.get(k, d)) for k, d in (("clips", 4), ("frames", 3), ("side", 4)))

    def partitions(self):
        return [InputPartition(i) for i in range(min(8, self.clips))]

    def read(self, partition):
        for clip in range(partition.value, self.clips, min(8, self.clips)):
            for f in range(self.frames):
                px = [0.0] * (self.side * self.side)
                px[(clip + f) % len(px)] = 1.0
                yield clip, f, px, self.side, self.side, 1


def register(spark: SparkSession) -> None:
    spark.dataSource.register(FrameSource)
