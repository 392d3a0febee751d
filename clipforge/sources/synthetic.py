"""A Python data source of synthetic frames: spark.read.format("cf_frames")."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class FrameReader(DataSourceReader):
    def __init__(self, videos: int, frames: int, parts: int):
        self.videos, self.frames, self.parts = videos, frames, parts

    def partitions(self):
        return [InputPartition(k) for k in range(self.parts)]

    def read(self, partition):
        for v in range(partition.value, self.videos, self.parts):
            for n in range(self.frames):
                yield v, n + 1, float((v * 7 + n * 3) % 50 + 300 * (n // 12 % 2))


class FrameSource(DataSource):
    """Options: videos, frames, parts. Levels step every twelve frames."""

    @classmethod
    def name(cls):
        return "cf_frames"

    def schema(self):
        return "media_id bigint, frame_no bigint, luma double"

    def reader(self, schema):
        o = self.options
        return FrameReader(int(o.get("videos", 4)), int(o.get("frames", 48)), int(o.get("parts", 2)))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(FrameSource)
