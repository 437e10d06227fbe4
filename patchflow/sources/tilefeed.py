"""A synthetic feed of tiles as a Python data source, for load tests without tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..shipping import ship_package


class TileReader(DataSourceReader):
    """One partition a clip; a frame is one Arrow batch."""

    def __init__(self, options: dict):
        self.clips, self.frames, self.rows, self.cols = (int(options.get(k, v)) for k, v in (("clips", 16), ("frames", 64), ("rows", 4), ("cols", 5)))

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(c) for c in range(self.clips)]

    def read(self, partition: InputPartition):
        import numpy as np
        import pyarrow as pa

        place = np.arange(self.rows * self.cols)
        for f in range(self.frames):
            value = (partition.value * 7919 + f * 104729 + place * 1299709) % 10007
            columns = [np.full(place.size, partition.value, np.int64), np.full(place.size, f, np.int32), (place // self.cols).astype(np.int32), (place % self.cols).astype(np.int32), value.astype(np.int64)]
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], ["clip_id", "frame_idx", "row", "col", "importance"])


class TileFeed(DataSource):
    """Options: clips, frames, rows, cols."""

    @classmethod
    def name(cls) -> str:
        return "tile_feed"

    def schema(self) -> str:
        return "clip_id long, frame_idx int, row int, col int, importance long"

    def reader(self, schema) -> DataSourceReader:
        return TileReader(self.options)


def tile_feed(spark: SparkSession, clips: int = 16, frames: int = 64, grid: tuple[int, int] = (4, 5)) -> DataFrame:
    ship_package(spark)
    spark.dataSource.register(TileFeed)
    return spark.read.format("tile_feed").options(clips=clips, frames=frames, rows=grid[0], cols=grid[1]).load()
