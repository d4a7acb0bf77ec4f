"""Made-up fields of view, for tests of scale: for the rows of a given table by ``over``, or for any number of rows by a data
source, spark.read.format('synthetic_fov').option('rows', n).load()."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "fov_id long, video_id long, lat double, lon double, theta double, r_m double, alpha double"


def shape(number: int | None) -> tuple[float, float, float, float, float]:
    """lat, lon, theta, r_m, alpha of a row, by its number only; without a number, as for -1."""
    import random

    noise = random.Random(-1 if number is None else number)
    return 10.0 + noise.gauss(0, 0.01), 20.0 + noise.gauss(0, 0.01), noise.uniform(0, 360), 350.0 * noise.gammavariate(1.6, 0.4), noise.choice([60.0, 160.0, 360.0])


def over(rows: DataFrame) -> DataFrame:
    """A made-up field of view for each row (fov_id, video_id) of a given table, whose ids take the place of row numbers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            shapes = list(zip(*map(shape, batch.column(0).to_pylist()), strict=True)) or [()] * 5
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *[pa.array(c, pa.float64()) for c in shapes]], ["fov_id", "video_id", "lat", "lon", "theta", "r_m", "alpha"])

    return rows.select("fov_id", "video_id").repartition("fov_id").mapInArrow(run, SCHEMA)


class _Reader(DataSourceReader):
    def __init__(self, rows: int, parts: int) -> None:
        self.rows, self.parts = rows, parts

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        for i in range(partition.value, self.rows, self.parts):
            yield (i, i // 87, *shape(i))


class SyntheticFovs(DataSource):
    """Options: rows (10000) and parts (4). A row depends on its number only, so a lost partition comes back as it was."""

    @classmethod
    def name(cls) -> str:
        return "synthetic_fov"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _Reader(int(self.options.get("rows", 10_000)), int(self.options.get("parts", 4)))
