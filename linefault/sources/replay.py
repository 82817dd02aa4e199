"""A Python data source that replays rows of a Parquet folder in time order, as batch or as stream."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader


class _Part(InputPartition):
    def __init__(self, begin: int, end: int):
        self.begin, self.end = begin, end


def _rows(path: str, begin: int, end: int) -> Iterator[tuple]:
    import pyarrow.dataset as ds

    table = ds.dataset(path).to_table(columns=["rec_id", "ts", "device", "snr", "tx"]).sort_by([("ts", "ascending"), ("rec_id", "ascending")])
    yield from (tuple(r.values()) for r in table.slice(begin, end - begin).to_pylist())


class ReplaySource(DataSource):
    """spark.read / readStream.format("replay").option("path", ...).option("rows", 500): for demonstrations and tests.

    Every read sorts the folder, so this is for small recordings; recorded files at scale go through
    stream_records.
    """

    @classmethod
    def name(cls) -> str:
        return "replay"

    def schema(self) -> str:
        return "rec_id long, ts timestamp, device long, snr double, tx double"

    def reader(self, schema) -> DataSourceReader:
        return _Batch(self.options)

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:
        return _Stream(self.options)


def _count(path: str) -> int:
    import pyarrow.dataset as ds

    return ds.dataset(path).count_rows()


class _Batch(DataSourceReader):
    def __init__(self, options):
        self.path, self.step = options["path"], int(options.get("rows", 500))

    def partitions(self):
        return [_Part(i, i + self.step) for i in range(0, _count(self.path), self.step)]

    def read(self, partition: _Part) -> Iterator[tuple]:
        return _rows(self.path, partition.begin, partition.end)


class _Stream(SimpleDataSourceStreamReader):
    def __init__(self, options):
        self.path, self.step = options["path"], int(options.get("rows", 500))

    def initialOffset(self) -> dict:
        return {"at": 0}

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        end = min(start["at"] + self.step, _count(self.path))
        return iter(list(_rows(self.path, start["at"], end))), {"at": end}  # Spark copies the iterator

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:
        return iter(list(_rows(self.path, start["at"], end["at"])))
