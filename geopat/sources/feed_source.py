"""A Python data source that replays reports in time order, as a batch and as a stream: those of a folder of Parquet files, or made-up ones."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
import pyarrow.parquet as pq
from pyarrow import fs
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

MINUTE_US = 60_000_000


def reports(start: int, end: int) -> Iterator[tuple[int, int, str]]:
    for i in range(start, end):
        yield i, i * MINUTE_US, f"type{i % 7}"


class ReportFeed(DataSource):
    """Options: `from`, a folder whose files, by name, hold id, at_us and type in time order (a batch takes a task for each).

    Without it reports are made up: `reports`, how many there are; `parts`, tasks of a batch; `step`, reports of a micro-batch.
    """

    @classmethod
    def name(cls) -> str:
        return "report_feed"

    def schema(self) -> str:
        return "id long, at_us long, type string"

    def reader(self, schema) -> DataSourceReader:  # noqa: ANN001
        if "from" in self.options:
            return _Files(self.options["from"])
        return _Batch(int(self.options.get("reports", 100)), int(self.options.get("parts", 2)))

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:  # noqa: ANN001, N802
        return _Stream(int(self.options.get("reports", 100)), int(self.options.get("step", 50)))


class _Batch(DataSourceReader):
    def __init__(self, n: int, parts: int):
        self.n, self.parts = n, parts

    def partitions(self) -> list[InputPartition]:
        edges = [self.n * i // self.parts for i in range(self.parts + 1)]
        return [InputPartition((a, b)) for a, b in zip(edges, edges[1:], strict=False)]

    def read(self, partition: InputPartition) -> Iterator[tuple[int, int, str]]:
        yield from reports(*partition.value)


class _Files(DataSourceReader):
    def __init__(self, folder: str):
        self.folder = folder

    def partitions(self) -> list[InputPartition]:
        store, path = fs.FileSystem.from_uri(self.folder)
        names = sorted(f.path for f in store.get_file_info(fs.FileSelector(path)) if f.is_file and f.base_name.startswith("part-"))
        return [InputPartition(n) for n in names] or [InputPartition(None)]

    def read(self, partition: InputPartition) -> Iterator[pa.RecordBatch]:
        if partition.value is None:
            return
        store, _ = fs.FileSystem.from_uri(self.folder)
        with store.open_input_file(partition.value) as file:
            yield from pq.ParquetFile(file).iter_batches(10_000, columns=["id", "at_us", "type"])


class _Stream(SimpleDataSourceStreamReader):
    def __init__(self, n: int, step: int):
        self.n, self.step = n, step

    def initialOffset(self) -> dict:  # noqa: N802
        return {"at": 0}

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        end = min(self.n, start["at"] + self.step)
        return iter(list(reports(start["at"], end))), {"at": end}

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:  # noqa: N802
        return iter(list(reports(start["at"], end["at"])))
