"""A replayed traffic source: recorded snapshots come back as a stream, a few per micro-batch."""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, SimpleDataSourceStreamReader


class ReplaySource(DataSource):
    """format('snapshot_replay'): options `path` (Parquet folder), `per_batch` snapshots and `columns`, snap first."""

    @classmethod
    def name(cls):
        return "snapshot_replay"

    def schema(self):
        return self.options.get("columns", "snap int, dim bigint, val double")

    def simpleStreamReader(self, schema):
        return ReplayReader(self.options)

    def reader(self, schema):
        return ReplayBatch(self.options)


def _rows(options, lo, hi):
    """Rows of snapshots lo to hi, from whatever file system the path names."""
    import pyarrow.dataset as ds
    from pyarrow import fs

    path = options["path"]
    system, place = fs.FileSystem.from_uri(path if "://" in path else "file://" + path.removeprefix("file:"))
    names = [c.split()[0] for c in options.get("columns", "snap int, dim bigint, val double").split(",")]
    table = ds.dataset(place, format="parquet", filesystem=system).to_table(columns=names, filter=(ds.field("snap") >= lo) & (ds.field("snap") < hi))
    for row in table.to_pylist():
        yield tuple(row[n] for n in names)


class ReplayReader(SimpleDataSourceStreamReader):
    def __init__(self, options):
        self.options, self.step = dict(options), int(options.get("per_batch", 4))

    def initialOffset(self):
        return {"snap": 0}

    def read(self, start):
        rows = list(_rows(self.options, start["snap"], start["snap"] + self.step))
        return iter(rows), ({"snap": start["snap"] + self.step} if rows else start)

    def readBetweenOffsets(self, start, end):
        return _rows(self.options, start["snap"], end["snap"])


class ReplayBatch(DataSourceReader):
    def __init__(self, options):
        self.options = dict(options)

    def read(self, partition):
        return _rows(self.options, 0, 1 << 30)
