"""A Spark data source for recorders that leave one text file a series.

``spark.dataSource.register(SeriesLog)``, then
``spark.read.format("series_log").load(folder)``: each file ``<grp>-<sid>.log``
holds ``idx,ts_us,val`` lines, either of the last two empty where missing. Files
are read in their own tasks, through any store that pyarrow knows.
"""

from __future__ import annotations

import re

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "grp string, sid int, idx bigint, ts_us bigint, val double"


def _store(path: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(path) if re.match(r"\w+:", path) else (fs.LocalFileSystem(), path)


class LogFile(InputPartition):
    def __init__(self, path: str, grp: str, sid: int):
        self.path, self.grp, self.sid = path, grp, sid


class SeriesReader(DataSourceReader):
    def __init__(self, folder: str):
        self.folder = folder

    def partitions(self) -> list[LogFile]:
        from pyarrow import fs

        store, at = _store(self.folder)
        found = []
        for info in store.get_file_info(fs.FileSelector(at)):
            if m := re.fullmatch(r"(.*)-(\d+)\.log", info.base_name):
                found.append(LogFile(info.path, m[1], int(m[2])))
        return sorted(found, key=lambda f: f.path)

    def read(self, partition: LogFile):
        store, _ = _store(self.folder)
        with store.open_input_stream(partition.path) as raw:
            for line in raw.read().decode("utf-8").splitlines():
                if line.strip():
                    idx, ts, val = line.split(",")
                    yield partition.grp, partition.sid, int(idx), int(ts) if ts else None, float(val) if val else None


class SeriesLog(DataSource):
    @classmethod
    def name(cls) -> str:
        return "series_log"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> SeriesReader:
        return SeriesReader(self.options["path"])
