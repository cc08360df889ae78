"""A Python data source of pairs in JSON lines: a partition per file, the split as a pushed filter.

spark.read.format("pairlens_pairs").load(folder). A line that is no JSON object gives a row of nulls with the line in
`broken`; with an equality on split pushed down, a line of another split ends before its texts become a row.
"""

from __future__ import annotations

import io
import json
from collections.abc import Iterator
from dataclasses import dataclass

from pyarrow import fs
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, InputPartition

FORMAT = "pairlens_pairs"
FIELDS = ("pair_id", "split", "lang", "origin", "seq", "reference", "summary")
NUMBERS = ("pair_id", "seq")


@dataclass
class PairFile(InputPartition):
    uri: str


class PairReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path if "://" in path or path.startswith("file:") else f"file://{path}"
        self.split: str | None = None

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("split",) and self.split in (None, f.value):
                self.split = f.value
            else:
                yield f

    def partitions(self) -> list[PairFile]:
        store, root = fs.FileSystem.from_uri(self.path)
        found = store.get_file_info(fs.FileSelector(root, recursive=True))
        return [PairFile(f.path) for f in sorted(found, key=lambda f: f.path) if f.is_file and not f.base_name.startswith(("_", "."))]

    def read(self, partition: PairFile | None):
        if partition is None:  # a folder without files
            return
        store, _ = fs.FileSystem.from_uri(self.path)
        with store.open_input_stream(partition.uri) as raw, io.TextIOWrapper(io.BufferedReader(raw), encoding="utf-8", errors="replace", newline="\n") as lines:
            for line in lines:
                row = self._row(line.rstrip("\r\n"))
                if row is not None:
                    yield row

    def _row(self, line: str) -> tuple | None:
        if not line.strip():
            return None
        try:
            d = json.loads(line)
            if not isinstance(d, dict):
                raise ValueError
            if self.split is not None and d.get("split") != self.split:
                return None
            row = [None if d.get(f) is None else int(d[f]) if f in NUMBERS else str(d[f]) for f in FIELDS]
        except (ValueError, TypeError):
            return None if self.split is not None else (*(None,) * len(FIELDS), line)
        return (*row, None)


class PairSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return FORMAT

    def schema(self) -> str:
        return "pair_id BIGINT, split STRING, lang STRING, origin STRING, seq BIGINT, reference STRING, summary STRING, broken STRING"

    def reader(self, schema) -> PairReader:
        return PairReader(self.options["path"])


def register_pairs(spark: SparkSession) -> None:
    """Also turns on pushed filters for Python sources in this session, without which a reader that takes any fails."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(PairSource)
