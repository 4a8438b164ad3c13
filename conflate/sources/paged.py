"""A paged, capped place API as a Python data source, simulated over a folder of JSON lines.

Options: ``path`` (one file per box, ``<level>_<ix>_<iy>.json``), ``cap``, ``page``, ``key``.  A query returns the
first ``cap`` rows of its box in pages of ``page`` with a token for the next.  Each box is one partition.
"""

from __future__ import annotations

import json
import os
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class Box(InputPartition):
    def __init__(self, name: str):
        super().__init__(name)
        self.name = name


def request(folder: str, box: str, token: int, cap: int, page: int) -> tuple[list[dict], int | None]:
    """One call: a page of rows and the token of the next page."""
    with open(os.path.join(folder, box)) as f:
        rows = sorted((json.loads(x) for x in f if x.strip()), key=lambda r: r["uid"])[:cap]
    got = rows[token : token + page]
    return got, token + page if token + page < len(rows) else None


class PagedReader(DataSourceReader):
    def __init__(self, options: dict):
        self.folder, self.cap, self.page = options["path"], int(options.get("cap", 60)), int(options.get("page", 20))

    def partitions(self) -> list[Box]:
        return [Box(n) for n in sorted(os.listdir(self.folder)) if n.endswith(".json")]

    def read(self, partition: Box) -> Iterator[tuple]:
        token: int | None = 0
        calls = 0
        while token is not None:
            rows, token = request(self.folder, partition.name, token, self.cap, self.page)
            calls += 1
            for r in rows:
                yield partition.name.removesuffix(".json"), calls, r["uid"], float(r["lat"]), float(r["lon"]), r.get("name")


class PagedPlaces(DataSource):
    @classmethod
    def name(cls) -> str:
        return "paged_places"

    def schema(self) -> str:
        return "box string, page_no int, uid string, lat double, lon double, name string"

    def reader(self, schema) -> PagedReader:  # noqa: ANN001
        if not self.options.get("key"):
            raise ValueError("the API wants a key")
        return PagedReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(PagedPlaces)
