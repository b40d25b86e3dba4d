"""A paged source for Spark's readers: pages of an export, one partition each, read where the tasks run."""

from __future__ import annotations

import glob
import json
from urllib.parse import unquote, urlparse

from pyspark.sql import DataFrame
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class Page(InputPartition):
    def __init__(self, number: int):
        self.number = number


class PagedSource(DataSource):
    """``format("evigraph_paged")`` with options ``path``, ``pages`` and ``since``: the records of an export, page
    by page after the checkpoint ``since`` (the last page that landed, -1 before the first)."""

    @classmethod
    def name(cls) -> str:
        return "evigraph_paged"

    def schema(self) -> str:
        return "page int, logical long, version string"

    def reader(self, schema) -> DataSourceReader:
        return PagedReader(self.options["path"], int(self.options.get("pages", 1)), int(self.options.get("since", -1)))


class PagedReader(DataSourceReader):
    def __init__(self, path: str, pages: int, since: int):
        self.path, self.pages, self.since = path, pages, since

    def partitions(self) -> list[InputPartition]:
        return [Page(k) for k in range(self.since + 1, self.pages)]

    def read(self, partition: Page):
        folder = unquote(urlparse(self.path).path)
        for name in sorted(glob.glob(f"{glob.escape(folder)}/page={partition.number}/*.json")):
            with open(name, encoding="utf-8") as lines:
                for line in lines:
                    r = json.loads(line)
                    yield partition.number, r.get("logical"), r.get("version")


def exported(records: DataFrame, path: str) -> None:
    """Write records (page, logical, version) as the pages that :class:`PagedSource` reads; the folder must be one
    that all executors see as files."""
    records.select("page", "logical", "version").write.partitionBy("page").json(path)
