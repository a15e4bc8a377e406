"""A data source of candidate pages: each page of ids is a partition, or a step of a stream, with the key that the draw orders by."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader


def _rows(start: int, end: int, seed: int, turn: int) -> Iterator[tuple[int, str]]:
    for i in range(start, end):
        yield i, hashlib.md5(f"{seed}:{turn}:{i}".encode()).hexdigest()


class Page(InputPartition):
    def __init__(self, start: int, end: int) -> None:
        self.start, self.end = start, end


class CandidatePages(DataSource):
    """Options: rows (ids from 0), page (ids of a page), seed and turn of the draw. For a batch instead of rows also pages: the numbers of those that are wanted, with commas, or none."""

    @classmethod
    def name(cls) -> str:
        return "candidate_pages"

    def schema(self) -> str:
        return "sample_id long, key string"

    def settings(self) -> tuple[int, int, int, int]:
        return tuple(int(self.options.get(k, v)) for k, v in (("rows", 0), ("page", 1000), ("seed", 42), ("turn", 0)))

    def reader(self, schema) -> DataSourceReader:
        wanted = self.options.get("pages")
        return PageReader(*self.settings(), None if wanted is None else [int(p) for p in wanted.split(",") if p != "none"])

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:
        return PageStream(*self.settings())


class PageReader(DataSourceReader):
    def __init__(self, rows: int, page: int, seed: int, turn: int, wanted: list[int] | None = None) -> None:
        self.rows, self.page, self.seed, self.turn, self.wanted = rows, page, seed, turn, wanted

    def partitions(self) -> list[Page]:
        if self.wanted is not None:
            return [Page(p * self.page, (p + 1) * self.page) for p in self.wanted] or [Page(0, 0)]
        return [Page(i, min(self.rows, i + self.page)) for i in range(0, self.rows, self.page)] or [Page(0, 0)]

    def read(self, partition: Page) -> Iterator[tuple[int, str]]:
        return _rows(partition.start, partition.end, self.seed, self.turn)


class PageStream(SimpleDataSourceStreamReader):
    """A page a step, until there are no more ids."""

    def __init__(self, rows: int, page: int, seed: int, turn: int) -> None:
        self.rows, self.page, self.seed, self.turn = rows, page, seed, turn

    def initialOffset(self) -> dict:
        return {"at": 0}

    def read(self, start: dict) -> tuple[Iterator[tuple[int, str]], dict]:
        end = min(self.rows, start["at"] + self.page)
        return iter(list(_rows(start["at"], end, self.seed, self.turn))), {"at": end}  # Spark keeps a copy of it

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple[int, str]]:
        return _rows(start["at"], end["at"], self.seed, self.turn)
