"""A source that is read page by page, such as the listing of a service: a Python data source, one partition for each run of pages."""

from __future__ import annotations

import functools
import importlib
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType

from evalengine.sources.staging import shared_folder

#: Pages that ``listed`` keeps in one file, which one task reads.
VOLUME = 256


class Pages(InputPartition):
    def __init__(self, first: int, end: int) -> None:
        super().__init__(first)
        self.first, self.end = first, end


class PagedReader(DataSourceReader):
    def __init__(self, options: dict[str, str]) -> None:
        self.options = options

    def partitions(self) -> list[InputPartition]:
        pages, together = int(self.options["pages"]), int(self.options.get("pages_a_task", "8"))
        return [Pages(k, min(k + together, pages)) for k in range(0, pages, together)] or [Pages(0, 0)]

    def read(self, partition: Pages) -> Iterator[tuple]:
        module, _, name = self.options["fetch"].partition(":")
        fetch = getattr(importlib.import_module(module), name)
        for page in range(partition.first, partition.end):
            yield from fetch(page, self.options)


class PagedSource(DataSource):
    """Options: ``fetch`` (``module:function`` of a page number and the options, giving rows), ``pages``, ``pages_a_task``."""

    @classmethod
    def name(cls) -> str:
        return "paged"

    def schema(self) -> str:
        return "id long, page int, body string"

    def reader(self, schema: StructType) -> DataSourceReader:
        return PagedReader(dict(self.options))


def paged(spark: SparkSession, fetch: str, pages: int, schema: str | None = None, **options: str) -> DataFrame:
    spark.dataSource.register(PagedSource)
    reader = spark.read.format("paged").option("fetch", fetch).option("pages", pages)
    for k, v in options.items():
        reader = reader.option(k, v)
    return (reader.schema(schema) if schema else reader).load()


def numbered_page(page: int, options: dict[str, str]) -> Iterator[tuple]:
    """A stand-in listing of ``total`` numbered items, ``size`` to a page."""
    size, total = int(options["size"]), int(options["total"])
    for i in range(page * size, min((page + 1) * size, total)):
        yield i, page, f"item {i}"


def listed(rows: DataFrame, size: int, pages_a_task: int = VOLUME) -> DataFrame:
    """A table (``id`` long from 0 up, ``body``) as a listing: ``size`` ids to a page, stored in the shared folder in volumes of pages,
    and read back page by page."""
    spark, folder = rows.sparkSession, shared_folder(rows.sparkSession, "listing")
    paged_rows = rows.where("id IS NOT NULL").select(F.col("id").cast("long"), F.floor(F.col("id") / size).cast("int").alias("page"), F.col("body").cast("string"))
    kept = paged_rows.withColumn("volume", F.floor(F.col("page") / VOLUME).cast("int"))
    kept.repartition("volume").sortWithinPartitions("volume", "page").write.partitionBy("volume").parquet(folder)
    last = spark.read.schema(kept.schema).parquet(folder).agg(F.max("page")).first()[0]
    return paged(spark, "evalengine.sources.paged:listed_page", 0 if last is None else last + 1, pages_a_task=str(pages_a_task), folder=folder)


@functools.lru_cache(1)
def _volume(folder: str, volume: int) -> tuple:
    """The rows of a volume by page, and their pages."""
    import pyarrow as pa
    from pyarrow import fs
    from pyarrow import parquet

    store, path = fs.FileSystem.from_uri(folder) if ":/" in folder else (fs.LocalFileSystem(), folder)
    files = store.get_file_info(fs.FileSelector(f"{path}/volume={volume}", allow_not_found=True))
    found = [parquet.ParquetFile(store.open_input_file(f.path)).read(["id", "page", "body"]) for f in files if f.path.endswith(".parquet")]
    rows = pa.concat_tables(found) if found else pa.table({"id": pa.array([], pa.int64()), "page": pa.array([], pa.int32()), "body": pa.array([], pa.string())})
    rows = rows.sort_by("page")
    return rows, rows.column("page").to_numpy()


def listed_page(page: int, options: dict[str, str]) -> Iterator[tuple]:
    rows, pages = _volume(options["folder"], page // VOLUME)
    begin, end = pages.searchsorted((page, page + 1)).tolist()
    yield from zip(*(c.to_pylist() for c in rows.slice(begin, end - begin).columns), strict=True)
