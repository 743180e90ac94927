"""A data source of code snippets by page, for feeds that come in pages."""

from __future__ import annotations

from urllib.parse import unquote, urlparse

from pyspark.sql import DataFrame
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def write_pages(df: DataFrame, folder: str, size: int = 1000) -> None:
    """df (sample_id, code) as a feed: a Parquet file a page, of at most size rows."""
    df.select("sample_id", "code").write.option("maxRecordsPerFile", size).parquet(folder)


def _store(uri: str):
    """File system and path: plain files for file: and paths without a scheme, Arrow's systems for others."""
    from pyarrow import fs

    at = urlparse(uri)
    return (fs.LocalFileSystem(), unquote(at.path)) if at.scheme in ("", "file") else fs.FileSystem.from_uri(uri)


class _Page(InputPartition):
    def __init__(self, name: str):
        self.name = name


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.folder = options["path"]

    def partitions(self):
        from pyarrow import fs

        store, path = _store(self.folder)
        names = sorted(f.base_name for f in store.get_file_info(fs.FileSelector(path)) if f.base_name.endswith(".parquet") and f.base_name[0] not in "._")
        return [_Page(n) for n in names] or [_Page("")]

    def read(self, partition):
        import pyarrow.parquet as pq

        store, path = _store(self.folder)
        if partition.name:
            with store.open_input_file(f"{path}/{partition.name}") as f:
                yield from pq.ParquetFile(f).iter_batches(1024, columns=["sample_id", "code"])


class SnippetFeed(DataSource):
    """spark.dataSource.register(SnippetFeed); spark.read.format('snippets').option('path', folder).load(): sample_id, code of each page's rows."""

    @classmethod
    def name(cls):
        return "snippets"

    def schema(self):
        return "sample_id long, code string"

    def reader(self, schema):
        return _Reader(self.options)
