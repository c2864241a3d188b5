"""``spark.read.format("lattice")`` over stored groups, with filters on ts pushed to their statistics."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceArrowWriter, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual, WriterCommitMessage

from lattice_pages.operators.codec import _GROUP, NEEDED, ROW_DDL, decoder


class LatticeSource(DataSource):
    """Value rows of a folder written by ``codec.save``, or group rows written to one.

    ``df.write.format("lattice").option("path", ...)`` takes the rows of ``codec.encode``.
    """

    @classmethod
    def name(cls) -> str:
        return "lattice"

    def schema(self) -> str:
        return ROW_DDL

    def reader(self, schema) -> DataSourceReader:
        return LatticeReader(self.options["path"])

    def writer(self, schema, overwrite: bool) -> DataSourceArrowWriter:
        if schema.names != _GROUP.names:
            raise ValueError("only group rows, as codec.encode gives them, can be written")
        return LatticeWriter(self.options["path"], overwrite)


@dataclass
class Written(WriterCommitMessage):
    file: str | None
    groups: int


def _place(path: str):
    """(file system, path in it)."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(path) if "://" in path or path.startswith(("/", "file:")) else (fs.LocalFileSystem(), path)


class LatticeWriter(DataSourceArrowWriter):
    """One Parquet file a task, under a hidden name until the job commits; the bytes of pages are not compressed again."""

    def __init__(self, path: str, overwrite: bool) -> None:
        self.path, self.overwrite = path, overwrite

    def write(self, iterator: Iterator) -> Written:
        import uuid

        import pyarrow as pa
        import pyarrow.parquet as pq

        files, at = _place(self.path)
        files.create_dir(at, recursive=True)
        name, groups, out = f"{at}/_part-{uuid.uuid4().hex}.parquet", 0, None
        for b in iterator:
            if b.num_rows:
                out = out or pq.ParquetWriter(name, _GROUP, filesystem=files, compression="none")
                out.write_table(pa.Table.from_batches([b]).cast(_GROUP))
                groups += b.num_rows
        if out:
            out.close()
        return Written(name if out else None, groups)

    def commit(self, messages: list) -> None:
        files, at = _place(self.path)
        if self.overwrite:
            from pyarrow import fs

            for old in files.get_file_info(fs.FileSelector(at, allow_not_found=True)):
                if not old.base_name.startswith(("_", ".")):
                    files.delete_file(old.path)
        for m in messages:
            if m is not None and m.file:
                folder, name = m.file.rsplit("/", 1)
                files.move(m.file, f"{folder}/{name[1:]}")

    def abort(self, messages: list) -> None:
        files, _ = _place(self.path)
        for m in messages:
            if m is not None and m.file:
                files.delete_file(m.file)


class LatticeReader(DataSourceReader):
    def __init__(self, path: str) -> None:
        self.path = path
        self.lo, self.hi, self.stream = -(1 << 62), 1 << 62, None

    def pushFilters(self, filters: list[Filter]) -> Iterable[Filter]:
        """Keeps bounds on ts and one stream for pruning; Spark applies every filter again to the rows."""
        for f in filters:
            column = getattr(f, "attribute", None)
            if column == ("ts",):
                if isinstance(f, (GreaterThan, GreaterThanOrEqual, EqualTo)):
                    self.lo = max(self.lo, f.value)
                if isinstance(f, (LessThan, LessThanOrEqual, WriterCommitMessage, EqualTo)):
                    self.hi = min(self.hi, f.value)
            elif column == ("stream_id",) and isinstance(f, EqualTo):
                self.stream = f.value
            yield f

    def partitions(self) -> list[InputPartition]:
        import pyarrow.dataset as ds
        from pyarrow import fs

        files, place = fs.FileSystem.from_uri(self.path) if "://" in self.path or self.path.startswith(("/", "file:")) else (None, self.path)
        return [InputPartition(f) for f in ds.dataset(place, format="parquet", filesystem=files).files]

    def read(self, partition: InputPartition) -> Iterator:
        import pyarrow.compute as pc
        import pyarrow.dataset as ds
        from pyarrow import fs

        files = fs.FileSystem.from_uri(self.path)[0] if "://" in self.path or self.path.startswith(("/", "file:")) else None
        hit = (pc.field("max_ts") >= self.lo) & (pc.field("min_ts") <= self.hi) | pc.field("max_ts").is_null()
        if self.stream is not None:
            hit = hit & (pc.field("stream_id") == self.stream)
        rows = ds.dataset(partition.value, format="parquet", filesystem=files).to_batches(filter=hit, columns=list(NEEDED), batch_size=8)
        keep = lambda d: d["max_ts"] is None or (d["max_ts"] >= self.lo and d["min_ts"] <= self.hi)
        yield from decoder(keep=keep)(rows)


def register(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(LatticeSource)
