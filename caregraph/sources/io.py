"""Sources and sinks around the graph."""

from __future__ import annotations

import hashlib
import io
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceStreamReader, InputPartition
from pyspark.sql.types import StructType

from caregraph.schema import TRIPLE
from caregraph.sources import ntriples


def read(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | StructType | None = None, **options: str) -> DataFrame:
    r = spark.read.format(fmt).options(**options)
    return (r.schema(schema) if schema else r).load(path)


def write(df: DataFrame, path: str, fmt: str = "parquet", partition_by: tuple[str, ...] = (), mode: str = "errorifexists", **options: str) -> None:
    w = df.write.format(fmt).mode(mode).options(**options)
    (w.partitionBy(*partition_by) if partition_by else w).save(path)


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int, sort: tuple[str, ...] = ()) -> None:
    """A table bucketed by ``key``, so later joins and windows on it need no exchange."""
    w = df.write.mode("overwrite").bucketBy(buckets, key)
    (w.sortBy(*sort) if sort else w).saveAsTable(table)


def jdbc(spark: SparkSession, url: str, table: str, key: str, lower: int, upper: int, parts: int, **options: str):
    """A reader of a database table in ``parts`` ranges of a numeric key; load() needs the database's driver."""
    return spark.read.format("jdbc").options(url=url, dbtable=table, partitionColumn=key, lowerBound=str(lower), upperBound=str(upper), numPartitions=str(parts), **options)


def _files(path: str) -> list[tuple[str, int]]:
    """(path, bytes) of the text files in a folder, by name; the folder may be on any file system that Arrow knows."""
    fs, root = _fs(path)
    found = fs.get_file_info(pafs.FileSelector(root, recursive=True))
    return sorted((f.path, f.size) for f in found if f.type == pafs.FileType.File and not f.base_name.startswith(("_", ".")) and f.size)


def _fs(path: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (pafs.LocalFileSystem(), path)


class _Piece(InputPartition):
    def __init__(self, path: str, start: int, end: int):
        self.path, self.start, self.end = path, start, end


def _pieces(files: list[tuple[str, int]], size: int) -> list[InputPartition]:
    """Ranges of at most ``size`` bytes; a line belongs to the range that it begins in."""
    return [_Piece(p, at, min(at + size, n)) for p, n in files for at in range(0, n, size)]


def _read_piece(folder: str, piece: _Piece) -> Iterator[pa.RecordBatch]:
    fs, _ = _fs(folder)
    rows: list[tuple] = []
    with fs.open_input_file(piece.path) as raw:
        f = io.BufferedReader(raw, 1 << 20)
        if piece.start:
            f.seek(piece.start - 1)
            f.readline()
        while f.tell() < piece.end and (line := f.readline()):
            row = ntriples.parse_line(line.decode().rstrip("\r\n"))
            if row:
                rows.append(row)
            if len(rows) >= 10_000:
                yield _batch(rows)
                rows = []
    if rows:
        yield _batch(rows)


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    names = ("s", "p", "o", "o_kind", "datatype", "lang")
    return pa.RecordBatch.from_arrays([pa.array(c, pa.string()) for c in zip(*rows, strict=True)], names=list(names))


class _Reader(DataSourceReader):
    def __init__(self, path: str, size: int):
        self.path, self.size = path, size

    def partitions(self) -> list[InputPartition]:
        return _pieces(_files(self.path), self.size) or [_Piece("", 0, 0)]

    def read(self, partition: _Piece):
        if partition.path:
            yield from _read_piece(self.path, partition)


class _StreamReader(DataSourceStreamReader):
    """Offsets count files in the order of their names, so writers must name later files later."""

    def __init__(self, path: str, size: int):
        self.path, self.size = path, size

    def initialOffset(self) -> dict:
        return {"files": 0}

    def latestOffset(self) -> dict:
        return {"files": len(_files(self.path))}

    def partitions(self, start: dict, end: dict) -> list[InputPartition]:
        return _pieces(_files(self.path)[start["files"] : end["files"]], self.size)

    def read(self, partition: _Piece):
        yield from _read_piece(self.path, partition)


class TripleSource(DataSource):
    """Format ``cg_triples``: a folder of N-Triples files, as a table or as a stream; large files are read in ranges of ``bytes``."""

    @classmethod
    def name(cls) -> str:
        return "cg_triples"

    def schema(self) -> str:
        return TRIPLE

    def reader(self, schema: StructType) -> DataSourceReader:
        return _Reader(self.options["path"], int(self.options.get("bytes", 64 << 20)))

    def streamReader(self, schema: StructType) -> DataSourceStreamReader:
        return _StreamReader(self.options["path"], int(self.options.get("bytes", 64 << 20)))


def digest(df: DataFrame) -> str:
    """A digest of a small result, whatever its row order; for tests."""
    return hashlib.sha256("\n".join(sorted(map(str, df.collect()))).encode()).hexdigest()
