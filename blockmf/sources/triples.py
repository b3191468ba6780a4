"""A Python data source 'ratings_text' for rating triples in text files: batch read with one partition per file, and write."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage

SCHEMA = "u bigint, v bigint, r double"


class FilePart(InputPartition):
    def __init__(self, path: str):
        self.path = path


def _fs(path: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(path if "://" in path else f"file://{path}")


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.sep = options["path"], options.get("sep")

    def partitions(self) -> list[FilePart]:
        from pyarrow import fs

        f, root = _fs(self.path)
        return [FilePart(x.path) for x in f.get_file_info(fs.FileSelector(root)) if x.is_file and not x.base_name.startswith(("_", "."))]

    def read(self, partition: FilePart) -> Iterator[tuple]:
        f, _ = _fs(self.path)
        with f.open_input_stream(partition.path) as s:
            for line in s.read().decode().splitlines():
                parts = line.split(self.sep)
                if len(parts) >= 3:
                    yield int(parts[0]), int(parts[1]), float(parts[2])


class _Done(WriterCommitMessage):
    def __init__(self, temp: str, name: str):
        self.temp, self.name = temp, name


class _Writer(DataSourceWriter):
    def __init__(self, options: dict):
        self.path, self.sep = options["path"], options.get("sep", " ")

    def write(self, rows: Iterator) -> _Done:
        import uuid

        from pyspark import TaskContext

        f, root = _fs(self.path)
        f.create_dir(root, recursive=True)
        name = f"{root}/part-{TaskContext.get().partitionId():05d}.txt"
        temp = f"{root}/_{uuid.uuid4().hex}"
        with f.open_output_stream(temp) as s:
            for row in rows:
                s.write((self.sep.join(map(str, row)) + "\n").encode())
        return _Done(temp, name)

    def commit(self, messages: list) -> None:
        f, _ = _fs(self.path)
        for m in messages:
            if m is not None:
                f.move(m.temp, m.name)

    def abort(self, messages: list) -> None:
        f, _ = _fs(self.path)
        for m in messages:
            if m is not None:
                f.delete_file(m.temp)


class RatingsText(DataSource):
    @classmethod
    def name(cls) -> str:
        return "ratings_text"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> _Reader:
        return _Reader(self.options)

    def writer(self, schema, overwrite: bool) -> _Writer:
        return _Writer(self.options)


def register(spark) -> None:
    spark.dataSource.register(RatingsText)
