"""A reader for crystal text files (key-value lines and an atom loop) as a Spark data source."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "structure_id bigint, element string, x double, y double, w double"


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.options = options

    def partitions(self) -> list[InputPartition]:
        from pyarrow import fs

        files, root = fs.FileSystem.from_uri(self.options["path"])
        infos = files.get_file_info(fs.FileSelector(root, recursive=True))
        return [_File(i.path) for i in sorted(infos, key=lambda i: i.path) if i.is_file and i.path.endswith(self.options.get("suffix", ".cif"))]

    def read(self, partition: _File) -> Iterator[tuple]:
        from pyarrow import fs

        files, _ = fs.FileSystem.from_uri(self.options["path"])
        with files.open_input_stream(partition.path) as stream:
            lines = stream.read().decode().splitlines()
        number, columns, looping = None, [], False
        for line in lines:
            parts = line.split()
            if not parts or parts[0].startswith("#"):
                continue
            if parts[0].startswith("data_"):
                looping = False
            elif parts[0] == "loop_":
                columns, looping = [], True
            elif parts[0].startswith("_"):
                if looping:
                    columns.append(parts[0])
                elif parts[0] == "_structure_number":
                    number = int(parts[1])
            elif looping and "_atom_site_type_symbol" in columns and len(parts) == len(columns):
                row = dict(zip(columns, parts))
                yield number, row["_atom_site_type_symbol"], *(float(row[f"_atom_site_Cartn_{c}"]) for c in "xyz")


class CrystalTextSource(DataSource):
    """``spark.read.format("crystaltext").load(uri)``: one partition per file; a file holds one structure or several (``data_`` blocks)."""

    @classmethod
    def name(cls) -> str:
        return "crystaltext"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)
