"""A Python data source for tiles of road segments kept as text files of WKT lines.

A folder holds one file a tile, ``<tile>.tsv``; a row is LINESTRING, road class,
direction and weight, parted by tabs. ``spark.read.format("wkt_tiles").load(folder)``
reads each file as one partition; the option ``tiles`` (numbers, comma-joined)
leaves only those files. A writer keeps the same form.
"""

from __future__ import annotations

import os
from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage
from pyspark.sql.types import StructType

SCHEMA = "tile bigint, wkt string, road_class string, direction string, weight bigint"


@dataclass
class Tile(InputPartition):
    path: str
    tile: int


@dataclass
class Written(WriterCommitMessage):
    files: list[str]


class WktTiles(DataSource):
    @classmethod
    def name(cls) -> str:
        return "wkt_tiles"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema: StructType) -> DataSourceReader:
        return Reader(self.options["path"], self.options.get("tiles"))

    def writer(self, schema: StructType, overwrite: bool) -> DataSourceWriter:
        return Writer(self.options["path"], overwrite, schema.names)


class Reader(DataSourceReader):
    """One partition a file."""

    def __init__(self, folder: str, tiles: str | None) -> None:
        self.folder, self.only = folder, None if tiles is None else {int(t) for t in tiles.split(",")}

    def partitions(self) -> list[Tile]:
        names = sorted(n for n in os.listdir(self.folder) if n.endswith(".tsv"))
        tiles = [Tile(os.path.join(self.folder, n), int(n.split("-")[0].removesuffix(".tsv"))) for n in names]
        return [t for t in tiles if self.only is None or t.tile in self.only] or [Tile("", -1)]

    def read(self, partition: Tile) -> Iterator[tuple]:
        if partition.path:
            with open(partition.path, encoding="utf-8") as rows:
                for row in rows:
                    wkt, road, direction, weight = row.rstrip("\n").split("\t")
                    yield partition.tile, wkt, road, direction, int(weight)


class Writer(DataSourceWriter):
    """A task writes one file for each tile that it holds; files count only once the job commits."""

    def __init__(self, folder: str, overwrite: bool, names: list[str]) -> None:
        self.folder, self.overwrite, self.names = folder, overwrite, names

    def write(self, rows: Iterator) -> Written:
        from pyspark import TaskContext

        task, files = TaskContext.get().taskAttemptId(), {}
        os.makedirs(self.folder, exist_ok=True)
        for row in rows:
            r = row.asDict()
            if r["tile"] not in files:
                files[r["tile"]] = open(os.path.join(self.folder, f"{r['tile']}-{task}.tsv.part"), "w", encoding="utf-8")  # noqa: SIM115
            files[r["tile"]].write(f"{r['wkt']}\t{r['road_class']}\t{r['direction']}\t{r['weight']}\n")
        for f in files.values():
            f.close()
        return Written([f.name for f in files.values()])

    def commit(self, messages: list) -> None:
        done = [f for m in messages if m is not None for f in m.files]
        if self.overwrite and os.path.isdir(self.folder):
            for n in os.listdir(self.folder):
                if n.endswith(".tsv"):
                    os.remove(os.path.join(self.folder, n))
        for f in done:
            os.rename(f, f.removesuffix(".part"))

    def abort(self, messages: list) -> None:
        for m in messages:
            for f in m.files if m is not None else ():
                if os.path.exists(f):
                    os.remove(f)
