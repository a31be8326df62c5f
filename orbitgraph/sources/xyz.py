"""Structure files: a Python data source for extended-XYZ text (count, comment with the lattice, species and positions).

Paths are read with Spark's own binary reader in :func:`read_structures`, so any store that Spark knows will do; the data
source form serves local and mounted folders."""

from __future__ import annotations

import glob
import os
import re
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SYMBOLS = {72: "Hf", 8: "O", 32: "Ge", 51: "Sb", 52: "Te"}
NUMBERS = {v: k for k, v in SYMBOLS.items()}
SCHEMA = "structure_id string, atom_id long, species int, x double, y double, z double, lx double, ly double, lz double"


def parse(name: str, text: str) -> Iterator[tuple]:
    """Rows of every frame of a file."""
    lines, at, frame = text.split("\n"), 0, 0
    while at < len(lines) and lines[at].strip():
        n = int(lines[at])
        found = re.search(r'Lattice="([^"]*)"', lines[at + 1])
        box = [float(v) for v in found[1].split()] if found else [0.0] * 9
        for i, line in enumerate(lines[at + 2 : at + 2 + n]):
            symbol, x, y, z = line.split()[:4]
            yield (f"{name}#{frame}", i, NUMBERS[symbol], float(x), float(y), float(z), box[0], box[4], box[8])
        at, frame = at + 2 + n, frame + 1


def render(rows: list[tuple[int, float, float, float]], lengths: tuple[float, float, float]) -> str:
    lx, ly, lz = lengths
    head = f'{len(rows)}\nLattice="{lx!r} 0 0 0 {ly!r} 0 0 0 {lz!r}" Properties=species:S:1:pos:R:3\n'
    return head + "".join(f"{SYMBOLS[s]} {x!r} {y!r} {z!r}\n" for s, x, y, z in rows)


def read_structures(spark: SparkSession, path: str) -> DataFrame:
    files = spark.read.format("binaryFile").load(path).select("path", "content")

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            for name, content in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                rows = list(parse(os.path.basename(name), content.decode()))
                if rows:
                    kinds = (pa.string(), pa.int64(), pa.int32(), *[pa.float64()] * 6)
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=[f.split()[0] for f in SCHEMA.split(", ")])

    return files.mapInArrow(run, SCHEMA)


class XyzSource(DataSource):
    """spark.dataSource.register(XyzSource); spark.read.format("xyz").load(folder)"""

    @classmethod
    def name(cls) -> str:
        return "xyz"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _XyzReader(self.options["path"])


class _XyzReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(p) for p in sorted(glob.glob(os.path.join(self.path, "*.xyz")) or [self.path])]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        with open(partition.value) as f:
            yield from parse(os.path.basename(partition.value), f.read())


def write_coo(coo: DataFrame, path: str, row_block: int = 100_000) -> None:
    """Matrix elements as Parquet, partitioned by blocks of rows."""
    coo.withColumn("row_block", F.floor(F.col("row") / row_block)).write.partitionBy("row_block").parquet(path)


def write_matrix_market(coo: DataFrame, path: str, size: int) -> None:
    """Lines of a Matrix-Market body (one-based), with the header in a file of its own beside them."""
    coo.select(F.concat_ws(" ", F.col("row") + 1, F.col("col") + 1, F.col("val"))).write.text(f"{path}/body")
    head = f"%%MatrixMarket matrix coordinate real general\n{size} {size} {coo.count()}"
    coo.sparkSession.createDataFrame([(head,)], "value string").coalesce(1).write.text(f"{path}/head")


def write_by_rank(edges: DataFrame, table: str, parts: int) -> None:
    """Edges bucketed by rank and sorted by destination: joins and groups on rank then need no exchange."""
    edges.write.bucketBy(parts, "rank").sortBy("dst").mode("overwrite").saveAsTable(table)
