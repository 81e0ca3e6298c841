"""Matrix Market and XYZ coordinate files as Spark data sources: ``spark.read.format("matrix_market").load(path)``."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def _open(path: str):
    from pyarrow import fs

    store, place = fs.FileSystem.from_uri(path if "://" in path else f"file://{path}")
    return store.open_input_file(place)


class ByteRange(InputPartition):
    """Lines that start from byte ``start`` to before ``end``."""

    def __init__(self, start: int, end: int):
        super().__init__((start, end))
        self.start, self.end = start, end


def _lines(path: str, start: int, end: int) -> Iterator[str]:
    with _open(path) as f:
        f.seek(max(0, start - 1))
        left = b"" if start == 0 else None
        at = max(0, start - 1)
        while True:
            chunk = f.read(1 << 20)
            if left is None:  # in the middle of a line that belongs to the range before
                cut = chunk.find(b"\n")
                if cut < 0 and chunk:
                    at += len(chunk)
                    continue
                left, chunk, at = b"", chunk[cut + 1 :], at + cut + 1
            data = left + chunk
            done = not chunk
            lines = data.split(b"\n")
            left = b"" if done else lines.pop()
            for line in lines:
                if at >= end:
                    return
                at += len(line) + 1
                if line.strip():
                    yield line.decode()
            if done:
                return


class MatrixMarketReader(DataSourceReader):
    def __init__(self, options):
        self.path, self.split = options["path"], int(options.get("split", 1 << 26))
        with _open(self.path) as f:
            head, at = f.read(1 << 16), 0
            self.size = f.size()
        banner, _, rest = head.partition(b"\n")
        words = banner.decode().lower().split()
        if words[:3] != ["%%matrixmarket", "matrix", "coordinate"] or words[3] not in ("real", "integer", "pattern"):
            raise ValueError("only coordinate matrices of real, integer or pattern entries")
        self.kind, self.mirror = words[3], words[4] == "symmetric"
        at = len(banner) + 1
        while rest.startswith(b"%"):
            line, _, rest = rest.partition(b"\n")
            at += len(line) + 1
        self.first = at + len(rest.partition(b"\n")[0]) + 1

    def partitions(self):
        return [ByteRange(a, min(a + self.split, self.size)) for a in range(self.first, max(self.size, self.first + 1), self.split)]

    def read(self, partition):
        for line in _lines(self.path, partition.start, partition.end):
            parts = line.split()
            i, j, v = int(parts[0]) - 1, int(parts[1]) - 1, float(parts[2]) if self.kind != "pattern" else 1.0
            yield i, j, v
            if self.mirror and i != j:
                yield j, i, v


class MatrixMarket(DataSource):
    """Rows (row, col, val), from 0; a symmetric file gives both triangles. Option ``split``: bytes a partition."""

    @classmethod
    def name(cls):
        return "matrix_market"

    def schema(self):
        return "row long, col long, val double"

    def reader(self, schema):
        return MatrixMarketReader(self.options)


class XyzReader(DataSourceReader):
    def __init__(self, options):
        self.path = options["path"]

    def read(self, partition):
        with _open(self.path) as f:
            lines = f.read().decode().split("\n")
        at = frame = 0
        while at < len(lines) and lines[at].strip():
            n = int(lines[at])
            for k, line in enumerate(lines[at + 2 : at + 2 + n]):
                s, x, y, z = line.split()[:4]
                yield frame, k, s, float(x), float(y), float(z)
            at, frame = at + 2 + n, frame + 1


class Xyz(DataSource):
    """Rows (frame, atom_id, species, x, y, z) of a file of frames."""

    @classmethod
    def name(cls):
        return "xyz"

    def schema(self):
        return "frame long, atom_id long, species string, x double, y double, z double"

    def reader(self, schema):
        return XyzReader(self.options)


def register(spark: SparkSession) -> None:
    """Make both formats known to the session."""
    spark.dataSource.register(MatrixMarket)
    spark.dataSource.register(Xyz)


def write_matrix_market(m: DataFrame, path: str) -> None:
    """One folder of text parts in row order, entries only; ``header`` goes before them when they are put together."""
    m.orderBy("row", "col").select(F.concat_ws(" ", F.col("row") + 1, F.col("col") + 1, "val").alias("value")).write.mode("overwrite").text(path)


def header(m: DataFrame) -> str:
    n = m.agg(F.max("row"), F.max("col"), F.count(F.lit(1))).first()
    return f"%%MatrixMarket matrix coordinate real general\n{n[0] + 1} {n[1] + 1} {n[2]}\n"
