"""A Spark data source for coordinate text: a banner, % comments, a line of sizes, then 1-based `row col [value]`."""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class CoordinatePartition(InputPartition):
    def __init__(self, path: str, start: int, end: int):
        self.path, self.start, self.end = path, start, end


def open_stream(path: str):
    from pyarrow import fs

    system, p = fs.FileSystem.from_uri(path) if ":/" in path else (fs.LocalFileSystem(), path)
    return system.open_input_file(p)


class CoordinateReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path = options["path"]
        self.split = int(options.get("split", 16 << 20))
        self.base = int(options.get("base", 1))

    def header(self) -> tuple[int, bool, bool]:
        """(offset of the first entry, pattern without values, symmetric)."""
        with open_stream(self.path) as f:
            data, at, banner = f.read(1 << 16), 0, b""
            while True:
                line_end = data.index(b"\n", at)
                line = data[at:line_end].strip()
                at = line_end + 1
                if line.startswith(b"%%"):
                    banner = line.lower()
                elif line and not line.startswith(b"%"):
                    return at, b"pattern" in banner, b"symmetric" in banner

    def partitions(self) -> list[InputPartition]:
        first, self.pattern, self.symmetric = self.header()
        with open_stream(self.path) as f:
            size = f.size()
        return [CoordinatePartition(self.path, a, min(a + self.split, size)) for a in range(first, max(size, first + 1), self.split)]

    def read(self, partition: CoordinatePartition):
        """Lines that begin in the partition's byte range."""
        first, pattern, symmetric = self.header()
        with open_stream(partition.path) as f:
            at = partition.start
            f.seek(max(at - 1, 0))
            if at > first and f.read(1) != b"\n":
                at += len(self._line(f, at)) + 1
            f.seek(at)
            while at < partition.end:
                block = f.read(partition.end - at)
                if not block.endswith(b"\n"):
                    block += self._line(f, at + len(block))
                for line in block.split(b"\n"):
                    if x := line.split():
                        i, j, v = int(x[0]) - self.base, int(x[1]) - self.base, 1.0 if pattern else float(x[2])
                        yield i, j, v
                        if symmetric and i != j:
                            yield j, i, v
                return

    @staticmethod
    def _line(f, at: int) -> bytes:
        f.seek(at)
        out = b""
        while b"\n" not in out:
            more = f.read(1 << 12)
            if not more:
                return out
            out += more
        return out[: out.index(b"\n")]


class CoordinateSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "coordinate"

    def schema(self) -> str:
        return "row bigint, col bigint, val double"

    def reader(self, schema) -> DataSourceReader:
        return CoordinateReader(self.options)


def read_coordinate(spark, path: str, *, base: int = 1):
    """(row, col, val) of a coordinate file, ids from 0."""
    spark.dataSource.register(CoordinateSource)
    return spark.read.format("coordinate").option("path", path).option("base", str(base)).load()
