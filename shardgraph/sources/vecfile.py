"""Length-prefixed vector files as a Spark data source, batch and stream."""

from __future__ import annotations

import struct
from collections.abc import Iterator
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceStreamReader, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual

#: Component types of the format: name -> (numpy type, bytes).
KINDS = {"float32": ("<f4", 4), "uint8": ("u1", 1)}


def write_vecfile(path: str, vectors: np.ndarray, kind: str = "float32") -> None:
    """Each record is the dimension as int32 and the components."""
    x = np.asarray(vectors)
    with open(path, "wb") as f:
        for row in x.astype(KINDS[kind][0]):
            f.write(struct.pack("<i", x.shape[1]) + row.tobytes())


class Range(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class _Reader:
    def __init__(self, options: dict):
        self.path = options["path"]
        self.dtype, width = KINDS[options.get("kind", "float32")]
        with open(self.path, "rb") as f:
            head = f.read(4)
        self.dim = struct.unpack("<i", head)[0] if len(head) == 4 else 0
        self.record = 4 + self.dim * width
        self.rows_per_part = int(options.get("rowsPerPartition", "100000"))

    def count(self) -> int:
        return Path(self.path).stat().st_size // self.record if self.dim else 0

    def ranges(self, first: int, last: int) -> list[Range]:
        return [Range(a, min(a + self.rows_per_part, last)) for a in range(first, last, self.rows_per_part)] or [Range(first, first)]

    def rows(self, part: Range) -> Iterator[pa.RecordBatch]:
        with open(self.path, "rb") as f:
            f.seek(part.first * self.record)
            for a in range(part.first, part.last, 4096):
                n = min(4096, part.last - a)
                raw = np.frombuffer(f.read(n * self.record), np.uint8).reshape(n, self.record)
                if (raw[:, :4].copy().view("<i4") != self.dim).any():
                    raise ValueError(f"{self.path}: records differ in dimension")
                x = np.ascontiguousarray(raw[:, 4:]).view(self.dtype).astype(np.float32)
                offsets = pa.array(np.arange(n + 1, dtype=np.int32) * self.dim)
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(a, a + n)), pa.ListArray.from_arrays(offsets, pa.array(x.ravel()))], names=["vec_id", "embedding"])


class VecBatchReader(DataSourceReader):
    """Splits by byte ranges; bounds on vec_id cut the range before anything is read."""

    def __init__(self, options: dict):
        self.reader = _Reader(options)
        self.low, self.high = 0, self.reader.count()

    def pushFilters(self, filters):  # noqa: N802
        for f in filters:
            if getattr(f, "attribute", None) == ("vec_id",):
                if isinstance(f, GreaterThanOrEqual):
                    self.low = max(self.low, f.value)
                    continue
                if isinstance(f, GreaterThan):
                    self.low = max(self.low, f.value + 1)
                    continue
                if isinstance(f, LessThanOrEqual):
                    self.high = min(self.high, f.value + 1)
                    continue
                if isinstance(f, LessThan):
                    self.high = min(self.high, f.value)
                    continue
            yield f

    def partitions(self):
        return self.reader.ranges(self.low, max(self.low, self.high))

    def read(self, partition):
        return self.reader.rows(partition)


class VecStreamReader(DataSourceStreamReader):
    """Offsets count records, so a growing file is a stream of blocks."""

    def __init__(self, options: dict):
        self.reader = _Reader(options)

    def initialOffset(self):  # noqa: N802
        return {"row": 0}

    def latestOffset(self):  # noqa: N802
        return {"row": self.reader.count()}

    def partitions(self, start, end):
        return self.reader.ranges(start["row"], end["row"])

    def read(self, partition):
        return self.reader.rows(partition)


class VecFile(DataSource):
    @classmethod
    def name(cls) -> str:
        return "vecfile"

    def schema(self) -> str:
        return "vec_id bigint, embedding array<float>"

    def reader(self, schema) -> DataSourceReader:
        return VecBatchReader(dict(self.options))

    def streamReader(self, schema) -> DataSourceStreamReader:  # noqa: N802
        return VecStreamReader(dict(self.options))
