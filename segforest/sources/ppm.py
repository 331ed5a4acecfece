"""Images as binary netpbm (P6) files: a Spark data source that writes pixels at their offsets, and reads them back.

Rows: x int, y int, r int, g int, b int. Options: path, width, height. All tasks write into one file of final
size, at the pixels' offsets, so ``path`` is on a file system that driver and executors share and that has strided writes (a path or a file: URI; other
schemes are an error). The driver makes header and size before, so pixels
without a row are black. A task sorts each batch by offset and writes runs of neighbouring pixels at once; of several rows of a
pixel any one stays. A task that is run again writes the same bytes."""

from __future__ import annotations

import os
from dataclasses import dataclass

import numpy as np
from pyspark.sql.datasource import DataSource, DataSourceArrowWriter, DataSourceReader, InputPartition, WriterCommitMessage

SCHEMA = "x int, y int, r int, g int, b int"


class PpmSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "ppm"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema):
        return PpmReader(local(self.options["path"]))

    def writer(self, schema, overwrite):
        return PpmWriter(local(self.options["path"]), int(self.options["width"]), int(self.options["height"]))


def local(path: str) -> str:
    """The path of a file: URI."""
    if path.startswith("file:"):
        path = "/" + path[5:].lstrip("/")
    if "://" in path:
        raise ValueError(f"{path}: no strided writes there")
    return path


def header(w: int, h: int) -> bytes:
    return f"P6\n{w} {h}\n255\n".encode()


@dataclass
class Done(WriterCommitMessage):
    pixels: int


class PpmWriter(DataSourceArrowWriter):
    def __init__(self, path: str, w: int, h: int):
        self.path, self.w, self.h = path, w, h
        with open(path, "wb") as f:
            f.write(header(w, h))
            f.truncate(len(header(w, h)) + 3 * w * h)

    def write(self, batches):
        n, start = 0, len(header(self.w, self.h))
        fd = os.open(self.path, os.O_WRONLY)
        try:
            for batch in batches:
                x, y, *rgb = (np.asarray(batch.column(k)) for k in range(5))
                if not len(x):
                    continue
                at, first = np.unique(y.astype(np.int64) * self.w + x, return_index=True)
                data = np.stack(rgb, 1).astype(np.uint8)[first]
                cuts = np.flatnonzero(np.diff(at) != 1) + 1
                for lo, hi in zip(np.append(0, cuts), np.append(cuts, len(at))):
                    os.pwrite(fd, data[lo:hi].tobytes(), start + 3 * int(at[lo]))
                n += len(x)
        finally:
            os.close(fd)
        return Done(n)

    def commit(self, messages):
        if os.path.getsize(self.path) != len(header(self.w, self.h)) + 3 * self.w * self.h:
            raise ValueError("image size")

    def abort(self, messages):
        if os.path.exists(self.path):
            os.remove(self.path)


@dataclass
class Rows(InputPartition):
    first: int
    end: int


class PpmReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path
        with open(path, "rb") as f:
            magic, size, _ = f.readline(), f.readline(), f.readline()
            if magic != b"P6\n":
                raise ValueError("not a P6 file")
            self.w, self.h = map(int, size.split())
            self.start = f.tell()

    def partitions(self):
        step = max(1, -(-self.h // 8))
        return [Rows(y, min(self.h, y + step)) for y in range(0, self.h, step)]

    def read(self, part):
        with open(self.path, "rb") as f:
            f.seek(self.start + 3 * part.first * self.w)
            for y in range(part.first, part.end):
                row = f.read(3 * self.w)
                for x in range(self.w):
                    yield x, y, row[3 * x], row[3 * x + 1], row[3 * x + 2]
