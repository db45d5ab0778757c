"""A data source of raw block files: one file a block of a brick, a JSON header line (box, ghost layer, value form), then the values; one partition a file.
Paths are of a file system that the driver and all tasks have mounted."""

from __future__ import annotations

import glob
import json
import os

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..operators.array_engine import blank


class CubeBin(DataSource):
    @classmethod
    def name(cls) -> str:
        return "cubebin"

    def schema(self) -> str:
        return "brick int, x long, y long, z long, v long"

    def reader(self, schema) -> DataSourceReader:
        return CubeBinReader(self.options["path"], self.options.get("bricks"))


class CubeBinReader(DataSourceReader):
    """Option bricks: comma-separated numbers; other files are not opened."""

    def __init__(self, path: str, bricks: str | None):
        self.path, self.bricks = path, None if bricks is None else {int(b) for b in bricks.split(",")}

    def partitions(self):
        files = sorted(glob.glob(os.path.join(self.path, "brick-*.bin")))
        number = lambda f: int(os.path.basename(f).split("-")[1])
        return [InputPartition(f) for f in files if self.bricks is None or number(f) in self.bricks]

    def read(self, partition):
        with open(partition.value, "rb") as file:
            head = json.loads(file.readline())
            x0, x1, y0, y1, z0, z1 = head["box"]
            ghost = head["ghost"]
            cells = np.frombuffer(file.read(), head["dtype"]).reshape(x1 - x0 + 2 * ghost, y1 - y0 + 2 * ghost, z1 - z0 + 2 * ghost)
        own = slice(ghost, -ghost) if ghost else slice(None)
        cells = cells[own, own, own]
        x, y, z = np.nonzero(~blank(cells))
        yield pa.RecordBatch.from_arrays(
            [pa.array(np.full(len(x), head["brick"], np.int32)), pa.array(x + x0), pa.array(y + y0), pa.array(z + z0), pa.array(cells[x, y, z].astype(np.int64))], ["brick", "x", "y", "z", "v"]
        )


def write(bricks: DataFrame, path: str) -> None:
    """Brick rows to files, by the tasks; path is a folder that all of them share."""

    def save(rows):
        os.makedirs(path, exist_ok=True)
        for r in rows:
            head = {"brick": r["brick"], "box": [r[c] for c in ("x0", "x1", "y0", "y1", "z0", "z1")], "ghost": r["ghost"], "dtype": r["dtype"]}
            with open(os.path.join(path, f"brick-{r['brick']:06d}-{r['block']}.bin"), "wb") as file:
                file.write(json.dumps(head).encode() + b"\n" + bytes(r["data"]))

    bricks.foreachPartition(save)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(CubeBin)
