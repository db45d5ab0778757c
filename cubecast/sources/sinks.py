"""Frames and cubes out: JSON, image bytes, partitioned and bucketed tables."""

from __future__ import annotations

import os

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def frame_json(frame: DataFrame) -> DataFrame:
    """One JSON document a scan line: v, line. A line is bounded by the frame's width."""
    line = F.array_sort(F.collect_list(F.struct("u", "val")))
    return frame.groupBy("v").agg(F.to_json(line).alias("line"))


def frame_pgm(frame: DataFrame, width: int, height: int, folder: str, top: int) -> None:
    """Grey image bytes, one part file a band of scan lines; written by the tasks, the driver sees no pixel. folder is of a file system that all tasks have mounted."""

    def band(rows):
        import numpy as np

        rows = list(rows)
        if not rows:
            return
        image = np.zeros((height, width), np.uint8)
        for r in rows:
            image[r["v"], r["u"]] = min(255, r["val"] * 255 // max(1, top))
        lines = sorted({r["v"] for r in rows})
        os.makedirs(folder, exist_ok=True)
        with open(os.path.join(folder, f"band-{lines[0]:05d}.pgm"), "wb") as file:
            file.write(f"P5 {width} {len(lines)} 255\n".encode() + image[lines].tobytes())

    frame.repartitionByRange(4, "v").foreachPartition(band)


def write_bucketed(voxels: DataFrame, table: str, buckets: int = 8) -> None:
    """Voxels bucketed and sorted by brick, for joins without a shuffle."""
    voxels.write.mode("overwrite").bucketBy(buckets, "brick").sortBy("brick", "x", "y", "z").saveAsTable(table)
