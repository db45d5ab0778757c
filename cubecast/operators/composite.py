"""Two-stage composition and its alternatives. Partials are (frame, node, brick, u, v, val); MIP merges in any order."""

from __future__ import annotations

import time
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.spec import ViewSpec

PIXEL_BYTES = 4


def node(partials: DataFrame) -> DataFrame:
    """First stage: partial images of a node's workers in one buffer."""
    return partials.groupBy("node", "u", "v").agg(F.max("val").alias("val"))


def final(node_images: DataFrame) -> DataFrame:
    """Second stage: the frame."""
    return node_images.groupBy("u", "v").agg(F.max("val").alias("val"))


def fill(frame: DataFrame, view: ViewSpec, background: int = 0) -> DataFrame:
    """All pixels; uncovered ones get the background."""
    n = view.width * view.height
    grid = frame.sparkSession.range(n).select((F.col("id") % view.width).cast("int").alias("u"), F.expr(f"int(id div {view.width})").alias("v"))
    return grid.join(frame, ["u", "v"], "left").withColumn("val", F.coalesce("val", F.lit(background)))


def tree(node_images: DataFrame, nodes: int, fanin: int = 2) -> DataFrame:
    """Multi-layer merge: log rounds of groups."""
    out = node_images
    while nodes > 1:
        out = out.withColumn("node", F.expr(f"int(node div {fanin})")).groupBy("node", "u", "v").agg(F.max("val").alias("val"))
        nodes = -(-nodes // fanin)
    return out.select("u", "v", "val")


def tiles(node_images: DataFrame, view: ViewSpec, across: int = 4) -> DataFrame:
    """Dedicated merging nodes, each the owner of a tile: a hash shuffle by tile."""
    w, h = -(-view.width // across), -(-view.height // across)
    tile = F.expr(f"int(u div {w}) * {across} + int(v div {h})")
    t = node_images.withColumn("tile", tile).repartition("tile")
    return t.groupBy("tile", "u", "v").agg(F.max("val").alias("val")).select("u", "v", "val")


#: A pixel that no partial covers. Pixels travel as four bytes each; of a message with a value that needs more, the upper four
#: bytes of all pixels travel beside them in ``high``, which is null otherwise.
BLANK = int(np.iinfo(np.int32).min)
SENT = "node int, u0 int, u1 int, v0 int, v1 int, data binary, high binary"


def pack(node_images: DataFrame, node_rects: DataFrame, wide: bool = False) -> DataFrame:
    """One message a node that has a rectangle: it and the clipped buffer, ``PIXEL_BYTES`` a pixel, uncovered pixels included. Bounded by the frame.
    Where values need more than four bytes, ``wide`` messages have ``high`` too; others fail rather than send wrong pixels."""

    def dense(table: pa.Table) -> pa.Table:
        box = [table.column(n)[0].as_py() for n in ("node", "u0", "u1", "v0", "v1")]
        table = table.filter(table.column("val").is_valid())
        c = {n: table.column(n).to_numpy() for n in ("u", "v", "val")}
        at, shape = (c["u"] - box[1], c["v"] - box[3]), (box[2] - box[1], box[4] - box[3])
        val = c["val"].astype(np.int64)
        buf, high = np.full(shape, BLANK, "<i4"), None
        if (val <= BLANK).any() or (val > np.iinfo(np.int32).max).any():
            if not wide or (val == (BLANK << 32) + 2**31).any():  # blank in both halves
                raise OverflowError("a pixel's value needs more than four bytes" if not wide else "a pixel has the value that stands for none")
            high = np.full(shape, BLANK, "<i4")
            high[at] = val >> 32
            high = high.tobytes()
        buf[at] = val.astype("<i4")  # the lower half
        return pa.Table.from_arrays([*(pa.array([b], pa.int32()) for b in box), pa.array([buf.tobytes()], pa.binary()), pa.array([high], pa.binary())], names=["node", "u0", "u1", "v0", "v1", "data", "high"])

    joined = node_images.join(F.broadcast(node_rects), "node").select("node", "u0", "u1", "v0", "v1", "u", "v", "val")
    # a row of each rectangle besides: a node without covered pixels sends a message too
    joined = joined.unionByName(node_rects.select("node", "u0", "u1", "v0", "v1", *[F.lit(None).cast(t).alias(c) for c, t in node_images.dtypes if c in ("u", "v", "val")]))
    return joined.groupBy("node").applyInArrow(dense, SENT)


def unpack(messages: DataFrame) -> DataFrame:
    """node, u, v, val of the covered pixels in each message."""

    def rows(batches):
        for batch in batches:
            for m in batch.to_pylist():
                shape = m["u1"] - m["u0"], m["v1"] - m["v0"]
                val = np.frombuffer(m["data"], "<i4").reshape(shape).astype(np.int64)
                gone = val == BLANK
                if m["high"] is not None:
                    high = np.frombuffer(m["high"], "<i4").reshape(shape).astype(np.int64)
                    gone &= high == BLANK
                    val = (high << 32) | (val & 0xFFFFFFFF)
                u, v = np.nonzero(~gone)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.full(len(u), m["node"], np.int32)), pa.array((u + m["u0"]).astype(np.int32)), pa.array((v + m["v0"]).astype(np.int32)), pa.array(val[u, v])], ["node", "u", "v", "val"]
                )

    return messages.mapInArrow(rows, "node int, u int, v int, val long")


def encode_buffer(data: bytes, kind: str, high: bytes | None = None) -> tuple[bytes, bytes | None]:
    """Code of a buffer, and of its upper halves: these at the places of the lower ones."""
    a = np.frombuffer(data, "<i4")
    h = None if high is None else np.frombuffer(high, "<i4")
    if kind == "zlib":
        return zlib.compress(data, 1), None if high is None else zlib.compress(high, 1)
    if kind == "sparse":
        at = np.flatnonzero(a != BLANK if h is None else (a != BLANK) | (h != BLANK)).astype("<i4")
        return np.int32(len(at)).tobytes() + at.tobytes() + a[at].tobytes(), None if h is None else h[at].tobytes()
    new = a[1:] != a[:-1] if h is None else (a[1:] != a[:-1]) | (h[1:] != h[:-1])
    first = np.concatenate([[0], np.flatnonzero(new) + 1])
    return np.int32(len(first)).tobytes() + np.diff(np.append(first, len(a))).astype("<i4").tobytes() + a[first].tobytes(), None if h is None else h[first].tobytes()


def decode_buffer(data: bytes, size: int, kind: str, high: bytes | None = None) -> tuple[bytes, bytes | None]:
    if kind == "zlib":
        return zlib.decompress(data), None if high is None else zlib.decompress(high)
    n = int(np.frombuffer(data[:4], "<i4")[0])
    places, halves = np.frombuffer(data[4 : 4 + 4 * n], "<i4"), (data[4 + 4 * n :], high)
    out = []
    for half in halves:
        if half is None:
            out.append(None)
        elif kind == "rle":
            out.append(np.repeat(np.frombuffer(half, "<i4"), places).tobytes())
        else:
            buf = np.full(size, BLANK, "<i4")
            buf[places] = np.frombuffer(half, "<i4")
            out.append(buf.tobytes())
    return tuple(out)


def recoded(messages: DataFrame, code) -> DataFrame:
    def run(batches):
        for batch in batches:
            both = [code(r) for r in batch.to_pylist()]
            for i, name in enumerate(("data", "high")):
                batch = batch.set_column(batch.schema.get_field_index(name), name, pa.array([x[i] for x in both], pa.binary()))
            yield batch

    return messages.mapInArrow(run, messages.schema)


def encoded(messages: DataFrame, kind: str = "zlib") -> DataFrame:
    """Messages with their buffer encoded: zlib, sparse (places and values of covered pixels) or rle (runs along the buffer)."""
    return recoded(messages, lambda r: encode_buffer(r["data"], kind, r["high"]))


def decoded(messages: DataFrame, kind: str = "zlib") -> DataFrame:
    return recoded(messages, lambda r: decode_buffer(r["data"], (r["u1"] - r["u0"]) * (r["v1"] - r["v0"]), kind, r["high"]))


def encoding_cost(messages: DataFrame, kinds: tuple[str, ...] = ("rle", "sparse", "zlib"), repeat: int = 20) -> DataFrame:
    """node, kind, raw, bytes, encode_ms, decode_ms, raw_high, bytes_high: what an encoding saves of a message and what it costs in CPU time, as the
    median of some runs. The last two are of the upper halves of wide values, which come on top."""

    def run(batches):
        def ms(f):
            times = []
            for _ in range(repeat):
                t = time.process_time_ns()
                out = f()
                times.append(time.process_time_ns() - t)
            return out, sorted(times)[repeat // 2] / 1e6

        for batch in batches:
            rows = []
            for m in batch.to_pylist():
                size = (m["u1"] - m["u0"]) * (m["v1"] - m["v0"])
                for kind in kinds:
                    (code, high), there = ms(lambda m=m, kind=kind: encode_buffer(m["data"], kind, m["high"]))
                    _, back = ms(lambda code=code, high=high, size=size, kind=kind: decode_buffer(code, size, kind, high))
                    rows.append((m["node"], kind, len(m["data"]), len(code), there, back, len(m["high"] or b""), len(high or b"")))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in zip(*rows, strict=True)], ["node", "kind", "raw", "bytes", "encode_ms", "decode_ms", "raw_high", "bytes_high"])

    return messages.mapInArrow(run, "node long, kind string, raw long, bytes long, encode_ms double, decode_ms double, raw_high long, bytes_high long")


def runs(filled: DataFrame) -> DataFrame:
    """Run lengths along scan lines of a filled frame: v, start, length, val (gaps and islands)."""
    g = filled.withColumn("island", F.col("u") - F.row_number().over(Window.partitionBy("v", "val").orderBy("u")))
    return g.groupBy("v", "val", "island").agg(F.min("u").alias("start"), F.count("*").alias("length")).select("v", "start", "length", "val")


def message_bytes(rects: DataFrame, view: ViewSpec, mode: str = "rect") -> DataFrame:
    """nodes, bytes of a frame's messages. full: every node sends the whole frame; rect: its rectangle."""
    area = F.lit(view.width * view.height) if mode == "full" else (F.col("u1") - F.col("u0")) * (F.col("v1") - F.col("v0"))
    return rects.agg(F.count("*").alias("nodes"), F.coalesce(F.sum((area * PIXEL_BYTES).cast("long")), F.lit(0)).alias("bytes"))


def depth(rects: DataFrame) -> DataFrame:
    """layers, pixels: how many rectangles cover a pixel."""
    from .view import pixels

    p = pixels(rects.select("u0", "u1", "v0", "v1"))
    return p.groupBy("u", "v").agg(F.count("*").alias("layers")).groupBy("layers").agg(F.count("*").alias("pixels"))


def overlap(rects: DataFrame) -> DataFrame:
    """total, covered, extra pixels of a set of rectangles: extra is what overlaps add to one frame."""
    d = depth(rects)
    return d.agg(F.sum(F.col("layers") * F.col("pixels")).alias("total"), F.sum("pixels").alias("covered"), F.sum((F.col("layers") - 1) * F.col("pixels")).alias("extra"))
