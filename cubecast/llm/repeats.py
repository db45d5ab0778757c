"""Repeated windows of tokens, found exactly with one row for about every (window - gram) / 2 tokens.

A window is ``length`` consecutive tokens (words or bytes) of one document. Each window is filed under the
smallest of its gram values (a gram is ``gram`` consecutive tokens), so equal windows are filed alike wherever they
stand. Consecutive windows under one gram form a path: it does not branch, and one row carries it, as its gram's
key, a digest of its whole content and its source coordinates. Rows meet in ordered buckets (see ``buckets``):

* paths of one content form a class; every window of a class also starts in the class's first document,
  so members in later documents are repeated whole;
* a key under which there are several classes is a branching place: the windows of each class's first
  document go through the same again with grams nearly as long as a window, which takes chance meetings apart,
  and what still branches goes on window by window, by two independent 64-bit digests.

What comes out are source coordinates (document, first window, number of windows).
"""

import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import buckets
from .arrays import U64, buffer_of, mix, odd, owners, ragged, slices, window_min
from .tables import ident, named, partitions

TAG_BITS = 26
LONG_PART = 4_000_000
#: Documents (in expectation) from which splitters are estimated.
SAMPLED_DOCS = 2000


def tags(buf: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """26 bits of each text: tells rows apart that repeat an identifier with another text."""
    view = memoryview(buf)
    return np.fromiter((zlib.crc32(view[a:b]) & ((1 << TAG_BITS) - 1) for a, b in zip(offsets[:-1], offsets[1:], strict=True)), np.int64, len(offsets) - 1)


def paths(grams: np.ndarray, at: np.ndarray, row: np.ndarray, gram: int, length: int):
    """First window, number of windows, row and value of each path of the windows at some places, in order."""
    w = length - gram + 1
    if not len(at):
        none = np.zeros(0, np.int64)
        return none, none, none, np.zeros(0, U64)
    value = window_min(grams, w)[at]
    new = np.ones(len(at), bool)
    new[1:] = (value[1:] != value[:-1]) | (at[1:] != at[:-1] + 1) | (row[1:] != row[:-1])
    first = np.flatnonzero(new)
    run = np.diff(np.append(first, len(at)))
    parts = -(-run // w)  # long runs, as in periodic text, are cut every w windows
    if (parts > 1).any():
        step = ragged(np.zeros(len(run), np.int64), parts) * w
        first, run = np.repeat(first, parts) + step, np.minimum(np.repeat(run, parts) - step, w)
    return at[first], run, row[first], value[first]


def all_windows(bounds: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """Place and row of every window."""
    sizes = np.maximum(np.diff(bounds) - length + 1, 0)
    return ragged(bounds[:-1], sizes), np.repeat(np.arange(len(sizes)), sizes)


def anchors(grams: np.ndarray, at: np.ndarray, n: np.ndarray, value: np.ndarray) -> np.ndarray:
    """Place of the first gram of the path's value in its last window."""
    out = at + n - 1
    todo = np.arange(len(at))
    while len(todo):
        todo = todo[grams[out[todo]] != value[todo]]
        out[todo] += 1
    return out


def path_batch(kind, buf, starts, grams, at, row, gram: int, length: int, bounds, doc, tag, splitters=None, base: int = 0) -> pa.RecordBatch:
    at, n, row, value = paths(grams, at, row, gram, length)
    m = odd(2, 99)
    digest = mix(window_digest(grams, at, gram, length, 1) * m[0] + window_digest(grams, at + n - 1, gram, length, 2) * m[1] + n.astype(U64))
    lead, rest = kind.order(buf, starts, value, anchors(grams, at, n, value) if kind.by_bytes else None)
    rows = {"lead": lead, "gram": rest, "digest": digest.view(np.int64), "doc": doc[row], "place": (at - bounds[row] + base) << 31 | tag[row] << 5 | n - 1}
    rows |= dict(zip(buckets.NODES, kind.nodes(grams, at, n, gram, length), strict=False))
    if splitters is not None:
        rows["gram"] = rest | buckets.places(splitters, rows) << 32
    return pa.RecordBatch.from_arrays([pa.array(x) for x in rows.values()], list(rows))


def window_digest(grams: np.ndarray, at: np.ndarray, gram: int, length: int, seed: int) -> np.ndarray:
    """Digest of the whole windows at some positions, from grams that cover them."""
    offsets = [*range(0, length - gram, gram), length - gram]
    total = np.zeros(len(at), U64)
    for o, m in zip(offsets, odd(len(offsets), seed), strict=True):
        total += grams[at + o] * m
    return mix(total)


def path_rows(docs: DataFrame, kind, splitters=None) -> DataFrame:
    """The paths of all documents."""
    gram, _, length = kind.sizes

    def run(batches):
        for batch in slices(batches, "text"):
            whole, offsets = buffer_of(batch.column("text"))
            doc, tag = batch.column("doc").to_numpy(zero_copy_only=False), tags(whole, offsets)
            for base, buf, cut in parts_of(kind, whole, offsets):
                starts, bounds = kind.tokens(buf, cut)
                yield path_batch(kind, buf, starts, kind.grams(buf, starts, 0, gram), *all_windows(bounds, length), gram, length, bounds, doc, tag, splitters, base)

    return docs.mapInArrow(run, buckets.path_schema(kind.has_nodes))


def parts_of(kind, buf: np.ndarray, offsets: np.ndarray):
    """(first token, bytes, offsets) of what is handled at once. A long text of bytes goes in parts that overlap by less than a window, so that each
    window lies in one part; paths are cut there, which costs a closer look at them but no window."""
    size = int(offsets[-1])
    if not kind.by_bytes or len(offsets) != 2 or size <= 2 * LONG_PART:
        yield 0, buf, offsets
        return
    for a in range(0, size, LONG_PART):
        b = min(size, a + LONG_PART + kind.sizes[2] - 1)
        if b - a < kind.sizes[2]:
            return
        part = np.zeros(b - a + 8, np.uint8)
        part[:-8] = buf[a:b]
        yield a, part, np.array([0, b - a])


def sampled(docs: DataFrame, kind) -> buckets.Rows:
    """Splitters of the paths, from a sample of about ``SAMPLED_DOCS`` documents."""
    n = partitions(docs.sparkSession)
    total = docs.count()
    part = docs if total <= SAMPLED_DOCS else docs.sample(False, SAMPLED_DOCS / total, 5)
    return buckets.splitters_of(path_rows(part, kind), n)


def packed_docs(docs: DataFrame) -> DataFrame:
    """doc, tag, size, packed: texts as compressed bytes, for shuffles."""

    def run(batches):
        codec = pa.Codec("zstd", 1)
        for batch in slices(batches, "text", 4_000_000):
            buf, offsets = buffer_of(batch.column("text"))
            view = memoryview(buf)
            packed = [codec.compress(view[a:b], asbytes=True) for a, b in zip(offsets[:-1], offsets[1:], strict=True)]
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc"), pa.array(tags(buf, offsets).astype(np.int32)), pa.array(np.diff(offsets)), pa.array(packed, pa.binary())], ["doc", "tag", "size", "packed"]
            )

    return docs.mapInArrow(run, "doc long, tag int, size long, packed binary")


def unpacked(batches, limit: int = 1_000_000):
    """(batch, buf, offsets) of slices whose texts are about ``limit`` bytes."""
    codec = pa.Codec("zstd")
    for batch in batches:
        sizes = batch.column("size").to_numpy()
        total = np.concatenate([[0], np.cumsum(sizes)])
        at = 0
        while at < batch.num_rows:
            end = max(at + 1, int(np.searchsorted(total, total[at] + limit, "right")) - 1)
            part = batch.slice(at, end - at)
            offsets = total[at : end + 1] - total[at]
            buf = np.zeros(offsets[-1] + 8, np.uint8)
            for i, x in enumerate(part.column("packed").to_pylist()):
                if offsets[i + 1] > offsets[i]:
                    buf[offsets[i] : offsets[i + 1]] = np.frombuffer(codec.decompress(x, int(sizes[at + i])), np.uint8)
            yield part, buf, offsets
            at = end


def lists(column) -> tuple[np.ndarray, np.ndarray]:
    """Flat values and n + 1 bounds of a list column; null lists are empty."""
    sizes = pc.list_value_length(column).fill_null(0).to_numpy()
    return column.flatten().to_numpy(zero_copy_only=False), np.concatenate([[0], np.cumsum(sizes)])


def by_document(hits: DataFrame) -> DataFrame:
    """doc, tag, and the spans of hits: whole, and those to be checked further."""
    kind = F.col("kind")
    return hits.groupBy("doc", tag_of("place").alias("tag")).agg(
        F.collect_list(F.when(kind == buckets.WHOLE, span_of("place"))).alias("whole"), F.collect_list(F.when(kind == buckets.CHECK, span_of("place"))).alias("checks")
    )


def tag_of(place: str) -> Column:
    return F.shiftright(place, 5).bitwiseAND((1 << TAG_BITS) - 1).cast("int")


def span_of(place: str) -> Column:
    """First window and number of windows, less one, in one long."""
    return F.shiftright(place, 31) * 32 + F.col(place).bitwiseAND(31)


class Texts:
    """Compressed texts by document; always a left join of the same texts, so that their exchange can be reused in a plan."""

    def __init__(self, docs: DataFrame):
        self.texts = packed_docs(docs)

    def joined(self, *tables: DataFrame) -> DataFrame:
        out = self.texts
        for t in tables:
            out = out.join(t.hint("shuffle_hash"), ["doc", "tag"], "left")
        return out


def levels(docs: DataFrame, texts: Texts, kind) -> list[DataFrame]:
    """Found rows by whole paths, by paths under longer grams where keys branch, and window by window where they still do."""
    gram, longer, length = kind.sizes
    first = buckets.judged(path_rows(docs, kind, sampled(docs, kind)), True, kind.has_nodes, ranges=True)

    def open_windows(batches):
        """(first token, bytes, tokens, bounds, places, rows, doc, tag) of the windows that are to be checked."""
        for part, whole, offsets in unpacked(only(batches, "checks")):
            flat, cut = lists(part.column("checks"))
            order = np.lexsort((flat, owners(cut)))
            row, at, size = owners(cut)[order], flat[order] >> 5, (flat[order] & 31) + 1
            row, at = np.repeat(row, size), ragged(at, size)
            doc, tag = part.column("doc").to_numpy(), part.column("tag").to_numpy().astype(np.int64)
            for base, buf, some in parts_of(kind, whole, offsets):
                starts, bounds = kind.tokens(buf, some)
                mine = (at >= base) & (at < base + LONG_PART) if len(buf) < len(whole) else slice(None)
                r, a = row[mine], at[mine] - base
                if len(a):
                    yield base, buf, starts, bounds, bounds[r] + a, r, doc, tag

    def finer(batches):
        for base, buf, starts, bounds, at, row, doc, tag in open_windows(batches):
            yield path_batch(kind, buf, starts, kind.grams(buf, starts, 0, longer), at, row, longer, length, bounds, doc, tag, None, base)

    def one_by_one(batches):
        for base, buf, starts, bounds, at, row, doc, tag in open_windows(batches):
            grams = kind.grams(buf, starts, 0, gram)
            one, two = (window_digest(g, at, gram, length, 3 + seed).view(np.int64) for seed, g in ((0, grams), (1, kind.grams(buf, starts, 1, gram))))
            columns = (one, np.zeros(len(at), np.int64), two, doc[row], (at - bounds[row] + base) << 31 | tag[row] << 5, *kind.nodes(grams, at, 1, gram, length))
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], list(buckets.COLUMNS[: len(columns)]))

    def to_check(found: DataFrame) -> DataFrame:
        table = by_document(found.where(F.col("kind") == buckets.CHECK)).select("doc", "tag", "checks")
        return texts.joined(table).select("doc", "tag", "size", "packed", "checks")

    schema = buckets.path_schema(kind.has_nodes)
    second = buckets.judged(to_check(first).mapInArrow(finer, schema), True, kind.has_nodes)
    third = buckets.judged(to_check(second).mapInArrow(one_by_one, schema), False, kind.has_nodes)
    return [first, second, third]


def cover(part, names, bounds, length: int) -> np.ndarray:
    """Whether each token lies in a window of the spans in some columns."""
    change = np.zeros(int(bounds[-1]) + 1, np.int32)
    for name in names:
        flat, cut = lists(part.column(name))
        at = bounds[owners(cut)] + (flat >> 5)
        np.add.at(change, at, 1)
        np.add.at(change, at + (flat & 31) + length, -1)
    return np.cumsum(change[:-1], dtype=np.int32) > 0


def named_out(schema: str) -> list[str]:
    return ["doc", *(x.strip().split(" ")[0] for x in schema.split(","))]


def only(batches, column: str):
    """The rows whose list is not empty."""
    for batch in batches:
        some = batch.filter(pc.greater(pc.list_value_length(batch.column(column)).fill_null(0), 0))
        if some.num_rows:
            yield some


def texts_of(docs: DataFrame, id_col: str, text_col: str, key: Column | None = None) -> DataFrame:
    return docs.select(ident(id_col).alias("doc"), named(text_col).alias("text"), *([] if key is None else [key.alias("key")]))
