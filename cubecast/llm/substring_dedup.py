"""Repeated word spans by compaction of a De Bruijn graph.

Edges of the graph are windows of 13 words, nodes the 12 words that two edges share. Only repeated edges are of use, and
runs of edges under one smallest gram can't branch within the run: they travel as one row each, which finds the rows
of equal content, its class (see ``repeats`` and ``buckets``); where classes share a gram, their edges are taken apart. So a class is
a short path of repeated edges, with its two end nodes, its first document and the place there. Then, in DataFrames:

1. Nodes at which one path ends and one begins don't branch. Paths that follow each other over such a node, in the text
   of one first document, are joined into one long path with one source coordinate.
2. The members of classes in other documents take their long path's coordinate, and members that follow each other become one
   long span of their document.
3. Each long span is verified: its words and those at its source coordinates must have equal 128-bit digests.

The words of verified spans are removed.

Null text: no words. Fewer than 13 words: nothing is removed. Null identifier: larger than all others. Rows repeating an
identifier do not make each other repeated. One output row for each input row; empty table: empty result.
Memory in a worker follows the longest text. Other columns are ignored.
"""

import hashlib
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import buckets
from .arrays import U64, hash_ranges, mix, odd, owners, ragged, rolled, word_bounds
from .repeats import Texts, levels, lists, named_out, only, tag_of, texts_of, unpacked, window_digest
from .tables import shared_table, unident

SIZES = GRAM, LONGER, WINDOW = 6, 10, 13
ROW = ("doc", "tag")


class Edges:
    """Words as tokens; keys are gram values."""

    sizes, by_bytes, has_nodes = SIZES, False, True

    @staticmethod
    def tokens(buf, offsets):
        starts, ends, bounds = word_bounds(buf, offsets)
        return (starts, ends), bounds

    @staticmethod
    def grams(buf, starts, seed, gram):
        return rolled(hash_ranges(buf, *starts, seed=seed), gram, 11 + seed)

    @staticmethod
    def order(buf, starts, value, at):
        return value.view(np.int64), np.zeros(len(value), np.int64)

    @staticmethod
    def nodes(grams, at, n, gram, length):
        """The first and the last node of paths of n edges."""
        return tuple(window_digest(grams, x, gram, length - 1, 5).view(np.int64) for x in (at, at + n))


def rows_of(found: list[DataFrame], kind: int, *columns: str) -> DataFrame:
    """Rows of one kind from all levels: level, id, doc, tag, start, n and columns. Places of different levels may overlap, those of one don't."""
    parts = [t.where(F.col("kind") == kind).select(F.lit(i).alias("level"), "id", "doc", tag_of("place").alias("tag"), F.shiftright("place", 31).alias("start"), (F.col("place").bitwiseAND(31) + 1).alias("n"), *columns) for i, t in enumerate(found)]
    return reduce(DataFrame.unionByName, parts)


def long_paths(sources: DataFrame) -> DataFrame:
    """level, id, s_doc, s_tag, s_start of each class, and head: where its long path begins in the first document."""
    edges = sources.groupBy("level", "id").agg(F.min(F.struct("doc", "tag", "start", "n", "src", "dst")).alias("e")).select("level", "id", "e.*")
    edges = shared_table(edges)
    ends = edges.groupBy("level", F.col("dst").alias("node")).agg(F.count("*").alias("ins"), F.first(F.struct("doc", "tag", (F.col("start") + F.col("n")).alias("start"))).alias("a"))
    begins = edges.groupBy("level", F.col("src").alias("node")).agg(F.count("*").alias("outs"), F.first(F.struct("doc", "tag", "start")).alias("b"), F.first("id").alias("id"))
    follows = ends.where("ins = 1").join(begins.where("outs = 1"), ["level", "node"]).where("a = b").select("level", "id", F.lit(True).alias("follows"))
    along = Window.partitionBy("level", *ROW).orderBy("start").rowsBetween(Window.unboundedPreceding, 0)
    out = edges.join(follows, ["level", "id"], "left").withColumn("head", F.last(F.when(F.col("follows").isNull(), F.col("start")), ignorenulls=True).over(along))
    return out.select("level", "id", F.col("doc").alias("s_doc"), F.col("tag").alias("s_tag"), F.col("start").alias("s_start"), "head")


def long_spans(members: DataFrame, paths: DataFrame) -> DataFrame:
    """doc, tag, start, n, s_doc, s_tag, s_start of the longest spans of members that follow each other along one long path."""
    m = members.join(paths, ["level", "id"])
    order = Window.partitionBy(*ROW).orderBy("level", "start")
    now = F.struct("level", "s_doc", "s_tag", "head", F.col("start"), F.col("s_start"))
    then = F.lag(F.struct("level", "s_doc", "s_tag", "head", (F.col("start") + F.col("n")).alias("start"), (F.col("s_start") + F.col("n")).alias("s_start"))).over(order)
    m = m.withColumn("new", F.when(now.eqNullSafe(then), 0).otherwise(1))
    m = m.withColumn("span", F.sum("new").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    first = F.min(F.struct("start", "s_doc", "s_tag", "s_start"))
    return m.groupBy(*ROW, "span").agg(first.alias("f"), F.sum("n").alias("n")).select(*ROW, "f.start", "n", "f.s_doc", "f.s_tag", "f.s_start")


def span_digests(texts: Texts, spans: DataFrame) -> DataFrame:
    """doc, tag, start, n, digest (128 bits) of spans of windows."""

    def run(batches):
        for part, buf, offsets in unpacked(only(batches, "spans")):
            starts, bounds = Edges.tokens(buf, offsets)
            flat, cut = lists(part.column("spans"))
            row, at, n = owners(cut), flat >> 31, flat & ((1 << 31) - 1)
            a, b = bounds[row] + at, bounds[row] + at + n + WINDOW - 1
            halves = []
            for seed, base in enumerate(odd(2, 61)):
                words = mix(hash_ranges(buf, *starts, seed=5 + seed))
                back = U64(pow(int(base), -1, 1 << 64))
                power = np.cumprod(np.concatenate([[U64(1)], np.full(len(words), base)]), dtype=U64)
                fall = np.cumprod(np.concatenate([[U64(1)], np.full(len(words), back)]), dtype=U64)
                total = np.concatenate([[U64(0)], np.cumsum(words * fall[:-1], dtype=U64)])
                halves.append(mix((total[b] - total[a]) * power[a]))  # the same wherever the words stand
            digest = np.ascontiguousarray(np.stack(halves, axis=1)).tobytes()
            columns = [part.column(x).take(pa.array(row)) for x in ROW]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(at), pa.array(n), pa.array([digest[i : i + 16] for i in range(0, len(digest), 16)], pa.binary())], [*ROW, "start", "n", "digest"])

    by_row = spans.distinct().groupBy(*ROW).agg(F.collect_list(F.shiftleft("start", 31) + F.col("n")).alias("spans"))
    return texts.joined(by_row).select(*ROW, "size", "packed", "spans").mapInArrow(run, "doc long, tag int, start long, n long, digest binary").distinct()


def verified(spans: DataFrame, texts: Texts) -> DataFrame:
    """The spans whose words are those at their source coordinates."""
    own = spans.select(*ROW, "start", "n")
    source = spans.select(F.col("s_doc").alias("doc"), F.col("s_tag").alias("tag"), F.col("s_start").alias("start"), "n")
    digests = shared_table(span_digests(texts, own.unionByName(source)))
    there = digests.select(F.col("doc").alias("s_doc"), F.col("tag").alias("s_tag"), F.col("start").alias("s_start"), "n", F.col("digest").alias("s_digest"))
    return spans.join(digests, [*ROW, "start", "n"]).join(there, ["s_doc", "s_tag", "s_start", "n"]).where("digest = s_digest").select(*ROW, "start", "n")


def digests(buf, offsets, starts, bounds, gone):
    """n_words, n_removed, kept_sha256."""
    starts, ends = starts
    keep = ~gone
    sizes = np.where(keep, ends - starts + 1, 0)
    out = buf[ragged(starts[keep], sizes[keep])]
    total = np.concatenate([[0], np.cumsum(sizes)])
    out[total[1:][keep] - 1] = 32
    view, cut = memoryview(out), total[bounds]
    sha = [hashlib.sha256(view[a : max(a, b - 1)]).hexdigest() for a, b in zip(cut[:-1], cut[1:], strict=True)]
    lost = np.concatenate([[0], np.cumsum(gone)])
    return [pa.array(np.diff(bounds)), pa.array(np.diff(lost[bounds])), pa.array(sha, pa.string())]


def kept_words(buf, offsets, starts, bounds, gone):
    """Kept text and the removed spans as [first word, words]."""
    starts, ends = starts
    texts, spans = [], []
    for a, b in zip(bounds[:-1], bounds[1:], strict=True):
        texts.append(b" ".join(buf[starts[i] : ends[i]].tobytes() for i in range(a, b) if not gone[i]).decode("utf-8", "replace"))
        edge = np.flatnonzero(np.diff(np.concatenate([[False], gone[a:b], [False]]).astype(np.int8)))
        spans.append([[int(x), int(y - x)] for x, y in zip(edge[::2], edge[1::2], strict=True)])
    return [pa.array(texts, pa.string()), pa.array(spans, pa.list_(pa.list_(pa.int64())))]


def removal(docs: DataFrame, id_col: str, text_col: str, finish, schema: str) -> DataFrame:
    d = texts_of(docs, id_col, text_col)
    texts = Texts(d)
    found = levels(d, texts, Edges)
    paths = long_paths(rows_of(found, buckets.SOURCE, "src", "dst"))
    spans = shared_table(long_spans(rows_of(found, buckets.WHOLE), paths))
    gone_spans = verified(spans, texts).groupBy(*ROW).agg(F.collect_list(F.shiftleft("start", 31) + F.col("n")).alias("spans"))

    def apply(batches):
        for part, buf, offsets in unpacked(batches):
            starts, bounds = Edges.tokens(buf, offsets)
            flat, cut = lists(part.column("spans"))
            change = np.zeros(int(bounds[-1]) + 1, np.int32)
            at = bounds[owners(cut)] + (flat >> 31)
            np.add.at(change, at, 1)
            np.add.at(change, at + (flat & ((1 << 31) - 1)) + WINDOW - 1, -1)
            gone = np.cumsum(change[:-1]) > 0
            yield pa.RecordBatch.from_arrays([part.column("doc"), *finish(buf, offsets, starts, bounds, gone)], names=named_out(schema))

    rows = texts.joined(gone_spans).select(*ROW, "size", "packed", "spans")
    return rows.mapInArrow(apply, f"doc long, {schema}").select(unident("doc").alias("doc_id"), *named_out(schema)[1:])


def repeated_words(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 of every row."""
    return removal(docs, id_col, text_col, digests, "n_words long, n_removed long, kept_sha256 string")


def without_repeated_words(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, text with the repeated words taken out, spans removed."""
    return removal(docs, id_col, text_col, kept_words, "text string, spans array<array<long>>")
