"""Repeated 50-byte strings by sorting suffixes.

Of all suffixes, those that start at a place picked by content (the smallest of 31 consecutive 20-byte grams) are
sorted; every 50-byte string holds such a place, so about one suffix in 16 stands for all strings around it. Suffixes are
ordered by their first eight bytes as they are, then by the rest of the gram and the content around (as digests), then by
document. Sampled splitters over that order range-partition them; each bucket sorts by multikey quicksort, spilling by
range, and buckets are compared across their bounds, so a passage that a third of all documents repeat may fill several
buckets (see ``buckets``). Neighbours of one content form a class, and where contents branch the strings are compared
one by one (see ``repeats``).

Null text: no bytes. Texts under 50 bytes: nothing is removed. Null identifier: larger than all others. Rows repeating
an identifier do not make each other repeated. One output row for each input row; empty table: empty result.
Long texts are read in parts; only the flags of what is removed are held for a whole text. Other columns are ignored.
"""

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .arrays import U64, eights, mix, odd
from .repeats import Texts, by_document, cover, levels, named_out, texts_of, unpacked
from .tables import unident

SIZES = GRAM, LONGER, WINDOW = 20, 36, 50


class Suffixes:
    """Bytes as tokens; keys are leading bytes."""

    sizes, by_bytes, has_nodes = SIZES, True, False

    @staticmethod
    def tokens(buf, offsets):
        return None, offsets

    @staticmethod
    def grams(buf, starts, seed, gram):
        """Digests of grams at every byte."""
        n = len(buf) - 8 - gram + 1
        if n <= 0:
            return np.zeros(0, U64)
        at = eights(buf)
        total = np.zeros(n, U64)
        for o, m in zip([*range(0, gram - 8, 8), gram - 8], odd(gram // 8 + 1, 51 + seed), strict=False):
            total += at[o : o + n] * m
            total ^= total >> U64(29)
        return mix(total)

    @staticmethod
    def order(buf, starts, value, at):
        """Eight leading bytes in byte order, and 32 bits for the rest of the gram."""
        lead = eights(buf)[at].astype("<u8").byteswap() ^ U64(1 << 63)
        return lead.view(np.int64), (value >> U64(32)).view(np.int64)

    @staticmethod
    def nodes(grams, at, n, gram, length):
        return ()


def running(flags: np.ndarray) -> np.ndarray:
    """Number of flags before each place, and in all."""
    out = np.zeros(len(flags) + 1, np.int32 if len(flags) < 2**31 else np.int64)
    np.cumsum(flags, out=out[1:])
    return out


def digests(buf, offsets, starts, bounds, gone):
    """n_bytes, n_removed, n_spans, kept_sha256."""
    lost = running(gone)
    rise = gone.copy()
    rise[1:] &= ~gone[:-1]
    rise[bounds[:-1][np.diff(bounds) > 0]] |= gone[bounds[:-1][np.diff(bounds) > 0]]
    runs = running(rise)
    kept = memoryview(buf[: len(gone)][~gone])
    cut = bounds - lost[bounds]
    sha = [hashlib.sha256(kept[a:b]).hexdigest() for a, b in zip(cut[:-1], cut[1:], strict=True)]
    return [pa.array(np.diff(bounds)), pa.array(np.diff(lost[bounds]).astype(np.int64)), pa.array(np.diff(runs[bounds]).astype(np.int64)), pa.array(sha, pa.string())]


def kept_bytes(buf, offsets, starts, bounds, gone):
    """Kept bytes and the removed spans as [first byte, bytes]."""
    texts, spans = [], []
    for a, b in zip(bounds[:-1], bounds[1:], strict=True):
        texts.append(buf[a:b][~gone[a:b]].tobytes())
        edge = np.flatnonzero(np.diff(np.concatenate([[False], gone[a:b], [False]]).astype(np.int8)))
        spans.append([[int(x), int(y - x)] for x, y in zip(edge[::2], edge[1::2], strict=True)])
    return [pa.array(texts, pa.binary()), pa.array(spans, pa.list_(pa.list_(pa.int64())))]


def removal(docs: DataFrame, id_col: str, text_col: str, finish, schema: str) -> DataFrame:
    d = texts_of(docs, id_col, text_col)
    texts = Texts(d)
    found = levels(d, texts, Suffixes)
    names = ["first", "second", "third"]

    def apply(batches):
        for part, buf, offsets in unpacked(batches):
            gone = cover(part, names, offsets, WINDOW)
            yield pa.RecordBatch.from_arrays([part.column("doc"), *finish(buf, offsets, None, offsets, gone)], names=named_out(schema))

    parts = [by_document(t.where("kind = 0")).select("doc", "tag", F.col("whole").alias(name)) for t, name in zip(found, names, strict=True)]
    rows = texts.joined(*parts).select("doc", "tag", "size", "packed", *names)
    return rows.mapInArrow(apply, f"doc long, {schema}").select(unident("doc").alias("doc_id"), *named_out(schema)[1:])


def repeated_bytes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of every row."""
    return removal(docs, id_col, text_col, digests, "n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def without_repeated_bytes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, kept bytes, spans removed."""
    return removal(docs, id_col, text_col, kept_bytes, "kept binary, spans array<array<long>>")
