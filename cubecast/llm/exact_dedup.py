"""Exact duplicates by owners in compressed radix tries.

Texts are equal when they are the same after white space is deleted. Each task first folds the equal texts
of a slice, so that a group holding a third of all rows sends one row a slice. The folded rows meet in
partitions by (length, content hash); there whole byte strings go into a radix trie whose terminal nodes
keep the best owner so far: the most code points in the original text, then the smallest identifier. When a
trie holds more than ``bound`` bytes, nodes included, the heaviest subtree below the prefix that all its strings share is
written to a scratch file of the task and goes through a trie of its own afterwards. The folded rows, still with
their members, then find their class by (length, hash), and members become rows only after that join.

Null text: as empty. Null identifier: larger than all others, returned as null. Repeated rows: each is a
member of its group; kept=true for all rows with the owner's identifier. Empty table: empty result. A very long text is
one trie label; memory follows the longest text. Columns besides identifier and text are ignored by
``duplicate_classes``. ``deduplicate`` keeps all columns, whatever their names, and exactly one row of each class: ties
of length and identifier, as among repeated rows or null identifiers, go to the smallest digest of the whole row.
"""

import hashlib
import marshal
import os
import struct
import tempfile

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .arrays import WHITE, slices
from .tables import ident, named, partitions, row_key, unident, without

TRIE_BYTES = 64_000_000
#: What a node costs besides its label.
NODE_BYTES = 250
SLICE = 8_000_000
PAYLOAD = ("points", "owner", "tie", "n")
TYPES = (pa.int64(), pa.int64(), pa.binary(), pa.int64())


class Trie:
    """A radix trie over byte strings. A node is [label, children by first byte, payload or None]."""

    def __init__(self):
        self.root = [b"", {}, None]
        self.held = 0

    def insert(self, key: bytes, payload, fold) -> None:
        node, at = self.root, 0
        while at < len(key):
            child = node[1].get(key[at])
            if child is None:
                node[1][key[at]] = node = [key[at:], {}, None]
                self.held += len(node[0]) + NODE_BYTES
                break
            label = child[0]
            if key.startswith(label, at):
                node, at = child, at + len(label)
                continue
            same = common(label, key[at : at + len(label)])
            upper = [label[:same], {label[same]: child}, None]
            child[0] = label[same:]
            self.held += NODE_BYTES
            node[1][key[at]] = node = upper
            at += same
        node[2] = payload if node[2] is None else fold(node[2], payload)

    def cut(self):
        """Takes the heaviest subtree below the shared prefix out: its prefix and its (key, payload); None if there is one key."""
        node, above = self.root, b""
        while len(node[1]) == 1 and (node[2] is None or node is self.root):
            (child,) = node[1].values()
            if not child[1]:
                break
            node, above = child, above + child[0]
        if len(node[1]) + (node[2] is not None) < 2:
            return None
        first = max(node[1], key=lambda b: weight(node[1][b]))
        taken = node[1].pop(first)
        self.held -= weight(taken)
        return above + bytes([first]), list(walk(taken, above))

    def items(self):
        return walk(self.root, b"")


def common(a: bytes, b: bytes) -> int:
    """Length of the common prefix."""
    low, high = 0, min(len(a), len(b))
    while low < high:
        mid = (low + high + 1) // 2
        low, high = (mid, high) if a[low:mid] == b[low:mid] else (low, mid - 1)
    return low


def weight(node) -> int:
    total, stack = 0, [node]
    while stack:
        node = stack.pop()
        total += len(node[0]) + NODE_BYTES
        stack += node[1].values()
    return total


def walk(node, above: bytes):
    stack = [(node, above)]
    while stack:
        node, above = stack.pop()
        key = above + node[0]
        if node[2] is not None:
            yield key, node[2]
        stack += [(x, key) for x in node[1].values()]


def better(a: tuple, b: tuple) -> tuple:
    """Folds (code points, owner, count): the owner comes from the one with more code points, then the smaller owner."""
    best = a if (-a[0], a[1]) <= (-b[0], b[1]) else b
    return best[0], best[1], a[2] + b[2]


class Spill:
    """Subtrees of one trie in scratch files, by their prefix. A key always goes to the longest prefix that it has."""

    def __init__(self, folder: str):
        self.folder, self.files, self.sizes = folder, {}, []

    def take(self, prefix: bytes, items) -> None:
        handle, path = tempfile.mkstemp(dir=self.folder)
        self.files[prefix] = (os.fdopen(handle, "wb"), path)
        self.sizes = sorted({*self.sizes, len(prefix)}, reverse=True)
        for key, payload in items:
            self.put(prefix, key, payload)

    def put(self, prefix: bytes, key: bytes, payload) -> None:
        about = marshal.dumps(payload)
        self.files[prefix][0].write(struct.pack(RECORD, len(about), len(key) - len(prefix)) + about + key[len(prefix) :])

    def place(self, key: bytes) -> bytes | None:
        return next((key[:n] for n in self.sizes if key[:n] in self.files), None)


RECORD = "<qq"


def records(path: str):
    with open(path, "rb") as file:
        while head := file.read(struct.calcsize(RECORD)):
            about, size = struct.unpack(RECORD, head)
            payload = marshal.loads(file.read(about))
            yield file.read(size), payload


def owners_of(pairs, bound: int = TRIE_BYTES):
    """(key, payload) of the distinct keys, each with its payloads folded, in memory of about ``bound`` bytes and the longest key."""
    with tempfile.TemporaryDirectory() as scratch:
        waiting = [(b"", None)]
        while waiting:
            head, path = waiting.pop()
            trie, spill = Trie(), Spill(scratch)
            for key, payload in pairs if path is None else records(path):
                if (prefix := spill.place(key)) is not None:
                    spill.put(prefix, key, payload)
                    continue
                trie.insert(key, payload, better)
                while trie.held > bound and (taken := trie.cut()):
                    spill.take(*taken)
            for key, payload in trie.items():
                yield head + key, payload
            del trie
            if path is not None:
                os.unlink(path)
            for prefix, (file, where) in spill.files.items():
                file.close()
                waiting.append((head + prefix, where))


def flat(payload: tuple) -> tuple:
    """points, identifier, row digest, count."""
    points, (owner, tie), n = payload
    return points, owner, tie, n


def folded(docs: DataFrame, id_col: str, text_col: str, tie: Column | None = None) -> DataFrame:
    """Equal texts of a slice in one row: size, sha, packed text, best owner, members (identifier and row digest)."""
    schema = "size long, sha binary, packed binary, points long, owner long, tie binary, n long, members array<long>, ties array<binary>"

    tied = tie is not None

    def run(batches):
        delete = bytes(WHITE)
        for batch in slices(batches, "text", SLICE):
            groups: dict = {}
            points = pc.utf8_length(batch.column("text")).fill_null(0).to_pylist()
            columns = (batch.column("doc").to_pylist(), batch.column("tie").to_pylist(), batch.column("text").cast(pa.binary()).to_pylist(), points)
            for key, own, text, n in zip(*columns, strict=True):
                plain = (text or b"").translate(None, delete)
                sha = hashlib.sha256(plain).digest()
                got = groups.get(sha)
                if got is None:
                    groups[sha] = [plain, (n, (key, own), 1), [key], [own]]
                else:
                    got[1] = better(got[1], (n, (key, own), 1))
                    got[2].append(key)
                    got[3].append(own)
            rows = list(groups.items())
            codec = pa.Codec("zstd", 1)
            if not rows:
                continue
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array([len(x[0]) for _, x in rows], pa.int64()),
                    pa.array([k for k, _ in rows], pa.binary()),
                    pa.array([codec.compress(x[0], asbytes=True) for _, x in rows], pa.binary()),
                    *(pa.array(x, t) for x, t in zip(zip(*(flat(x[1]) for _, x in rows)), TYPES, strict=True)),
                    pa.array([x[2] for _, x in rows], pa.list_(pa.int64())),
                    pa.array([x[3] if tied else [] for _, x in rows], pa.list_(pa.binary())),
                ],
                ["size", "sha", "packed", *PAYLOAD, "members", "ties"],
            )

    own = F.lit(b"") if tie is None else tie
    return docs.select(ident(id_col).alias("doc"), own.alias("tie"), named(text_col).alias("text")).mapInArrow(run, schema)


def owner_table(fold: DataFrame, bound: int = TRIE_BYTES) -> DataFrame:
    """size, sha and payload of each class, from the tries of the partitions by (size, sha)."""

    def run(batches):
        codec = pa.Codec("zstd")

        def pairs():
            for batch in batches:
                for size, packed, points, owner, tie, n in zip(*(batch.column(x).to_pylist() for x in ("size", "packed", *PAYLOAD)), strict=True):
                    yield codec.decompress(packed, size, asbytes=True) if size else b"", (points, (owner, tie), n)

        out: list = []
        for key, payload in owners_of(pairs(), bound):
            out.append((len(key), hashlib.sha256(key).digest(), *flat(payload)))
            if len(out) >= 5000:
                yield as_batch(out)
                out = []
        if out:
            yield as_batch(out)

    def as_batch(rows):
        return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows), (pa.int64(), pa.binary(), *TYPES), strict=True)], ["size", "sha", *PAYLOAD])

    n = partitions(fold.sparkSession)
    dealt = fold.select("size", "packed", *PAYLOAD, "sha").repartition(n, "size", "sha").select("size", "packed", *PAYLOAD)
    return dealt.mapInArrow(run, "size long, sha binary, points long, owner long, tie binary, n long")


def duplicate_classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", bound: int = TRIE_BYTES) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 of every row."""
    fold = folded(docs, id_col, text_col)
    groups = fold.select("size", "sha", "members").join(owner_table(fold, bound).select("size", "sha", "owner", "n"), ["size", "sha"])
    return groups.select("sha", "owner", "n", F.explode("members").alias("doc")).select(
        unident("doc").alias("doc_id"),
        unident("owner").alias("keep_id"),
        F.col("n").alias("group_size"),
        (F.col("doc") == F.col("owner")).alias("kept"),
        F.lower(F.hex("sha")).alias("text_sha256"),
    )


def deduplicate(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", bound: int = TRIE_BYTES) -> DataFrame:
    """One row of each class, with all its columns."""
    fold = folded(docs, id_col, text_col, row_key(docs))
    groups = fold.select("size", "sha", "ties").join(owner_table(fold, bound).select("size", "sha", "tie", "n"), ["size", "sha"]).where("n > 1")
    keys = groups.select("tie", F.explode("ties").alias("key")).groupBy("key", "tie").agg(F.count("*").alias("same"))
    keys = keys.select("key", (F.col("key") != F.col("tie")).alias("gone"), "same")
    return without(docs, keys.where("gone or same > 1").select("key", "gone"))
