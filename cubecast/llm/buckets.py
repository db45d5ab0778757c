"""Sorting paths in buckets: multikey quicksort with a spill, classes of equal paths, and comparison across the bounds of buckets.

A path row is (lead, gram, digest, doc, place, src, dst): lead and gram make its key, digest its content, and place holds its
first window and its number of windows (see ``repeats``). Rows are ordered by key, content and document. Buckets
are ranges of that order between sampled splitters, which are whole tuples: a key or a content that fills many
buckets is cut by document. A task sorts its bucket by multikey quicksort in memory of about ``ROWS`` rows; a larger bucket is first
dealt to scratch files by splitters of its own, again by whole tuples, as the same quicksort would part it.

Neighbours in order make classes (one content) and keys. A class or key may go on in the next bucket: rows whose
judgement depends on that are put out as pending, with one summary a bucket, and settled when the summaries, as many as
there are buckets, have been compared along the order.
"""

import marshal
import struct
import tempfile

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .arrays import U64, mix, odd
from .tables import partitions, shared_table

ROWS = 1_500_000
#: Segments from which a quicksort goes on by a plain sort of the remaining columns.
SEGMENT = 8192
COLUMNS = ("lead", "gram", "digest", "doc", "place", "src", "dst")
ORDER, NODES = COLUMNS[:4], COLUMNS[5:]
#: gram holds 32 bits, and above them the bucket that the row goes to, if it has one.
GRAM_BITS = (1 << 32) - 1
#: Kinds of rows that come out.
WHOLE, CHECK, FIRST, LAST_KEY, SOURCE, SUMMARY = range(6)
FOUND = "kind int, bucket int, id long, doc long, place long, src long, dst long, note binary"
NAMES = [x.split(" ")[0] for x in FOUND.split(", ")]
Rows = dict[str, np.ndarray]


def path_schema(nodes: bool) -> str:
    return ", ".join(f"{c} long" for c in COLUMNS[: 7 if nodes else 5])


def taken(rows: Rows, which) -> Rows:
    return {k: v[which] for k, v in rows.items()}


def joined(parts: list[Rows]) -> Rows:
    return {k: np.concatenate([p[k] for p in parts]) for k in parts[0]}


def size_of(rows: Rows) -> int:
    return len(rows["doc"])


def quicksort(columns: list[np.ndarray]) -> np.ndarray:
    """Order of rows by columns: three-way partitions by one column at a time; rows equal in it go on with the next."""
    out = np.arange(len(columns[0]))
    stack = [(0, len(out), 0)]
    while stack:
        a, b, d = stack.pop()
        if b - a < 2 or d == len(columns):
            continue
        part = out[a:b]
        if b - a <= SEGMENT:
            out[a:b] = part[np.lexsort([c[part] for c in reversed(columns[d:])])]
            continue
        v = columns[d][part]
        pivot = np.partition(v[:: len(v) // 31], 15)[15]
        below, above = v < pivot, v > pivot
        low, same, high = part[below], part[~below & ~above], part[above]
        i, j = a + len(low), b - len(high)
        out[a:i], out[i:j], out[j:b] = low, same, high
        stack += [(a, i, d), (i, j, d + 1), (j, b, d)]
    return out


def ordered(rows: Rows) -> Rows:
    return taken(rows, quicksort([rows[c] for c in ORDER]))


def places(splitters: Rows, rows: Rows) -> np.ndarray:
    """Number of splitters at or before each row, by whole tuples."""
    low, out = (np.searchsorted(splitters["lead"], rows["lead"], side) for side in ("left", "right"))
    unclear = np.flatnonzero(low < out)
    if len(unclear):
        out[unclear] = low[unclear]
        for first in np.unique(low[unclear]):
            mine = unclear[low[unclear] == first]
            r = taken({c: rows[c] for c in ORDER}, mine)
            last = np.searchsorted(splitters["lead"], splitters["lead"][first], "right")
            for s in range(first, last):
                g, d = r["gram"], r["digest"]
                sg, sd, so = (splitters[c][s] for c in ("gram", "digest", "doc"))
                out[mine] += (g > sg) | (g == sg) & ((d > sd) | (d == sd) & (r["doc"] >= so))
    return out


def picked(rows: Rows, n: int) -> Rows:
    """Up to n - 1 different splitters that part sorted rows evenly."""
    at = np.unique(np.arange(1, n) * size_of(rows) // n)
    some = taken({c: rows[c] for c in ORDER}, at[at < size_of(rows)])
    new = np.ones(len(some["doc"]), bool)
    new[1:] = np.any([some[c][1:] != some[c][:-1] for c in ORDER], axis=0)
    return taken(some, new)


def splitters_of(sample: DataFrame, n: int) -> Rows:
    """Splitters of n buckets from path rows of a sample of documents; at most 40 rows a bucket reach the driver. Balance depends on them, results do not."""
    if n < 2:
        return {c: np.zeros(0, np.int64) for c in ORDER}
    table = sample.select(*ORDER).orderBy(F.xxhash64(*ORDER)).limit(40 * n).toArrow()
    rows = {c: table.column(c).to_numpy().astype(np.int64) for c in ORDER}
    return picked(taken(rows, quicksort([rows[c] for c in ORDER])), n) if size_of(rows) else rows


def in_order(parts, rows: int, scratch: str):
    """Sorted blocks, in order, of the rows that come in parts."""
    held, count = [], 0
    parts = iter(parts)
    for part in parts:
        held.append(part)
        count += size_of(part)
        if count > rows:
            break
    else:
        if held:
            yield ordered(joined(held))
        return
    first = ordered(joined(held))
    del held
    cut = picked(first, 16)
    if not size_of(cut):
        cut = taken({c: first[c] for c in ORDER}, np.array([size_of(first) // 2]))
    files = [tempfile.TemporaryFile(dir=scratch) for _ in range(2 * size_of(cut) + 1)]  # noqa: SIM115
    put(files, cut, first)
    del first
    for part in parts:
        put(files, cut, part)
    for i, file in enumerate(files):
        file.seek(0)
        # between two splitters, or equal to one: then all rows are alike
        yield from back(file) if i % 2 else in_order(back(file), rows, scratch)
        file.close()


def put(files, cut: Rows, rows: Rows) -> None:
    at = places(cut, rows)
    equal = (at > 0) & np.all([cut[c][np.maximum(at - 1, 0)] == rows[c] for c in ORDER], axis=0)
    where = 2 * at - equal
    for i in np.unique(where):
        some = taken(rows, where == i)
        data = marshal.dumps({c: x.tobytes() for c, x in some.items()})
        files[i].write(struct.pack("<q", len(data)) + data)


def back(file):
    while head := file.read(8):
        data = marshal.loads(file.read(*struct.unpack("<q", head)))
        yield {c: np.frombuffer(x, np.int64) for c, x in data.items()}


class Judge:
    """Sorted blocks of one bucket in, found rows out. Between blocks it holds the first document's rows of the open key's only class."""

    def __init__(self, bucket: int, checks: bool, sources: bool):
        self.bucket, self.checks, self.sources = bucket, checks, sources
        self.key = self.digest = self.least = self.first = None
        self.keys, self.classes, self.number = 0, 0, 0  # seen: keys, classes of the open key, classes
        self.first_many = False
        self.waiting: list[Rows] = []
        self.head, self.told = None, True  # the open class's first row, and whether it is out

    def __call__(self, rows: Rows):
        n = size_of(rows)
        if not n:
            return
        lead, gram, digest, doc = (rows[c] for c in ORDER)
        new_key, new_class = np.ones(n, bool), np.ones(n, bool)
        new_key[1:] = (lead[1:] != lead[:-1]) | (gram[1:] != gram[:-1])
        new_key[0] = self.key != (lead[0], gram[0])
        new_class[1:] = digest[1:] != digest[:-1]
        new_class[0] = digest[0] != self.digest
        new_class |= new_key
        goes_on = not new_class[0]
        if self.first is None:
            self.first = tuple(int(x[0]) for x in (lead, gram, digest))
        starts = np.flatnonzero(new_class) if not goes_on else np.append(0, np.flatnonzero(new_class))
        run = np.diff(np.append(starts, n))
        leasts = doc[starts].copy()
        if goes_on:
            leasts[0] = self.least
        number = np.repeat(np.arange(len(starts)), run) + self.number + (not goes_on)  # of the class, from 1
        whole = doc > np.repeat(leasts, run)
        kind = np.where(whole, WHOLE, np.where(number == 1, FIRST, -1))
        if self.sources:
            yield from self.source_rows(rows, starts, whole, goes_on)
        if self.checks:
            group = np.cumsum(new_key) - new_key[0]  # group 0 goes on from the last block unless new_key[0]
            classes = np.bincount(group, new_class, group[-1] + 1).astype(np.int64)
            classes[0] += 0 if new_key[0] else self.classes
            many = classes > 1
            if self.keys + new_key[0] == 1:
                self.first_many |= bool(many[0])
            if self.waiting and (new_key[0] or many[0] or len(classes) > 1):
                if not new_key[0] and many[0]:  # they turn out to share their key
                    for held in self.waiting:
                        yield self.out(held, np.full(size_of(held), CHECK))
                self.waiting = []
            rest = kind == -1
            kind[rest & many[group]] = CHECK
            if not many[-1] and (hold := rest & (group == group[-1])).any():
                self.waiting.append(taken(rows, hold))
            self.classes = int(classes[-1])
        self.keys += int(new_key.sum())
        self.number = int(number[-1])
        self.key, self.digest, self.least = (lead[-1], gram[-1]), digest[-1], leasts[-1]
        if (keep := kind >= 0).any():
            yield self.out(taken(rows, keep), kind[keep])

    def source_rows(self, rows: Rows, starts, whole, goes_on: bool):
        """The first row of each class that turns out to have a second document."""
        has = np.add.reduceat(whole.astype(np.int64), starts) > 0
        if goes_on and has[0] and not self.told:
            yield self.out(self.head, np.array([SOURCE]))
        fresh = has.copy()
        fresh[0] &= not goes_on
        if fresh.any():
            yield self.out(taken(rows, starts[fresh]), np.full(int(fresh.sum()), SOURCE))
        if goes_on and len(starts) == 1:
            self.told |= bool(has[0])
        else:
            self.head, self.told = taken(rows, starts[-1:]), bool(has[-1])

    def end(self):
        """What is open, and the bucket's summary."""
        if self.first is None:
            return
        for held in self.waiting:
            yield self.out(held, np.full(size_of(held), LAST_KEY))
        if self.sources and not self.told:
            yield self.out(self.head, np.array([SOURCE]))  # the class may go on in the next bucket
        key = tuple(map(int, self.key))
        facts = (*self.first, self.first_many, *key, int(self.digest), int(self.least), self.classes > 1, self.keys == 1, self.number == 1)
        empty = [pa.array([None], pa.int64())] * 5
        yield pa.RecordBatch.from_arrays([pa.array([SUMMARY], pa.int32()), pa.array([self.bucket], pa.int32()), *empty, pa.array([marshal.dumps(facts)], pa.binary())], NAMES)

    def out(self, rows: Rows, kind: np.ndarray) -> pa.RecordBatch:
        n = size_of(rows)
        about = [pa.nulls(n, pa.int64())] * 3
        if self.sources:
            m = odd(3, 77)
            ident = mix(rows["lead"].view(U64) * m[0] + rows["gram"].view(U64) * m[1] + rows["digest"].view(U64) * m[2])
            about = [pa.array(ident.view(np.int64)), *(pa.array(rows[c], mask=kind != SOURCE) for c in NODES)]
        return pa.RecordBatch.from_arrays(
            [pa.array(kind.astype(np.int32)), pa.array(np.full(n, self.bucket, np.int32)), about[0], pa.array(rows["doc"]), pa.array(rows["place"]), *about[1:], pa.nulls(n, pa.binary())], NAMES
        )


def compared(notes: list[tuple[int, bytes]]) -> list[tuple]:
    """bucket, least document of its first class in earlier buckets, whether its first and its last key have several classes anywhere."""
    many: list[bool] = []  # of each key that opens or closes a bucket, in order
    out, before = [], None
    for bucket, note in sorted(notes):
        a, b, digest, first_many, c, d, last_digest, least, last_many, one_key, one_class = marshal.loads(note)
        carry = None
        if before and before[0] == (a, b):
            many[-1] |= first_many or before[1] != digest
            if before[1] == digest:
                carry = before[2]
        else:
            many.append(first_many)
        first = len(many) - 1
        if one_key:
            many[-1] |= last_many
        else:
            many.append(last_many)
        before = ((c, d), last_digest, carry if one_class and carry is not None else least)
        out.append((bucket, carry, first, len(many) - 1))
    return [(bucket, carry, many[i], many[j]) for bucket, carry, i, j in out]


def judged(rows: DataFrame, checks: bool, sources: bool = False, ranges: bool = False) -> DataFrame:
    """kind (WHOLE, CHECK or SOURCE), id, doc, place, src, dst of what is repeated, to be checked, or the first of its class.

    rows of ``path_schema``: with ranges they go to their bucket, else they are dealt by key. Without sources ids and nodes are null.
    """
    spark = rows.sparkSession
    n = partitions(spark)

    def run(batches):
        def parts():
            for batch in batches:
                if batch.num_rows:
                    part = {c: batch.column(c).to_numpy(zero_copy_only=False) for c in batch.schema.names}
                    yield part | {"gram": part["gram"] & GRAM_BITS}

        judge = Judge(TaskContext.get().partitionId(), checks, sources)
        with tempfile.TemporaryDirectory() as scratch:
            for block in in_order(parts(), ROWS, scratch):
                yield from judge(block)
        yield from judge.end()

    dealt = rows.repartitionById(n, F.shiftright("gram", 32).cast("int")) if ranges else rows.repartition(n, "lead", "gram")
    raw = shared_table(dealt.mapInArrow(run, FOUND))
    notes = raw.where(F.col("kind") == SUMMARY).select("bucket", "note").collect()  # one row a bucket
    facts = spark.createDataFrame(compared([(r["bucket"], bytes(r["note"])) for r in notes]), "bucket int, carry long, first_many boolean, last_many boolean")
    kind = F.col("kind")
    settled = (
        F.when(kind == FIRST, F.when(F.col("doc") > F.col("carry"), WHOLE).when(F.col("first_many"), CHECK))
        .when(kind == LAST_KEY, F.when(F.col("last_many"), CHECK))
        .otherwise(kind)
    )
    if not checks:
        settled = F.when(kind == FIRST, F.when(F.col("doc") > F.col("carry"), WHOLE)).when(kind != LAST_KEY, kind)
    out = raw.where(kind != SUMMARY).join(F.broadcast(facts), "bucket", "left").withColumn("kind", settled)
    return out.where("kind is not null").select("kind", "id", "doc", "place", "src", "dst")
