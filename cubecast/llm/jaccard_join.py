"""Exact Jaccard join of documents by their distinct 4-word shingles, as a join in a metric space.

The distance is 1 - intersection / union; documents link within a radius. Almost all pairs of a corpus lie at distance 1,
where document pivots tell nothing, so the space is divided twice:

1. The first pivot is the empty set under the symmetric-difference metric: rings by set size. By the triangle inequality a
   document can link only within its ring and the next, so each is replicated to the ring below as well. Inside a ring the
   hash range is cut into more blocks than the largest symmetric difference of a linked pair, with some to spare;
   linked sets agree on a whole block of two shingles or more, and meet there. A set with too few such blocks also uses
   those of one shingle, and where these are too few meets others of its kind at each shingle of its prefix.
2. Sets that meet, directly or through others, form a region; only regions read whole sets again. In a region of more than
   ``TILE`` sets, dealt to as many parts, every set measures its distance to a few pivots, sets of the region picked by hash.
   Links with pivots join sets at once; far pivots make Voronoi cells: a set goes to its nearest pivot's cell, and to any
   other whose pivot is at most two radii farther, so that linked sets share the cell of either one's pivot. Within a cell only
   pairs with a set outside the region's largest component so far can still tell anything: those sets, in parts, meet all
   parts of the cell. Within a tile of parts, cells divide further in the same way, until small ones go by distance, where
   only sets of different components within the triangle windows of all pivots are compared.

Equal sets are one point. Components of links are exact; links inside a component that are not needed to connect it need not
be computed. Digests: 128 bits for sets, 64 for shingles within a region.

Fewer than four words: the whole sequence is the one shingle. No words, or null text: the empty set, linked with
nothing. Null identifier: larger than all others. Repeated rows and identifiers: one output row each. Empty table: empty result.
Memory in a worker follows the longest text. Other columns are ignored by ``linked_documents``. ``distinct_documents`` keeps
them, whatever their names, and one row of each component, and all rows without words; ties of the smallest identifier, as among
repeated rows or null identifiers, go to the smallest digest of the whole row.
"""

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .arrays import U64, buffer_of, hash_ranges, lower_table, mix, odd, owners, ragged, slices, word_bounds
from .components import components
from .repeats import packed_docs, texts_of, unpacked
from .tables import forget, partitions, row_key, shared_table, unident, without

WORDS = 4
PERCENT = 85
TILE = 256
LEAF = 24
PIVOTS = 6
#: Pivots of a large region, on average.
STARS = 12
#: Cells that a set of a region may lie in, on average, for the cells to be used.
SPREAD = 1.5
FAR = -(2**63)
SLACK = 1e-9
SEEN = 500_000
#: A shingle of so many in so many sets is frequent; the longest list, and the most counts that a task holds.
OFTEN, SETS, MOST, HELD = 5, 4000, 200_000, 2_000_000


def shingles(buf: np.ndarray, offsets: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle digests of each row, one row after the other, and n + 1 bounds."""
    buf = lower_table()[buf]
    starts, ends, bounds = word_bounds(buf, offsets)
    words = hash_ranges(buf, starts, ends)
    count = np.diff(bounds)
    full = np.maximum(count - size + 1, 0)
    at = ragged(bounds[:-1], full)
    total = np.zeros(len(at), U64)
    for j, m in enumerate(odd(size, 21)):
        total += words[at + j] * m
    row = np.repeat(np.arange(len(count)), full)
    few = np.flatnonzero((count > 0) & (count < size))
    short = np.zeros(len(few), U64)
    for j, m in enumerate(odd(size - 1, 22)):
        some = count[few] > j
        short[some] += words[bounds[:-1][few[some]] + j] * m
    value = mix(np.concatenate([total, short + count[few].astype(U64)]))
    row = np.concatenate([row, few])
    order = np.lexsort((value, row))
    value, row = value[order], row[order]
    keep = np.ones(len(value), bool)
    keep[1:] = (value[1:] != value[:-1]) | (row[1:] != row[:-1])
    value, row = value[keep], row[keep]
    return value, np.searchsorted(row, np.arange(len(count) + 1))


def set_digests(value: np.ndarray, bounds: np.ndarray) -> list[np.ndarray]:
    """Two 64-bit digests of each set."""
    out = []
    for m in odd(2, 31):
        total = np.concatenate([[U64(0)], np.cumsum(mix(value * m), dtype=U64)])
        out.append(mix(total[bounds[1:]] - total[bounds[:-1]] + np.diff(bounds).astype(U64)).view(np.int64))
    return out


def rings(largest: int, percent: int) -> np.ndarray:
    """First sizes of the rings, up to one that starts above ``largest``."""
    out = [1]
    while out[-1] <= largest:
        out.append(out[-1] * 100 // percent + 1)
    return np.array(out)


def spare(percent: int) -> float:
    """Share of additional blocks with which, on average, enough blocks hold two shingles or more."""
    mean, more = percent / (100 - percent), 0.0
    while True:
        m = mean / (1 + more)
        if (1 - math.exp(-m) * (1 + m)) * (1 + more) >= 1.04 or more >= 1:
            return more
        more += 0.02


def signatures(value: np.ndarray, bounds: np.ndarray, percent: int, frequent: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Row and key of each place where a set meets others.

    Frequent shingles are left out of the blocks: what differs between two sets without them is no more than what differs
    with them, so the count of blocks still holds, whatever the list. Blocks of one shingle are used only by sets with too few larger ones.
    """
    size = np.diff(bounds)
    edge = rings(int(size.max(initial=0)) + 1, percent)
    ring = np.searchsorted(edge, size, "right") - 1
    whose = owners(bounds)
    common = np.zeros(len(value), bool)
    if len(frequent):
        common = frequent[np.minimum(np.searchsorted(frequent, value), len(frequent) - 1)] == value
    rare, rare_row = value[~common], whose[~common]
    rare_bounds = np.searchsorted(rare_row, np.arange(len(size) + 1))
    ordered = np.lexsort((value, common, whose))  # within a set, frequent shingles last
    more_blocks = spare(percent)
    rows, keys = [], []
    for shift in (0, 1):
        group = ring - shift
        use = np.flatnonzero((size > 0) & (group >= 0))
        if not len(use):
            continue
        top = np.append(edge, edge[-1] * 100 // percent + 1)[group[use] + 1] - 1  # the largest size of the group's lower ring
        reach = size[use] <= top * 100 // percent
        use, top = use[reach], top[reach]
        differ = top * (100 - percent) // percent  # the largest symmetric difference of a linked pair whose smaller set has ``top``
        blocks = np.where(differ > 0, np.ceil((differ + 1) * (1 + more_blocks)).astype(np.int64), 1)
        own = np.minimum(differ, size[use] * (100 - percent) // percent)  # and of one that this set can be in
        count = np.diff(rare_bounds)[use]
        at = ragged(rare_bounds[:-1][use], count)
        who = np.repeat(np.arange(len(use)), count)
        v = rare[at]
        block = ((v >> U64(32)) * blocks[who].astype(U64) >> U64(32)).astype(np.int64)
        new = np.ones(len(v), bool)
        new[1:] = (who[1:] != who[:-1]) | (block[1:] != block[:-1])
        head = np.flatnonzero(new)
        full, some = np.zeros(len(use), np.int64), np.zeros(len(use), np.int64)
        if len(head):
            content = np.add.reduceat(mix(v * odd(1, 41)[0]), head)
            large = np.diff(np.append(head, len(v))) > 1
            w = who[head]
            full, some = np.bincount(w[large], minlength=len(use)), np.bincount(w, minlength=len(use))
            key = mix(content + mix((block[head].astype(U64) << U64(24)) + (group[use[w]].astype(U64) << U64(1)) + U64(1)))
            send = large | (full <= own)[w]
            rows.append(use[w[send]])
            keys.append(key[send])
        lacking = np.flatnonzero((full <= own) & (some <= own))
        if len(lacking):
            n = size[use[lacking]]
            prefix = n - -(-n * percent // 100) + 1
            more = value[ordered[ragged(bounds[:-1][use[lacking]], prefix)]]
            rows.append(np.repeat(use[lacking], prefix))
            keys.append(mix(more + mix(np.repeat(group[use[lacking]], prefix).astype(U64) << U64(1))))
    if not rows:
        return np.zeros(0, np.int64), np.zeros(0, U64)
    return np.concatenate(rows), np.concatenate(keys)


class Heavy:
    """Counts of shingles in a task's different sets; when more than ``HELD`` would be held, the rarest go, by rising counts."""

    def __init__(self):
        self.key, self.count, self.waiting, self.size, self.sets, self.seen = np.zeros(0, U64), np.zeros(0, np.int64), [], 0, 0, set()

    def add(self, value: np.ndarray, bounds: np.ndarray, d1: np.ndarray) -> None:
        fresh = np.zeros(len(d1), bool)
        for i, d in enumerate(d1.tolist()):
            if d not in self.seen and bounds[i] < bounds[i + 1]:
                fresh[i] = True
                self.seen.add(d)
        if len(self.seen) > SEEN:
            self.seen = set()
        self.sets += int(fresh.sum())
        self.waiting.append(value[np.repeat(fresh, np.diff(bounds))])
        self.size += len(self.waiting[-1])
        if self.size > HELD:
            self.fold()

    def fold(self) -> None:
        fresh, n = np.unique(np.concatenate([*self.waiting, np.zeros(0, U64)]), return_counts=True)
        self.waiting, self.size = [], 0
        both = np.concatenate([self.key, fresh])
        order = np.argsort(both, kind="stable")
        both, n = both[order], np.concatenate([self.count, n])[order]
        head = np.flatnonzero(np.concatenate([[True], both[1:] != both[:-1]])) if len(both) else np.zeros(0, np.int64)
        self.key, self.count = both[head], np.add.reduceat(n, head) if len(head) else np.zeros(0, np.int64)
        least = 1
        while len(self.key) > HELD:
            keep = self.count > least
            self.key, self.count, least = self.key[keep], self.count[keep], 2 * least

    def found(self) -> tuple[np.ndarray, np.ndarray]:
        """Those of at least two sets and half the share that makes a shingle frequent."""
        self.fold()
        keep = self.count >= max(2, OFTEN * self.sets / SETS / 2)
        return self.key[keep], self.count[keep]


def frequent_shingles(texts: DataFrame, size: int) -> np.ndarray:
    """Shingles that at least ``OFTEN`` in ``SETS`` of all documents' sets have, counted over every document; equal sets of a task
    count once. A hint for cost that no result depends on: where a task has few sets with a shingle, they may go uncounted."""

    def run(batches):
        heavy = Heavy()
        for batch in slices(batches, "text"):
            value, bounds = shingles(*buffer_of(batch.column("text")), size)
            heavy.add(value, bounds, set_digests(value, bounds)[0])
        key, count = heavy.found()
        yield pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(count)], ["shingle", "count"])
        yield pa.RecordBatch.from_arrays([pa.array([None], pa.int64()), pa.array([heavy.sets])], ["shingle", "count"])  # all sets

    found = shared_table(texts.mapInArrow(run, "shingle long, count long").groupBy("shingle").agg(F.sum("count").alias("count")))
    sets = found.where("shingle is null").first()
    least = max(OFTEN, OFTEN * (sets["count"] if sets else 0) / SETS)
    rows = found.where(F.col("shingle").isNotNull() & (F.col("count") >= least)).orderBy(F.desc("count"), "shingle").limit(MOST).select("shingle").toArrow()
    forget(found)
    return np.sort(rows.column(0).to_numpy().view(U64))


def set_rows(texts: DataFrame, size: int) -> DataFrame:
    """doc, key, n, d1, d2 of every row of doc, text, key."""

    def run(batches):
        for batch in slices(batches, "text"):
            value, bounds = shingles(*buffer_of(batch.column("text")), size)
            d1, d2 = set_digests(value, bounds)
            yield pa.RecordBatch.from_arrays([batch.column("doc"), batch.column("key"), pa.array(np.diff(bounds)), pa.array(d1), pa.array(d2)], ["doc", "key", "n", "d1", "d2"])

    return texts.mapInArrow(run, "doc long, key binary, n long, d1 long, d2 long")


def meeting_pairs(texts: DataFrame, size: int, percent: int) -> DataFrame:
    """a, b: digests of sets that meet at a key, each paired with the least there."""
    frequent = frequent_shingles(texts, size)

    def emit(batches):
        seen: set = set()  # equal sets of a task go out once, unless forgotten
        for batch in slices(batches, "text"):
            value, bounds = shingles(*buffer_of(batch.column("text")), size)
            d1, _ = set_digests(value, bounds)
            row, key = signatures(value, bounds, percent, frequent)
            fresh = np.zeros(len(d1), bool)
            for i, d in enumerate(d1.tolist()):
                if d not in seen:
                    fresh[i] = True
                    seen.add(d)
            if len(seen) > SEEN:
                seen = set()
            keep = fresh[row]
            yield pa.RecordBatch.from_arrays([pa.array(key[keep].view(np.int64)), pa.array(d1[row[keep]])], ["key", "d1"])

    def pair(batches):
        last_key = head = None
        for batch in batches:
            if not batch.num_rows:
                continue
            key, d1 = batch.column("key").to_numpy(), batch.column("d1").to_numpy()
            new = np.ones(len(key), bool)
            new[1:] = key[1:] != key[:-1]
            new[0] = last_key is None or key[0] != last_key
            at = np.flatnonzero(new)
            heads = d1[at] if new[0] else np.concatenate([[head], d1[at]])
            least = np.repeat(heads, np.diff(np.concatenate([at if new[0] else np.append(0, at), [len(key)]])))
            other = d1 != least
            other[1:] &= (d1[1:] != d1[:-1]) | new[1:]
            last_key, head = key[-1], least[-1]
            if other.any():
                pairs = np.unique(np.stack([least[other], d1[other]], axis=1), axis=0)
                yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0].copy()), pa.array(pairs[:, 1].copy())], ["a", "b"])

    n = partitions(texts.sparkSession)
    rows = texts.mapInArrow(emit, "key long, d1 long").repartition(n, "key").sortWithinPartitions("key", "d1")
    return rows.mapInArrow(pair, "a long, b long")


class Tile:
    """Sets of one tile, joined exactly; links connect components."""

    def __init__(self, value: np.ndarray, bounds: np.ndarray, percent: int):
        self.flat, self.bounds, self.size, self.percent = np.unique(value, return_inverse=True)[1], bounds, np.diff(bounds), percent
        self.universe = int(self.flat.max(initial=0)) + 1
        self.root = np.arange(len(self.size))
        self.links: list[tuple[int, int]] = []
        self.radius = 1 - percent / 100

    def linkable(self, items: np.ndarray) -> np.ndarray:
        """Those whose shingles are shared with others among them often enough for any link."""
        while len(items) > 1:
            at = ragged(self.bounds[items], self.size[items])
            count = np.bincount(self.flat[at], minlength=self.universe)
            total = np.concatenate([[0], np.cumsum(count[self.flat[at]] > 1)])
            cut = np.concatenate([[0], np.cumsum(self.size[items])])
            keep = 100 * np.diff(total[cut]) >= self.percent * self.size[items]
            if keep.all():
                break
            items = items[keep]
        return items

    def shared(self, one: int, items: np.ndarray) -> np.ndarray:
        """Sizes of the intersections of one set with some."""
        mark = np.zeros(self.universe, np.int32)
        mark[self.flat[self.bounds[one] : self.bounds[one + 1]]] = 1
        at = ragged(self.bounds[items], self.size[items])
        return np.add.reduceat(mark[self.flat[at]], np.concatenate([[0], np.cumsum(self.size[items])[:-1]]))

    def compare(self, one: int, items: np.ndarray) -> np.ndarray:
        """Distances; links found on the way are kept."""
        both = self.shared(one, items)
        union = self.size[one] + self.size[items] - both
        for j in items[100 * both >= self.percent * union]:
            if self.root[j] != self.root[one]:
                self.links.append((one, int(j)))
                self.root[self.root == self.root[j]] = self.root[one]
        return 1 - both / union

    def join(self, items: np.ndarray) -> None:
        if len(items) < 2 or len(np.unique(self.root[items])) < 2:
            return
        if len(items) <= LEAF:
            self.pairs(items, np.zeros((0, len(items))))
            return
        far = [self.compare(int(items[0]), items)]
        while len(far) < PIVOTS:
            nearest = np.min(far, axis=0)
            if nearest.max() <= 2 * self.radius:
                break
            far.append(self.compare(int(items[nearest.argmax()]), items))
        far = np.array(far)
        near = far.min(axis=0)
        cells = [items[d - near <= 2 * self.radius + 1e-9] for d in far]
        if max(map(len, cells)) <= 0.8 * len(items):
            for cell in cells:
                self.join(cell)
        else:  # the pivots don't part these
            self.pairs(items, far)

    def pairs(self, items: np.ndarray, far: np.ndarray) -> None:
        for k in range(len(items) - 1):
            rest = np.arange(k + 1, len(items))
            rest = rest[self.root[items[rest]] != self.root[items[k]]]
            a, b = self.size[items[k]], self.size[items[rest]]
            rest = rest[100 * np.minimum(a, b) >= self.percent * np.maximum(a, b)]
            if len(far):
                rest = rest[(np.abs(far[:, rest] - far[:, [k]]) <= self.radius + 1e-9).all(axis=0)]
            if len(rest):
                self.compare(int(items[k]), items[rest])


def groups_of(batches, columns: tuple[str, ...], size: int):
    """Key, names, sets and last flags of the rows of one key after the other, from rows sorted by key."""
    key, sets, names, flags = None, [], [], []
    for part, buf, offsets in unpacked(batches):
        value, bounds = shingles(buf, offsets, size)
        keys = list(zip(*(part.column(x).to_pylist() for x in columns), strict=True))
        flag = part.column("flag").to_pylist()
        for r, d in enumerate(part.column("d1").to_pylist()):
            if keys[r] != key:
                if names:
                    yield key, names, sets, flags
                key, sets, names, flags = keys[r], [], [], []
            sets.append(value[bounds[r] : bounds[r + 1]])
            names.append(d)
            flags.append(flag[r])
    if names:
        yield key, names, sets, flags


def tile_of(sets: list, percent: int) -> "Tile":
    return Tile(np.concatenate(sets), np.concatenate([[0], np.cumsum([len(x) for x in sets])]), percent)


def stars(large: DataFrame, size: int, percent: int) -> DataFrame:
    """region, d1, pivots (linked with the set), cells (pivots in whose cells or windows it lies) of the members of large regions."""
    part = F.pmod(F.xxhash64("d1", F.lit(1)), F.col("parts")).cast("int")
    pivot = F.pmod(F.xxhash64("d1", F.lit(2)), F.col("members")) < STARS
    columns = ["region", "part", "d1", "size", "packed"]
    centres = large.where(pivot).withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    rows = large.withColumn("part", part).select(*columns, F.lit(False).alias("flag")).unionByName(centres.select(*columns, F.lit(True).alias("flag")))

    def run(batches):
        for (region, _), names, sets, flags in groups_of(batches, ("region", "part"), size):
            t = tile_of(sets, percent)
            flag = np.array(flags)
            far_of = {n: i for i, n in enumerate(names) if flag[i]}
            centre = [far_of[n] for n in sorted(far_of)]  # in the same order in every part
            mine = np.flatnonzero(~flag)
            if not len(mine):
                continue
            every = np.concatenate([mine, np.array(centre, np.int64)])
            both = np.array([t.shared(c, every) for c in centre], np.int64).reshape(len(centre), len(every))
            union = t.size[centre][:, None] + t.size[every][None, :] - both
            linked = (100 * both >= percent * union)[:, : len(mine)]
            away = 1 - both / union
            apart: list[int] = []  # pivots that make cells: far from each other
            for i in range(len(centre)):
                if all(away[j, len(mine) + i] > 2 * t.radius + SLACK for j in apart):
                    apart.append(i)
            away = away[apart][:, : len(mine)]
            near = away.min(axis=0, initial=1.0)
            # sets far from all pivots have a cell of their own, ``FAR``; others reach no farther than a radius into it
            edge = 1 - t.radius - 0.01
            inside = (away - near <= 2 * t.radius + SLACK) & (away <= edge + t.radius + SLACK)
            outside = near > edge - t.radius - SLACK
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array([region] * len(mine), pa.int64()),
                    pa.array([names[i] for i in mine], pa.int64()),
                    pa.array([[names[c] for c, x in zip(centre, linked[:, k], strict=True) if x] for k in range(len(mine))], pa.list_(pa.int64())),
                    pa.array([[names[centre[a]] for a, x in zip(apart, inside[:, k], strict=True) if x] + [FAR] * bool(outside[k]) for k in range(len(mine))], pa.list_(pa.int64())),
                ],
                ["region", "d1", "pivots", "cells"],
            )

    n = partitions(large.sparkSession)
    dealt = rows.repartition(n, "region", "part").sortWithinPartitions("region", "part", "flag")
    return dealt.mapInArrow(run, "region long, d1 long, pivots array<long>, cells array<long>")


def tiles_joined(tiles: DataFrame, size: int, percent: int) -> DataFrame:
    """a, b: links found in tiles (region, cell, i, j, d1, size, packed, flag), where two sets without flag aren't compared."""

    def run(batches):
        for _, names, sets, flags in groups_of(batches, ("region", "cell", "i", "j"), size):
            if len(names) < 2:
                continue
            t = tile_of(sets, percent)
            settled = np.flatnonzero(~np.array(flags))
            if len(settled):
                t.root[settled] = settled[0]
            t.join(t.linkable(np.argsort(t.size, kind="stable")))
            if t.links:
                a, b = np.array(t.links).T
                d = np.array(names)
                yield pa.RecordBatch.from_arrays([pa.array(d[a]), pa.array(d[b])], ["a", "b"])

    n = partitions(tiles.sparkSession)
    return tiles.repartition(n, "region", "cell", "i", "j").sortWithinPartitions("region", "cell", "i", "j").mapInArrow(run, "a long, b long")


def links_of(members: DataFrame, size: int, percent: int) -> DataFrame:
    """a, b: links that connect the components among members (region, members, d1, size, packed)."""
    whole = F.lit(0).alias("i"), F.lit(0).alias("j"), F.lit(True).alias("flag")
    small = members.where(F.col("members") <= TILE).select("region", F.col("region").alias("cell"), *whole, "d1", "size", "packed")
    found = tiles_joined(small, size, percent)
    large = members.where(F.col("members") > TILE).withColumn("parts", F.ceil(F.col("members") / TILE).cast("int"))
    if large.isEmpty():
        return found
    star = shared_table(stars(large, size, percent))
    links = star.select(F.explode("pivots").alias("a"), F.col("d1").alias("b")).where("a <> b")
    roots = star.select("region", "d1").join(components(links).withColumnRenamed("node", "d1"), "d1", "left").withColumn("root", F.coalesce("root", "d1"))
    counted = roots.groupBy("region", "root").count()
    main = counted.groupBy("region").agg(F.max_by("root", F.struct("count", "root")).alias("main"))
    opened = roots.join(main, "region").select("d1", (F.col("root") != F.col("main")).alias("open"))
    # windows that hold most of a region twice don't part it: such a region is one cell
    spread = star.groupBy("region").agg((F.avg(F.size("cells")) > SPREAD).alias("whole"))
    cell = F.explode(F.when(F.col("whole"), F.array(F.lit(FAR))).otherwise(F.col("cells")))
    cells = shared_table(star.join(spread, "region").select("region", "d1", cell.alias("cell")).join(opened, "d1"))
    some = lambda c: F.ceil(F.count_if(c) / TILE).cast("int")
    counts = cells.groupBy("region", "cell").agg(some(F.col("open")).alias("open_parts"), some(~F.col("open")).alias("settled_parts"))
    dealt = cells.join(counts.where("open_parts > 0"), ["region", "cell"])
    # open sets fill the first parts, settled ones the others; tiles are pairs of parts of which the first is open
    mix = F.xxhash64("d1", F.lit(3))
    mine = F.when(F.col("open"), F.pmod(mix, F.col("open_parts"))).otherwise(F.col("open_parts") + F.pmod(mix, F.col("settled_parts"))).cast("int")
    last = F.when(F.col("open"), F.col("open_parts") + F.col("settled_parts")).otherwise(F.col("open_parts")) - 1
    both = dealt.withColumn("mine", mine).withColumn("other", F.explode(F.sequence(F.lit(0), last)))
    both = both.select("region", "cell", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"), "d1", F.col("open").alias("flag"))
    tiles = both.join(large.select("d1", "size", "packed"), "d1")
    return found.unionByName(tiles_joined(tiles, size, percent)).unionByName(links)


def marked_documents(docs: DataFrame, id_col: str, text_col: str, size: int, percent: int, tie: Column | None = None) -> DataFrame:
    """doc, key, n, component of every row."""
    texts = texts_of(docs, id_col, text_col)
    keyed = texts_of(docs, id_col, text_col, F.lit(b"") if tie is None else tie)
    sets = shared_table(set_rows(keyed, size))
    points = sets.where("n > 0").groupBy("d1", "d2", "n").agg(F.min("doc").alias("doc"))
    regions = components(meeting_pairs(texts, size, percent))
    counted = regions.join(regions.groupBy("root").agg(F.count("*").alias("members")), "root")
    chosen = counted.withColumnRenamed("node", "d1").join(points, "d1").select("doc", "d1", F.col("root").alias("region"), "members")
    # the identifier may be repeated with another text: its set's digest tells them apart
    members = packed_docs(texts).join(chosen.select("doc").distinct().hint("shuffle_hash"), "doc", "left_semi")
    members = shared_table(packed_sets(members, size).dropDuplicates(["d1"]).join(chosen.select("d1", "region", "members"), "d1"))
    roots = components(links_of(members, size, percent))
    least = sets.where("n > 0").groupBy("d1").agg(F.min("doc").alias("doc"))
    labelled = least.join(roots.withColumnRenamed("node", "d1"), "d1", "left").withColumn("root", F.coalesce("root", "d1"))
    ids = labelled.groupBy("root").agg(F.min("doc").alias("component"))
    lookup = labelled.join(ids, "root").select("d1", "root", "component")
    return sets.join(lookup, "d1", "left").withColumn("component", F.when(F.col("n") > 0, F.col("component")).otherwise(F.col("doc")))


def linked_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = WORDS, percent: int = PERCENT) -> DataFrame:
    """doc_id, n_shingles, component_id of every row."""
    out = marked_documents(docs, id_col, text_col, size, percent)
    return out.select(unident("doc").alias("doc_id"), F.col("n").alias("n_shingles"), unident("component").alias("component_id"))


def packed_sets(packed: DataFrame, size: int) -> DataFrame:
    """d1, size, packed: compressed texts with the digest of their sets."""

    def run(batches):
        for part, buf, offsets in unpacked(batches):
            d1, _ = set_digests(*shingles(buf, offsets, size))
            yield pa.RecordBatch.from_arrays([pa.array(d1), part.column("size"), part.column("packed")], ["d1", "size", "packed"])

    return packed.mapInArrow(run, "d1 long, size long, packed binary")


def distinct_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = WORDS, percent: int = PERCENT) -> DataFrame:
    """The first row of each component (by identifier), and all rows without words, with all their columns."""
    rows = shared_table(marked_documents(docs, id_col, text_col, size, percent, row_key(docs)).where("n > 0").select("root", "doc", "key"))
    counted = rows.groupBy("root", "doc", "key").agg(F.count("*").alias("same"))
    first = counted.groupBy("root").agg(F.min(F.struct("doc", "key")).alias("first"), F.sum("same").alias("n")).where("n > 1")
    keys = counted.join(first, "root").select("key", (F.struct("doc", "key") != F.col("first")).alias("gone"), "same")
    return without(docs, keys.where("gone or same > 1").select("key", "gone"))
