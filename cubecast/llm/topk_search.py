"""Exact top-k by inner product: a ball tree for each shard, searched by branch and bound.

Vectors are dealt to shards by a hash of their identifier. A shard's task reads its vectors, builds a ball tree, and
then answers queries block by block as they stream in. A node's upper bound for a query is q . centre + |q| radius;
of two children each query goes first to the one with its larger bound, and leaves out nodes below its current kth
score. The kth score is shared twice: within a block's search, and between shards, as every query first searches its home
shard and takes the kth score found there, with its identifier, to all others, which return only what beats it.

Components: floor(scale * x) as integers of any size; scores are exact. Where float64 can't hold all sums exactly, it only
chooses candidates, which then go through split integer products or, beyond 2^62, Python integers. A score
outside the long range is returned as the range's end, but ranked by its true value. Vectors that are null, or hold a null or a
non-finite component, take no part. Shorter vectors count as padded with zeros. A query's own row, and rows that repeat its
identifier, are no candidates. Null identifiers are candidates, last in ties. Repeated query rows are answered once; repeated
candidate rows each take a place. Ties go to the smaller identifier. Fewer candidates than k: all. Empty table: empty
result. Other columns are ignored.
"""

import math
import struct
from fractions import Fraction

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .tables import ident, named, partitions, unident

SHARD_ROWS = 65_536
LEAST_SHARD = 2_048
LEAF = 128
BLOCK = 2_048
TOGETHER = 256


class BallTree:
    """Nodes in arrays: centre, radius, range of points, children."""

    def __init__(self, points: np.ndarray, leaf: int = LEAF):
        self.order = np.arange(len(points))
        self.centre, self.radius, self.range, self.child = [], [], [], []
        self.points = points
        self.build(0, len(points), leaf)
        self.points = points[self.order]
        self.centre, self.radius = np.array(self.centre), np.array(self.radius)

    def build(self, a: int, b: int, leaf: int) -> int:
        part = self.points[self.order[a:b]]
        centre = part.mean(axis=0)
        me = len(self.centre)
        self.centre.append(centre)
        # a little more than the largest distance: the bound must hold in floating point
        self.radius.append(np.sqrt(((part - centre) ** 2).sum(axis=1).max()) * (1 + 1e-9) + 1e-6)
        self.range.append((a, b))
        self.child.append(None)
        if b - a > leaf:
            spread = part - centre
            far = spread[(spread**2).sum(axis=1).argmax()]
            other = spread[((spread - far) ** 2).sum(axis=1).argmax()]
            half = (b - a) // 2
            self.order[a:b] = self.order[a:b][np.argsort(spread @ (far - other), kind="stable")]  # halves along the longest line, equal points too
            self.child[me] = (self.build(a, a + half, leaf), self.build(a + half, b, leaf))
        return me


LONG = np.iinfo(np.int64)
WHOLE, WIDE, RAW = b"\0", b"\1", b"\2"  # int32; whole numbers as float64; components not yet scaled, as float64


class Best:
    """The k best (score, true score where it is no long, identifier) of each query of a block, and what candidates must beat."""

    def __init__(self, n: int, k: int, reach: np.ndarray, limit: np.ndarray):
        self.k, self.reach, self.limit, self.waiting = k, reach.copy(), limit.copy(), 0
        self.row, self.score, self.far, self.ident = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, object), np.zeros(0, np.int64)
        self.new: list = []

    def add(self, row, score, far, ident):
        self.new.append((row, score, far, ident))
        self.waiting += len(row)
        if self.waiting > 20_000:
            self.settle()

    def beats(self, rows: np.ndarray, score: np.ndarray, name: np.ndarray) -> np.ndarray:
        level = self.reach[rows][:, None]
        return (score > level) | (score == level) & ((name[None, :] <= self.limit[rows][:, None]) | (np.abs(score) >= LONG.max))

    def settle(self):
        if not self.new:
            return
        row, score, far, ident = (np.concatenate([a, *b]) for a, b in zip((self.row, self.score, self.far, self.ident), zip(*self.new), strict=True))
        if any(x is not None for x in far):
            place = np.array(sorted(range(len(row)), key=lambda i: (row[i], -(int(score[i]) if far[i] is None else far[i]), ident[i])), np.int64)
        else:
            place = np.lexsort((ident, -score, row))
        row, score, far, ident = row[place], score[place], far[place], ident[place]
        turn = np.arange(len(row)) - np.searchsorted(row, row)
        keep = turn < self.k
        last = np.flatnonzero((turn == self.k - 1) & ((score > self.reach[row]) | (score == self.reach[row]) & (ident < self.limit[row])))
        self.reach[row[last]], self.limit[row[last]] = score[last], ident[last]
        self.row, self.score, self.far, self.ident, self.new, self.waiting = row[keep], score[keep], far[keep], ident[keep], [], 0


def exact_scores(queries: np.ndarray, points: np.ndarray, q_whole, p_whole, rows, a: int, b: int, likely):
    """Scores as longs, and true scores where they are none: [row, point]."""
    q, p = queries[rows], points[a:b]
    far = None
    with np.errstate(over="ignore", invalid="ignore"):
        qn, pn = np.sqrt((q**2).sum(axis=1).max()), np.sqrt((p**2).sum(axis=1).max())
        top = qn * pn
    if top < 2.0**52:
        return np.rint(q @ p.T).astype(np.int64), far
    low = np.mod(p, 65536.0)
    if top < 2.0**61 and qn * np.sqrt((low**2).sum(axis=1).max()) < 2.0**52 and qn * (pn / 65536 + np.sqrt(p.shape[1])) < 2.0**52:
        return np.rint(q @ ((p - low) / 65536).T).astype(np.int64) * 65536 + np.rint(q @ low.T).astype(np.int64), far
    score, far = np.full(likely.shape, LONG.min), np.full(likely.shape, None, object)
    for i, j in zip(*np.nonzero(likely), strict=True):
        x = sum(s * t for s, t in zip(q_whole(rows[i]), p_whole(a + j), strict=False))
        score[i, j] = min(max(x, -LONG.max), LONG.max)
        if not -LONG.max < x < LONG.max:
            far[i, j] = x
    return score, far


def search(tree: BallTree, ids: np.ndarray, queries: np.ndarray, own: np.ndarray, k: int, reach: np.ndarray, limit: np.ndarray, q_whole, p_whole) -> Best:
    best = Best(len(queries), k, reach, limit)
    with np.errstate(over="ignore", invalid="ignore"):
        norm = np.sqrt((queries**2).sum(axis=1)) * (1 + 1e-9)
        size = np.sqrt((tree.centre**2).sum(axis=1)) + tree.radius
        # what float64 may lose in a sum of products of this length
        slack = (queries.shape[1] + 8) * 2.3e-16 * norm[:, None] * size[None, :] + 1e-6
        bound = np.nan_to_num(queries @ tree.centre.T + norm[:, None] * tree.radius[None, :] + slack, nan=np.inf, posinf=np.inf, neginf=-np.inf)
        exact = bool(norm.max(initial=0) * size[0] < 2.0**52)  # products of whole numbers, no sum of them rounded
    names = ids[tree.order]
    stack = [(0, np.arange(len(queries)))]
    while stack:
        node, rows = stack.pop()
        rows = rows[bound[rows, node] >= best.reach[rows]]
        if not len(rows):
            continue
        if tree.child[node]:
            left, right = tree.child[node]
            to_left = bound[rows, left] >= bound[rows, right]
            if len(rows) < TOGETHER:  # a few queries stay together
                to_left[:] = to_left.sum() * 2 >= len(rows)
            for part, first, second in ((rows[~to_left], right, left), (rows[to_left], left, right)):
                if len(part):
                    stack += [(second, part), (first, part)]  # the last goes first
            continue
        a, b = tree.range[node]
        name = names[a:b]
        if exact:
            score = queries[rows] @ tree.points[a:b].T
            r, c = np.nonzero(score >= best.reach[rows][:, None].astype(np.float64))
            at, found, who = rows[r], score[r, c].astype(np.int64), name[c]
            keep = (who != own[at]) & ((found > best.reach[at]) | (who <= best.limit[at]))
            if keep.any():
                best.add(at[keep], found[keep], np.full(int(keep.sum()), None, object), who[keep])
                if best.waiting > 4 * k * len(queries) or (best.reach[rows] == LONG.min).any():
                    best.settle()
            continue
        other = name[None, :] != own[rows][:, None]
        with np.errstate(over="ignore", invalid="ignore"):
            rough = np.nan_to_num(queries[rows] @ tree.points[a:b].T + slack[rows, node][:, None], nan=np.inf, posinf=np.inf)
        likely = other & (rough >= best.reach[rows][:, None])
        score, far = exact_scores(queries, tree.points, q_whole, lambda i: p_whole(tree.order[i]), rows, a, b, likely)
        r, c = np.nonzero(likely & best.beats(rows, score, name))
        if len(r):
            best.add(rows[r], score[r, c], far[r, c] if far is not None else np.full(len(r), None, object), name[c])
            if best.waiting > 4 * k * len(queries) or (best.reach[rows] == LONG.min).any():
                best.settle()
    best.settle()
    return best


def integers(table: DataFrame, id_col: str, vec_col: str, scale: float) -> DataFrame:
    """id, packed (a mark, then little-endian components) of the vectors that take part."""

    def run(batches):
        for batch in batches:
            column = batch.column("v")
            sizes = pc.list_value_length(column)
            flat = np.asarray(column.flatten().cast(pa.float64()).fill_null(np.nan).to_numpy(zero_copy_only=False), np.float64)
            with np.errstate(over="ignore", invalid="ignore"):
                x = np.floor(scale * flat) + 0.0
            cut = np.concatenate([[0], np.cumsum(sizes.fill_null(0).to_numpy())])

            def some(flags, cut=cut):
                return np.diff(np.concatenate([[0], np.cumsum(flags)])[cut]) > 0

            wrong, wide, raw = some(~np.isfinite(flat)), some(~(np.abs(x) < 2.0**31)), some(~(np.abs(x) < 1e140))
            keep = np.flatnonzero(sizes.is_valid().to_numpy(zero_copy_only=False) & ~wrong)
            small = np.where(np.abs(x) < 2.0**31, x, 0).astype("<i4").tobytes()
            packed = []
            for i in keep:
                a, b = int(cut[i]), int(cut[i + 1])
                packed.append(RAW + flat[a:b].astype("<f8").tobytes() if raw[i] else WIDE + x[a:b].astype("<f8").tobytes() if wide[i] else WHOLE + small[4 * a : 4 * b])
            yield pa.RecordBatch.from_arrays([batch.column("id").take(pa.array(keep)), pa.array(packed, pa.binary())], ["id", "packed"])

    return table.select(ident(id_col).alias("id"), named(vec_col).alias("v")).mapInArrow(run, "id long, packed binary")


def components_of(data: bytes, scale: float) -> np.ndarray:
    kind = data[:1]
    with np.errstate(over="ignore"):
        return np.frombuffer(data, "<i4", offset=1) if kind == WHOLE else np.frombuffer(data, "<f8", offset=1) * (scale if kind == RAW else 1)


def whole_numbers(data: bytes, scale: float) -> list[int]:
    """Components as Python integers."""
    if data[:1] == RAW:
        return [math.floor(Fraction(x) * Fraction(scale)) for x in np.frombuffer(data, "<f8", offset=1).tolist()]
    return [int(x) for x in components_of(data, scale).tolist()]


def matrix(data: list[bytes], scale: float, width: int | None = None) -> np.ndarray:
    rows = [components_of(x, scale) for x in data]
    width = max([len(x) for x in rows], default=0) if width is None else width
    out = np.zeros((len(rows), width))
    for i, x in enumerate(rows):
        out[i, : min(width, len(x))] = x[:width]
    return out


def ordered(x: int | None) -> bytes | None:
    """An integer as bytes in its order."""
    if x is None:
        return None
    size = (abs(x).bit_length() + 7) // 8
    body = struct.pack(">I", size) + abs(x).to_bytes(size, "big")
    return b"\1" + body if x >= 0 else b"\0" + bytes(255 - b for b in body)


FOUND = "query_id long, packed binary, vec_id long, score long, far binary"


def answered(rows: DataFrame, k: int, scale: float) -> DataFrame:
    """Rows (shard, query, id, packed, reach, limit), a shard's vectors (query false) before its queries -> FOUND."""

    def run(batches):
        state: dict = {"shard": None, "held": [], "tree": None}

        def answer(part):
            if not state["held"]:
                return
            if state["tree"] is None:
                state["data"] = pa.concat_arrays([x.column("packed") for x in state["held"]]).to_pylist()
                state["ids"] = np.concatenate([x.column("id").to_numpy() for x in state["held"]])
                state["tree"] = BallTree(matrix(state["data"], scale))
            tree, data = state["tree"], state["data"]
            for at in range(0, part.num_rows, BLOCK):
                block = part.slice(at, BLOCK)
                packed = block.column("packed").to_pylist()
                q = matrix(packed, scale, tree.points.shape[1])
                own = block.column("id").to_numpy()
                reach, limit = block.column("reach").to_numpy(), block.column("limit").to_numpy()
                best = search(tree, state["ids"], q, own, k, reach, limit, lambda i, p=packed: whole_numbers(p[i], scale), lambda i: whole_numbers(data[i], scale))
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(own[best.row]),
                        block.column("packed").take(pa.array(best.row)),
                        pa.array(best.ident),
                        pa.array(best.score),
                        pa.array([ordered(x) for x in best.far], pa.binary()),
                    ],
                    ["query_id", "packed", "vec_id", "score", "far"],
                )

        for batch in batches:
            shard, query = batch.column("shard").to_numpy(), batch.column("query").to_numpy(zero_copy_only=False)
            edge = np.flatnonzero((shard[1:] != shard[:-1]) | (query[1:] != query[:-1])) + 1
            for a, b in zip([0, *edge], [*edge, len(shard)], strict=True):
                if a == b:
                    continue
                part = batch.slice(a, b - a)
                if shard[a] != state["shard"]:
                    state.update(shard=shard[a], held=[], tree=None)
                if query[a]:
                    yield from answer(part)
                else:
                    state["held"].append(part)

    n = partitions(rows.sparkSession)
    dealt = rows.repartitionById(n, F.pmod("shard", F.lit(n)).cast("int")).sortWithinPartitions("shard", "query", "id")
    return dealt.mapInArrow(run, FOUND)


def ranked(found: DataFrame, k: int) -> DataFrame:
    best = Window.partitionBy("query_id", "packed").orderBy(F.desc("score"), F.desc("far"), "vec_id")
    return found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)


def top_k(table: DataFrame, is_query: Column, k: int = 20, scale: float = 64.0, id_col: str = "vec_id", vec_col: str = "embedding", shard_rows: int = SHARD_ROWS) -> DataFrame:
    """query_id, rank, vec_id, score. is_query: condition over the identifier, as column ``id``."""
    spark = table.sparkSession
    total = table.count()
    shards = max(1, -(-total // shard_rows), min(partitions(spark), -(-total // LEAST_SHARD)))
    vectors = integers(table, id_col, vec_col, scale).withColumn("shard", F.pmod(F.xxhash64("id"), F.lit(shards)).cast("int"))
    # rows that repeat one identifier are dealt by their content too: no identifier fills a shard
    vectors = vectors.withColumn("shard", F.pmod(F.xxhash64("shard", F.xxhash64("packed")), F.lit(shards)).cast("int"))
    none, last = F.lit(-(2**63)), F.lit(2**63 - 1)
    mine = vectors.select("shard", F.lit(False).alias("query"), "id", "packed", none.alias("reach"), last.alias("limit"))
    queries = vectors.where(is_query & (F.col("id") != F.lit(2**63 - 1))).dropDuplicates(["id", "packed"])
    home = answered(mine.unionByName(queries.select("shard", F.lit(True).alias("query"), "id", "packed", none.alias("reach"), last.alias("limit"))), k, scale)
    if shards > 1:
        home = ranked(home, k)
        level = home.where(F.col("rank") == k).select(F.col("query_id").alias("id"), "packed", F.col("score").alias("level"), F.col("vec_id").alias("kth"))
        away = (
            queries.withColumnRenamed("shard", "at")
            .join(level, ["id", "packed"], "left")
            .withColumn("shard", F.explode(F.sequence(F.lit(0), F.lit(shards - 1))))
            .where(F.col("shard") != F.col("at"))
            .select("shard", F.lit(True).alias("query"), "id", "packed", F.coalesce("level", none).alias("reach"), F.coalesce("kth", last).alias("limit"))
        )
        home = home.drop("rank").unionByName(answered(mine.unionByName(away), k, scale))
    return ranked(home, k).select("query_id", "rank", unident("vec_id").alias("vec_id"), "score")


ORACLE = """
with v as (select vec_id, list_transform(embedding, lambda x: floor(64e0 * x::double)::bigint) as v from embeddings
           where embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x::double))) = 0),
s as (select q.vec_id as query_id, c.vec_id, coalesce(list_sum(list_transform(list_zip(q.v, c.v), lambda z: z[1] * z[2])), 0)::bigint as score
      from v q join v c on c.vec_id is distinct from q.vec_id where q.vec_id % 20 = 0)
select query_id, row_number() over (partition by query_id order by score desc, vec_id)::int as rank, vec_id, score from s
qualify rank <= 20
"""
