"""Quality classifier from weak labels.

Eight heuristic labellers look at a text and vote good, bad or nothing. Expectation-maximisation over the counts of
vote patterns (of all documents; at most 3^8 patterns reach the driver, whatever the corpus) estimates each
labeller's accuracy in both classes and the posterior of each pattern. The posteriors are the soft labels of a hashed linear
scorer, trained on at most ``TRAIN_ROWS`` documents picked by a hash of identifier and text; the scorer then
judges every document. Given labels are not needed; tests use them to measure accuracy.

Null or blank text: score 0, rejected. Null or repeated identifiers and repeated rows: one output row each, equal texts alike.
Long texts are read whole. Empty table: empty result. Other columns are kept by ``accepted``, whatever their names.
"""

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .arrays import U64, buffer_of, eights, hash_ranges, mix, owners, slices, word_bounds
from .tables import named

TRAIN_ROWS = 4000
BITS = 11
PARTS = 3
#: A text counts as so many words longer when features are averaged, so that a few words say little.
CALM = 5
EDGE = 20
# Frequent function words of English, German, French and Spanish.
FUNCTION_WORDS = """the of and to in is was for on that by this with as it be are an a der die das und ein eine den von zu mit ist im
nicht auf de la le les et un une des en du que qui dans pour sur el los las y una por con para es""".split()
NOTHING, GOOD, BAD = 0, 1, 2
LABELLERS = ("symbols", "capitals", "stutter", "function words", "bars", "word length", "top word", "sentences")


def codes(words: list[str]) -> np.ndarray:
    buf, offsets = buffer_of(pa.array(words))
    return np.sort(hash_ranges(buf, offsets[:-1], offsets[1:]))


class Reader:
    """What labellers and scorer need of the texts of a slice."""

    def __init__(self, column):
        self.buf, self.offsets = buffer_of(column)
        self.starts, self.ends, self.bounds = word_bounds(self.buf, self.offsets)
        self.hashes = hash_ranges(self.buf, self.starts, self.ends)
        self.count = np.diff(self.bounds)
        self.row = owners(self.bounds)

    def per_word(self, values) -> np.ndarray:
        """Sums by document over its words."""
        total = np.concatenate([[0.0], np.cumsum(values, dtype=np.float64)])
        return total[self.bounds[1:]] - total[self.bounds[:-1]]

    def per_byte(self, values) -> np.ndarray:
        total = np.concatenate([[0], np.cumsum(values, dtype=np.int64)])
        return (total[self.offsets[1:]] - total[self.offsets[:-1]]).astype(np.float64)

    def stutters(self) -> np.ndarray:
        same = np.zeros(len(self.hashes), bool)
        same[1:] = (self.hashes[1:] == self.hashes[:-1]) & (self.row[1:] == self.row[:-1])
        return same

    def top_share(self) -> np.ndarray:
        """Share of each document's most frequent word."""
        if not len(self.hashes):
            return np.zeros(len(self.count))
        order = np.lexsort((self.hashes, self.row))
        h, r = self.hashes[order], self.row[order]
        new = np.ones(len(h), bool)
        new[1:] = (h[1:] != h[:-1]) | (r[1:] != r[:-1])
        at = np.flatnonzero(new)
        most = np.zeros(len(self.count))
        np.maximum.at(most, r[at], np.diff(np.append(at, len(h))))
        return most / np.maximum(self.count, 1)

    def votes(self) -> np.ndarray:
        """[document, labeller]."""
        n = np.maximum(self.count, 1)
        text = self.buf[: self.offsets[-1]]
        kind = np.zeros(256, np.int8)
        kind[97:123], kind[65:91], kind[128:] = 1, 2, 1
        kind[[ord(c) for c in "$%&*#|!@^~=+<>{}[]\\_"]] = 3
        k = kind[text]
        size = np.maximum(self.per_byte(np.ones(len(text), np.int8)), 1)
        lower, upper, odd = (self.per_byte(k == i) for i in (1, 2, 3))
        letters = np.maximum(lower + upper, 1)
        function = self.per_word(np.isin(self.hashes, codes(FUNCTION_WORDS))) / n
        stutter = self.per_word(self.stutters()) / n
        bars = self.per_word(self.hashes == codes(["|"])[0]) / n
        length = size / n
        ends = self.per_word(self.buf[self.ends - 1] == 46) if len(self.ends) else np.zeros(len(n))
        top = self.top_share()

        never, few = np.zeros(len(n), bool), n <= 20  # a few words show nothing but marks

        def vote(bad, good):
            return np.where(bad, BAD, np.where(good, GOOD, NOTHING))

        out = np.stack(
            [
                vote(odd / size > 0.08, never),
                vote((upper / letters > 0.4) & (n > 5), never),
                vote(stutter > 0.2, never),
                vote((function < 0.03) & ~few, ((function > 0.08) | few) & (stutter < 0.1)),
                vote(bars > 0.1, never),
                vote(((length < 3) | (length > 14)) & ~few, never),
                vote((top > 0.4) & ~few, (top < 0.2) | few),
                vote((ends == 0) & (n > 60), ((ends / n > 0.01) & (ends / n < 0.3)) | few),
            ],
            axis=1,
        )
        out[self.count == 0] = NOTHING
        return out

    def features(self) -> tuple[np.ndarray, ...]:
        """Feature numbers of each word: itself, its last bytes, its shape with whether it repeats the word before."""
        at = eights(np.concatenate([np.zeros(8, np.uint8), self.buf]))
        tail = at[self.ends] >> U64(40)  # the last three bytes before the end
        kind = np.full(256, 1, np.uint8)
        kind[65:91], kind[48:58], kind[33:48], kind[58:65], kind[91:97], kind[123:128] = 2, 3, 4, 5, 6, 7
        size = np.minimum(self.ends - self.starts, 15)
        shape = kind[self.buf[self.starts]].astype(U64) | kind[self.buf[self.ends - 1]].astype(U64) << U64(3) | size.astype(U64) << U64(6) | self.stutters().astype(U64) << U64(10)
        mask = U64((1 << BITS) - 1)
        return tuple((mix(x * U64(2 * i + 3)) & mask).astype(np.int64) + (i << BITS) for i, x in enumerate((self.hashes, tail, shape)))


def estimated(patterns: np.ndarray, counts: np.ndarray, rounds: int = 100) -> tuple[np.ndarray, np.ndarray, float]:
    """Posterior of good for each vote pattern, P(vote | class) as [labeller, class, vote], P(good).

    Class 0 is good, 1 bad. The start is the share of good votes; one vote of each kind in each class is added to the counts.
    Labellers are taken to be better than chance: a bad vote is at least ``EDGE`` times as likely on a bad document. Without that,
    EM is free to call the larger of two groups of languages bad; with it, a labeller whose bad votes fall on both classes is
    estimated as weak (few bad votes in either class), not as wrong.
    """
    good, bad = (patterns == GOOD).sum(1), (patterns == BAD).sum(1)
    post = np.where(good + bad > 0, (good + 0.5) / (good + bad + 1.0), 0.5)
    post = np.where(bad > 0, np.minimum(post, 0.5), post)  # bad marks are rarer than good ones
    seen = np.stack([patterns == v for v in (NOTHING, GOOD, BAD)], axis=2)
    table, prior = np.zeros((patterns.shape[1], 2, 3)), 0.5
    for _ in range(rounds):
        for c, p in enumerate((post, 1 - post)):
            mass = np.einsum("p,plv->lv", counts * p, seen.astype(float)) + 1.0
            table[:, c] = mass / mass.sum(1, keepdims=True)
        table[:, 0, BAD] = np.minimum(table[:, 0, BAD], table[:, 1, BAD] / EDGE)
        table[:, 1, GOOD] = np.minimum(table[:, 1, GOOD], table[:, 0, GOOD])
        prior = (np.sum(counts * post) + 1) / (counts.sum() + 2)
        logs = np.einsum("plv,lcv->pc", seen.astype(float), np.log(table)) + np.log([prior, 1 - prior])
        new = 1 / (1 + np.exp(np.clip(logs[:, 1] - logs[:, 0], -50, 50)))
        done = np.abs(new - post).max() < 1e-9
        post = new
        if done:
            break
    return post, table, float(prior)


class Shares:
    """Rows of feature shares, most of them zero, as places and values by row and by feature. ``rows``: bytes of two-byte places, then of as many two-byte reals."""

    def __init__(self, rows: list[bytes], width: int):
        n = np.array([len(r) // 4 for r in rows], np.int64)
        place = np.concatenate([np.frombuffer(r, "<u2", len(r) // 4) for r in rows])
        self.values = np.concatenate([np.frombuffer(r, "<f2", offset=len(r) // 2) for r in rows]).astype(np.float32)
        self.places, self.shape = place.astype(np.int32), (len(rows), width)
        order = np.argsort(place, kind="stable")
        self.row = np.repeat(np.arange(len(rows), dtype=np.int32), n)[order]
        self.by_place = self.values[order]
        self.full, self.used = np.flatnonzero(n), np.flatnonzero(np.bincount(place, minlength=width))
        self.starts = np.concatenate([[0], np.cumsum(n)])[self.full]
        self.heads = np.searchsorted(place[order], self.used)

    def times(self, w: np.ndarray) -> np.ndarray:
        out = np.zeros(self.shape[0], np.float32)
        if len(self.full):
            out[self.full] = np.add.reduceat(self.values * w[self.places], self.starts)
        return out

    def turned(self, g: np.ndarray) -> np.ndarray:
        """The transpose times a vector."""
        out = np.zeros(self.shape[1], np.float32)
        if len(self.used):
            out[self.used] = np.add.reduceat(self.by_place * g[self.row], self.heads)
        return out


def fitted(x: Shares, y: np.ndarray, rounds: int = 300, decay: float = 2e-5) -> tuple[np.ndarray, float]:
    """Logistic regression on rows of feature shares, soft labels, by accelerated gradient steps."""
    weight = 1 / len(y)
    w, b = np.zeros(x.shape[1], np.float32), 0.0
    ww, bb = w.copy(), b
    rate = 8.0
    for i in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x.times(ww) + bb, -30, 30)))
        g = (weight * (p - y)).astype(np.float32)
        new, newb = ww - rate * (x.turned(g) + decay * ww), bb - rate * float(g.sum())
        m = i / (i + 3)
        ww, bb = (new + m * (new - w)).astype(np.float32), newb + m * (newb - b)
        w, b = new, newb
    return w, b


class Scorer:
    def __init__(self, weights: np.ndarray, bias: float):
        self.weights, self.bias = weights, bias

    def __call__(self, reader: Reader) -> np.ndarray:
        raw = sum(self.weights[f] for f in reader.features()) if len(reader.hashes) else np.zeros(0)
        total = reader.per_word(raw) / (reader.count + CALM) + self.bias
        return np.where(reader.count > 0, 1 / (1 + np.exp(-np.clip(total, -30, 30))), 0.0)


def pattern_counts(docs: DataFrame, text_col: str) -> DataFrame:
    def run(batches):
        for batch in slices(batches, "text"):
            votes = Reader(batch.column("text")).votes()
            found, n = np.unique(votes @ 3 ** np.arange(votes.shape[1]), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(found.astype(np.int64)), pa.array(n.astype(np.int64))], ["pattern", "n"])

    return docs.select(named(text_col).alias("text")).mapInArrow(run, "pattern long, n long").groupBy("pattern").agg(F.sum("n").alias("n"))


def trained(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rows: int = TRAIN_ROWS) -> tuple[Scorer, dict]:
    """The scorer, and what was estimated: posterior by pattern, P(vote | class) by labeller, P(good)."""
    counted = pattern_counts(docs, text_col).collect()
    size = len(LABELLERS)
    if not counted:
        return Scorer(np.zeros(PARTS << BITS, np.float32), 0.0), {"posterior": {}, "labellers": {}, "good": 0.5}
    ids = np.array(sorted(r["pattern"] for r in counted))
    n = {r["pattern"]: r["n"] for r in counted}
    patterns = ids[:, None] // 3 ** np.arange(size) % 3
    counts = np.array([n[i] for i in ids], float)
    post, table, prior = estimated(patterns, counts)
    posterior = dict(zip(ids.tolist(), post.tolist(), strict=True))

    def run(batches):
        for batch in (b.slice(i, 500) for b in slices(batches, "text") for i in range(0, b.num_rows, 500)):
            r = Reader(batch.column("text"))
            votes = r.votes() @ 3 ** np.arange(size)
            x = np.zeros((len(votes), PARTS << BITS), np.float32)
            for f in r.features():
                np.add.at(x, (r.row, f), 1)
            x /= (r.count + CALM)[:, None]
            some = [np.flatnonzero(row) for row in x]  # few features of a text: dense rows would fill the driver
            packed = [at.astype("<u2").tobytes() + row[at].astype("<f2").tobytes() for at, row in zip(some, x, strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(votes.astype(np.int64)), pa.array(packed, pa.binary())], ["pattern", "x"])

    # the share is set so that about ``rows`` documents are picked, equal ones once; the limit, in the order of the hash, is a
    # guard that chance doesn't reach
    total = counts.sum()
    part = docs.select(named(text_col).alias("text"), F.xxhash64(named(id_col), named(text_col)).alias("pick"))
    if total > rows:
        part = part.where(F.pmod("pick", F.lit(1 << 48)) < F.lit(max(1, int((1 << 48) * min(1.0, rows / total)))))
    part = part.groupBy("pick").agg(F.min("text").alias("text")).orderBy("pick").limit(2 * rows)
    sample = part.select("text").mapInArrow(run, "pattern long, x binary").collect()
    if not sample:
        return Scorer(np.zeros(PARTS << BITS, np.float32), 0.0), {"posterior": posterior, "labellers": {}, "good": prior}
    x = Shares([s["x"] for s in sample], PARTS << BITS)
    y = np.array([posterior[s["pattern"]] for s in sample])
    w, b = fitted(x, y)
    return Scorer(w, b), {"posterior": posterior, "labellers": dict(zip(LABELLERS, table.tolist(), strict=True)), "good": prior}


def judged(docs: DataFrame, scorer: Scorer, id_col: str = "doc_id", text_col: str = "text", least: float = 0.5) -> DataFrame:
    """doc_id, score, kept of every row."""

    def run(batches):
        for batch in slices(batches, text_col):
            score = scorer(Reader(batch.column(text_col)))
            yield pa.RecordBatch.from_arrays([batch.column(id_col), pa.array(score), pa.array(score >= least)], ["doc_id", "score", "kept"])

    return docs.select(named(id_col), named(text_col)).mapInArrow(run, f"doc_id {docs.schema[id_col].dataType.simpleString()}, score double, kept boolean")


def accepted(docs: DataFrame, scorer: Scorer, text_col: str = "text", least: float = 0.5) -> DataFrame:
    """The rows that are not rejected, with all their columns."""

    def run(batches):
        for batch in slices(batches, text_col):
            yield batch.filter(pa.array(scorer(Reader(batch.column(text_col))) >= least))

    return docs.mapInArrow(run, docs.schema)
