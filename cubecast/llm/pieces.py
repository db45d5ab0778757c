"""Encoding to pieces and decoding, in numpy, for the model files of a public piece library.

Texts are cut where a run of spaces begins: no piece crosses such a place. The distinct words of a slice are encoded,
grouped by length, so that equal-length words advance together in matrices: substring hashes of all starts and
lengths are looked up once in a table of the pieces (a second hash confirms each hit), and then

* a unigram model goes through Viterbi: at each end, a maximum of scores over piece lengths, with backpointers;
* a merge model (byte-pair scores) goes through the same lattice, where a step counts only if the piece follows the one before
  it as merging would leave them. Merging works in a fixed order and locally, so a row of pieces is what merging gives if and only
  if merging the characters of each two neighbours gives these two. So at each end exactly one piece may be
  the last one; it is found longest first and its length is the backpointer. Verdicts on pairs come from batched merging of the
  pair's characters; a worker remembers up to ``REMEMBERED``. Maximal sums of scores would give other pieces than the model's library.

Words longer than ``LONG`` code points go through the same lattice one by one.
Code points that no piece holds become byte pieces, or the unknown piece.

Long texts go in parts, cut before spaces. Null text: as empty, no pieces. Null or repeated identifiers and repeated rows: one output row each. Empty table: empty
result. Other columns are ignored.
"""

import hashlib
import struct

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from .arrays import U64, buffer_of, cut_text, ragged, slices
from .tables import named

SLICE = 4_000_000
LONG = 48
REMEMBERED = 5_000_000
#: Places (word, start, length) that are looked up at once.
CELLS = 8_000_000
FILL = "\U0010ffff"
MARK = 0x2581
BASES = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F)
SPREAD = 0xD6E8FEB86659FD93
#: Codes whose substrings are looked up together, and bits of the table that tells most substrings from pieces: both stay in a core's cache.
TILE, SHADE = 1 << 15, 20
# Field numbers and piece types of the public model format.
PIECES, TRAINER, NORMALIZER = 1, 2, 3
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
UNIGRAM, MERGES = 1, 2


def fields(data: bytes):
    """(number, value) of a message in the public wire format."""
    at = 0

    def varint():
        nonlocal at
        out = shift = 0
        while True:
            b = data[at]
            at += 1
            out |= (b & 127) << shift
            shift += 7
            if b < 128:
                return out

    while at < len(data):
        tag = varint()
        kind = tag & 7
        if kind == 0:
            yield tag >> 3, varint()
        elif kind == 2:
            size = varint()
            yield tag >> 3, data[at : at + size]
            at += size
        else:
            size = 4 if kind == 5 else 8
            yield tag >> 3, data[at : at + size]
            at += size


def grown(code: np.ndarray, base: int) -> np.ndarray:
    """Prefix hashes along the last axis, one longer than it."""
    out = np.zeros((*code.shape[:-1], code.shape[-1] + 1), U64)
    for i in range(code.shape[-1]):
        out[..., i + 1] = out[..., i] * U64(base) + code[..., i] + U64(1)
    return out


def spread(keys: np.ndarray, bits: int) -> np.ndarray:
    """Slots of keys in a table of 2^bits."""
    return ((keys.astype(U64, copy=False) * U64(SPREAD)) >> U64(64 - bits)).view(np.int64)


class Memory:
    """Verdicts on pairs that a worker remembers of one model: a hash table, at most half full, where a pair goes to the next free slot. What is forgotten is judged again."""

    def __init__(self):
        self.clear()

    def clear(self, bits: int = 16) -> None:
        self.bits, self.count, self.slots = bits, 0, np.full(1 << bits, -1, np.int64)

    def find(self, pairs: np.ndarray) -> np.ndarray:
        """1 or 0, or -1 for a pair that isn't there."""
        out = np.full(len(pairs), -1, np.int8)
        at, live = spread(pairs, self.bits), np.arange(len(pairs))
        while len(live):
            held = self.slots[at]
            same = held >> 1 == pairs[live]
            out[live[same]] = held[same] & 1
            on = ~same & (held >= 0)
            live, at = live[on], (at[on] + 1) & (len(self.slots) - 1)
        return out

    def add(self, pairs: np.ndarray, verdict: np.ndarray) -> None:
        """Different pairs, none of them there."""
        if self.count + len(pairs) > REMEMBERED:
            self.clear()
        new = pairs * 2 + verdict
        if 2 * (self.count + len(new)) > len(self.slots):
            new = np.concatenate([self.slots[self.slots >= 0], new])
            self.clear((2 * len(new)).bit_length())
        self.count += len(new)
        at = spread(new >> 1, self.bits)
        while len(new):
            free = self.slots[at] < 0
            self.slots[at[free]] = new[free]
            lost = self.slots[at] != new
            new, at = new[lost], (at[lost] + 1) & (len(self.slots) - 1)


MEMORIES: dict[str, Memory] = {}


class Model:
    """Pieces, scores and tables of one model file; small enough to travel with a function."""

    def __init__(self, pieces: list[tuple[str, float, int]], kind: int, dummy_prefix: bool = True):
        self.kind, self.dummy_prefix = kind, dummy_prefix
        self.pieces = pieces
        self.unknown = next((i for i, p in enumerate(pieces) if p[2] == UNKNOWN), 0)
        self.byte_ids = np.full(256, -1, np.int64)
        for i, (text, _, type_) in enumerate(pieces):
            if type_ == BYTE:
                self.byte_ids[int(text[3:5], 16)] = i
        usable = [i for i, p in enumerate(pieces) if p[2] in (NORMAL, USER)]
        self.longest = max([1, *(len(pieces[i][0]) for i in usable)])
        keys = [np.zeros(len(usable), U64), np.zeros(len(usable), U64)]
        by_length: dict = {}
        for at, i in enumerate(usable):
            by_length.setdefault(len(pieces[i][0]), []).append((at, i))
        for n, group in by_length.items():
            code = np.array([[ord(c) for c in pieces[i][0]] for _, i in group], U64).reshape(len(group), n)
            for k, base in enumerate(BASES):
                keys[k][[at for at, _ in group]] = grown(code, base)[:, -1] + U64(n)
        order = np.argsort(keys[0], kind="stable")
        self.keys, self.second = keys[0][order], keys[1][order]
        self.shade, self.place = np.zeros(1 << SHADE, bool), np.zeros(1 << SHADE, np.int32)
        slot = spread(self.keys, SHADE)
        self.shade[slot], self.place[slot] = True, np.arange(len(slot))
        self.ids = np.array(usable, np.int64)[order]
        self.scores = np.array([pieces[i][1] for i in usable], np.float64)[order]
        # Fixed value: what an unknown code point loses against the worst piece
        self.unknown_score = float(self.scores.min(initial=0.0)) - 10.0
        self.base = len(pieces) + 0x110001  # pieces, then code points without a piece, then no piece at all
        self.name = hashlib.sha256(repr((kind, dummy_prefix, pieces)).encode()).hexdigest()
        shown = [self.shown(i) for i in range(len(pieces))]
        self.flat = np.frombuffer(b"".join(shown), np.uint8)
        self.cuts = np.concatenate([[0], np.cumsum([len(x) for x in shown])])

    @classmethod
    def load(cls, path: str) -> "Model":
        with open(path, "rb") as file:
            data = file.read()
        pieces, kind, prefix = [], UNIGRAM, True
        for number, value in fields(data):
            if number == PIECES:
                piece = dict(fields(value))
                pieces.append((piece.get(1, b"").decode(), struct.unpack("<f", piece[2])[0] if 2 in piece else 0.0, piece.get(3, NORMAL)))
            elif number == TRAINER:
                kind = dict(fields(value)).get(3, UNIGRAM)
            elif number == NORMALIZER:
                rules = dict(fields(value))
                prefix = bool(rules.get(3, 1))
                if rules.get(2) or rules.get(4, 1) or not rules.get(5, 1):
                    raise ValueError("only models that keep texts as they are (no character map, no space removal) can be used")
        if kind not in (UNIGRAM, MERGES):
            raise ValueError("only unigram and merge models can be used")
        if any(type_ == USER for _, _, type_ in pieces) or any("▁" in text.lstrip("▁") for text, _, _ in pieces):
            raise ValueError("pieces that cross a word's start can't be used")
        return cls(pieces, kind, prefix)

    def shown(self, i: int) -> bytes:
        text, _, type_ = self.pieces[i]
        if type_ == BYTE:
            return bytes([int(text[3:5], 16)])
        return b"" if type_ == CONTROL else " ⁇ ".encode() if type_ == UNKNOWN else text.replace("▁", " ").encode()

    def probe(self, code: np.ndarray) -> np.ndarray:
        """For words of one length: place in the sorted keys of the piece at each start of each length, or -1; [length - 1, word, start]."""
        words, n = code.shape
        out = np.full((min(n, self.longest), words, n), -1, np.int32)
        step = max(1, TILE // max(n, 1))
        for row in range(0, words, step):
            first, second = (grown(code[row : row + step].astype(U64), b) for b in BASES)
            powers = [U64(1), U64(1)]
            with np.errstate(over="ignore"):
                for size in range(1, len(out) + 1):
                    powers = [p * U64(b) for p, b in zip(powers, BASES, strict=True)]
                    key = (first[:, size:] - first[:, : n - size + 1] * powers[0] + U64(size)).ravel()
                    slot = spread(key, SHADE)
                    maybe = np.flatnonzero(self.shade[slot])
                    at, key = self.place[slot[maybe]], key[maybe]
                    other = np.flatnonzero(self.keys[at] != key)  # no piece, or one of several in a slot
                    at[other] = np.minimum(np.searchsorted(self.keys, key[other]), len(self.keys) - 1)
                    w, s = np.divmod(maybe, n - size + 1)
                    hit = (self.keys[at] == key) & (self.second[at] == second[w, s + size] - second[w, s] * powers[1] + U64(size))
                    out[size - 1, row + w[hit], s[hit]] = at[hit]
        return out

    def score_of(self, found: np.ndarray) -> np.ndarray:
        return np.where(found >= 0, self.scores[found], -np.inf)

    def viterbi(self, code: np.ndarray) -> np.ndarray:
        """Symbol ends: for each word and start, the end of the symbol that starts there, 0 if none does."""
        found = self.probe(code)
        words, n = code.shape
        best = np.full((words, n + 1), -np.inf)
        best[:, 0] = 0
        back = np.zeros((words, n + 1), np.int32)
        for end in range(1, n + 1):
            sizes = np.arange(min(end, len(found)), 0, -1)  # the longest of equals first
            step = np.stack([best[:, end - s] + self.score_of(found[s - 1, :, end - s]) for s in sizes])
            alone = best[:, end - 1] + self.unknown_score
            step[-1] = np.where(found[0, :, end - 1] >= 0, step[-1], alone)
            pick = step.argmax(axis=0)
            best[:, end] = step[pick, np.arange(words)]
            back[:, end] = sizes[pick]
        return self.traced(back), found

    @staticmethod
    def traced(back: np.ndarray) -> np.ndarray:
        """Symbol ends along the backpointers."""
        words, n = back.shape[0], back.shape[1] - 1
        ends = np.zeros((words, n), np.int32)
        at = np.full(words, n)
        live = np.arange(words)
        while len(live):
            start = at[live] - back[live, at[live]]
            ends[live, start] = at[live]
            at[live] = start
            live = live[start > 0]
        return ends

    def merged(self, code: np.ndarray):
        """Symbol ends by merging the best pair of each word, again and again, for all words at once."""
        found = self.probe(code)
        words, n = code.shape
        ends = np.tile(np.arange(1, n + 1, dtype=np.int32), (words, 1))
        before = np.tile(np.arange(-1, n, dtype=np.int32), (words, 1))
        gain = np.full((words, n), -np.inf)
        if n > 1 and len(found) > 1:
            gain[:, : n - 1] = self.score_of(found[1, :, : n - 1])

        def pair(w, a):
            """Score of the symbol at a with the one after it."""
            b = ends[w, a]
            inside = b < n
            c = np.where(inside, ends[w, np.minimum(b, n - 1)], 0)
            size = c - a
            good = inside & (size <= len(found))
            return np.where(good, self.score_of(found[np.where(good, size - 1, 0), w, a]), -np.inf)

        live = np.arange(words)
        while len(live):
            a = gain[live].argmax(axis=1)
            keep = gain[live, a] > -np.inf
            live, a = live[keep], a[keep]
            if not len(live):
                break
            b = ends[live, a]
            c = ends[live, b]
            ends[live, a] = c
            ends[live, b] = 0
            gain[live, b] = -np.inf
            before[live, c] = a
            gain[live, a] = pair(live, a)
            p = before[live, a]
            inner = p >= 0
            gain[live[inner], p[inner]] = pair(live[inner], p[inner])
        return ends, found

    @property
    def memory(self) -> Memory:
        return MEMORIES.setdefault(self.name, Memory())

    def spelled(self, symbol: int) -> str:
        n = len(self.pieces)
        return self.pieces[symbol][0] if symbol < n else chr(symbol - n) if symbol < self.base - 1 else ""

    def judge(self, pairs: np.ndarray) -> np.ndarray:
        """Whether merging the characters of two symbols gives the two."""
        left = [self.spelled(int(x)) for x in pairs // self.base]
        texts = [a + self.spelled(int(x)) for a, x in zip(left, pairs % self.base, strict=True)]
        middle, size = np.array([len(x) for x in left]), np.array([len(x) for x in texts])
        room = -(-size // 8) * 8  # filled up with what no piece holds, so that a few matrices take all
        out = np.zeros(len(pairs), bool)
        for n in np.unique(room):
            group = np.flatnonzero(room == n)
            for at in range(0, len(group), 20_000):
                part = group[at : at + 20_000]
                block = np.frombuffer("".join(texts[i].ljust(n, FILL) for i in part).encode("utf-32-le", "surrogatepass"), np.uint32).reshape(len(part), n)
                ends, _ = self.merged(block)
                m, k, row = middle[part], size[part], np.arange(len(part))
                out[part] = np.where(m > 0, (ends[row, 0] == m) & (ends[row, np.minimum(m, n - 1)] == k), ends[row, 0] == k)
        return out

    def follow(self, before: np.ndarray, symbol: np.ndarray) -> np.ndarray:
        """Verdicts on pairs of symbols."""
        known, pairs = self.memory, before * self.base + symbol
        verdict = known.find(pairs)
        miss = np.flatnonzero(verdict < 0)
        if len(miss):
            new, back = np.unique(pairs[miss], return_inverse=True)
            judged = self.judge(new)
            known.add(new, judged)
            verdict[miss] = judged[back]
        return verdict > 0

    def chained(self, blocks: list[np.ndarray]):
        """Symbol ends, by the lattice in which each symbol may follow the one before. A block holds words of one length; shorter blocks come first."""
        found = [self.probe(x) for x in blocks]
        rows = np.array([len(x) for x in blocks])
        length = np.repeat([x.shape[1] for x in blocks], rows)
        inner = np.concatenate([np.arange(n) for n in rows]) * length
        place_at = np.repeat(np.concatenate([[0], np.cumsum([x.size for x in found])[:-1]]), rows) + inner  # of a word's first start, for length 1
        stride = np.repeat([x.size for x in blocks], rows)  # to the next length
        code_at = np.repeat(np.concatenate([[0], np.cumsum([x.size for x in blocks])[:-1]]), rows) + inner
        state_at = np.concatenate([[0], np.cumsum(length + 1)[:-1]])
        places, code = np.concatenate([x.ravel() for x in found]), np.concatenate([x.ravel() for x in blocks]).astype(np.int64)
        last = np.full(int((length + 1).sum()), self.base - 1, np.int64)
        back = np.zeros(len(last), np.int32)
        for end in range(1, int(length[-1]) + 1):
            waiting = np.arange(np.searchsorted(length, end), len(length))
            for size in range(min(end, self.longest), 0, -1):
                place = places[place_at[waiting] + (size - 1) * stride[waiting] + end - size]
                symbol = self.ids[place]
                if size == 1:
                    symbol = np.where(place >= 0, symbol, len(self.pieces) + code[code_at[waiting] + end - 1])
                    maybe = np.ones(len(waiting), bool)
                else:
                    maybe = place >= 0
                    if not maybe.any():
                        continue
                who, symbol = waiting[maybe], symbol[maybe]
                good = self.follow(last[state_at[who] + end - size], symbol)
                state = state_at[who[good]] + end
                last[state], back[state] = symbol[good], size
                maybe[maybe] = good
                waiting = waiting[~maybe]
                if not len(waiting):
                    break
        cuts = np.concatenate([[0], np.cumsum([len(x) * (x.shape[1] + 1) for x in blocks])])
        return [(self.traced(back[i:j].reshape(len(x), x.shape[1] + 1)), f) for i, j, x, f in zip(cuts[:-1], cuts[1:], blocks, found, strict=True)]

    def chained_alone(self, code: np.ndarray):
        """The same for one long word."""
        found, n, none = self.probe(code), code.shape[1], self.base - 1
        back = np.zeros((1, n + 1), np.int32)
        last = [none] * (n + 1)
        verdicts: dict = {}
        size_of, end_of = np.nonzero(found[:, 0, :] >= 0)
        ends = end_of + size_of + 1
        order = np.lexsort((-size_of, ends))
        steps = zip(ends[order].tolist(), (size_of[order] + 1).tolist(), self.ids[found[size_of, 0, end_of]][order].tolist(), strict=True)
        by_end: dict = {}
        for end, size, symbol in steps:
            by_end.setdefault(end, []).append((size, symbol))
        for end in range(1, n + 1):
            options = by_end.pop(end, [])
            if not options or options[-1][0] > 1:
                options.append((1, len(self.pieces) + int(code[0, end - 1])))
            for size, symbol in options:
                pair = (last[end - size], symbol)
                if pair not in verdicts:
                    verdicts[pair] = bool(self.follow(np.array([pair[0]]), np.array([pair[1]]))[0])
                if verdicts[pair]:
                    last[end], back[0, end] = symbol, size
                    break
        return self.traced(back), found

    def words(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all words, one after the other, and n + 1 cuts. Spaces stand for the mark."""
        sizes = pc.utf8_length(texts).to_numpy(zero_copy_only=False).astype(np.int64)
        buf, offsets = buffer_of(texts)
        code = np.frombuffer(buf[: offsets[-1]].tobytes().decode("utf-8", "replace").encode("utf-32-le"), np.uint32).copy()
        code[code == 32] = MARK
        cuts = np.concatenate([[0], np.cumsum(sizes)])
        word, start, ident = [], [], []

        def settle(parts):
            """parts: word numbers of one length each, shorter ones first."""
            blocks = [code[cuts[p][:, None] + np.arange(sizes[p[0]])] for p in parts]
            if self.kind == UNIGRAM:
                done = [self.viterbi(x) for x in blocks]
            else:
                done = self.chained(blocks) if sizes[parts[-1][0]] <= LONG else [self.chained_alone(x) for x in blocks]
            for part, block, (ends, found) in zip(parts, blocks, done, strict=True):
                w, a = np.nonzero(ends)
                place = found[np.minimum(ends[w, a] - a, len(found)) - 1, w, a]
                known = place >= 0
                word.append(part[w[known]])
                start.append(a[known] * 4)
                ident.append(self.ids[place[known]])
                if not known.all():
                    w, a = w[~known], a[~known]
                    ids, row, byte = self.unknown_ids(block[w, a])
                    word.append(part[w[row]])
                    start.append(a[row] * 4 + byte)
                    ident.append(ids)

        held, cells = [], 0
        for n in np.unique(sizes):
            if not n:
                continue
            group = np.flatnonzero(sizes == n)
            step = 1 if n > LONG else max(1, CELLS // int(n * min(n, self.longest)))
            for at in range(0, len(group), step):
                part = group[at : at + step]
                if held and (n > LONG or cells + len(part) * int(n * min(n, self.longest)) > CELLS):
                    settle(held)
                    held, cells = [], 0
                held.append(part)
                cells += len(part) * int(n * min(n, self.longest))
        if held:
            settle(held)
        if not word:
            return np.zeros(0, np.int32), np.zeros(len(sizes) + 1, np.int64)
        word, start, ident = np.concatenate(word), np.concatenate(start), np.concatenate(ident)
        order = np.lexsort((start, word))
        return ident[order].astype(np.int32), np.searchsorted(word[order], np.arange(len(sizes) + 1))

    def unknown_ids(self, points: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids of code points without a piece: byte pieces where the model has all of them, else the unknown piece; with each id's row and byte."""
        size = 1 + (points >= 0x80) + (points >= 0x800) + (points >= 0x10000).astype(np.int64)
        data = np.frombuffer(points.astype("<u4").tobytes().decode("utf-32-le").encode(), np.uint8)
        ids, row = self.byte_ids[data], np.repeat(np.arange(len(points)), size)
        byte = np.arange(len(data)) - np.repeat(np.cumsum(size) - size, size)
        lacking = np.bincount(row, ids < 0, len(points)) > 0
        keep = ~lacking[row] | (byte == 0)
        return np.where(lacking[row], self.unknown, ids)[keep], row[keep], byte[keep]

    def encode(self, column) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all rows, one after the other, and n + 1 cuts. A long text goes in parts, cut before spaces, as no piece crosses the start of a run of spaces."""
        if len(column) == 1 and (data := column.cast(pa.large_binary())[0].as_py() or b"") and len(data) > 2 * SLICE:
            parts, held = [], b""
            for part in cut_text(data, SLICE, b" "):
                if held.endswith(b" ") or not held:  # a run of spaces stays in one part
                    held += part
                    continue
                parts.append(self.encode_some(pa.array([held], pa.large_binary()), self.dummy_prefix and not parts)[0])
                held = part
            parts.append(self.encode_some(pa.array([held], pa.large_binary()), self.dummy_prefix and not parts)[0])
            ids = np.concatenate(parts)
            return ids, np.array([0, len(ids)])
        return self.encode_some(column, self.dummy_prefix)

    def encode_some(self, column, prefix: bool) -> tuple[np.ndarray, np.ndarray]:
        buf, offsets = buffer_of(column)
        sizes = np.diff(offsets)
        some = sizes > 0
        shift = np.concatenate([[0], np.cumsum(some & prefix)])
        moved = offsets + shift  # each text goes behind a space
        text = np.full(int(moved[-1]), 32, np.uint8)
        text[ragged(moved[:-1] + (some & prefix), sizes)] = buf[: offsets[-1]]
        space = text == 32
        start = space.copy()
        start[1:] &= ~space[:-1]
        mark = (text[:-3] == 0xE2) & (text[1:-2] == 0x96) & (text[2:-1] == 0x81) if len(text) > 3 else np.zeros(0, bool)
        start[3:] &= ~mark
        start[moved[:-1][some]] = True
        begins = np.flatnonzero(start)
        words = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(begins), [None, pa.py_buffer(np.append(begins, len(text)).astype(np.int64)), pa.py_buffer(text)])
        coded = words.dictionary_encode()
        flat, cuts = self.words(coded.dictionary.cast(pa.large_string()))
        code = coded.indices.to_numpy(zero_copy_only=False)
        count = np.diff(cuts)[code]
        ids = flat[ragged(cuts[code], count)]
        total = np.concatenate([[0], np.cumsum(count)])
        return ids, total[np.searchsorted(begins, moved)]

    def decode(self, ids: np.ndarray, cuts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Bytes of all rows and n + 1 offsets."""
        size = np.diff(self.cuts)[ids]
        out = self.flat[ragged(self.cuts[ids], size)]
        total = np.concatenate([[0], np.cumsum(size)])[cuts]
        if self.dummy_prefix:
            heads = total[:-1][np.diff(total) > 0]
            heads = heads[out[heads] == 32]
            keep = np.ones(len(out), bool)
            keep[heads] = False
            lost = np.concatenate([[0], np.cumsum(~keep)])
            out, total = out[keep], total - lost[total]
        return out, total


def encoded(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, ids of every row."""
    model = Model.load(path)

    def run(batches):
        for batch in slices(batches, text_col, SLICE):
            ids, cuts = model.encode(batch.column(text_col))
            yield pa.RecordBatch.from_arrays([batch.column(id_col), pa.ListArray.from_arrays(pa.array(cuts.astype(np.int32)), pa.array(ids))], ["doc_id", "ids"])

    return docs.select(named(id_col), named(text_col)).mapInArrow(run, f"doc_id {docs.schema[id_col].dataType.simpleString()}, ids array<int>")


def decoded(rows: DataFrame, path: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """doc_id, text of every row; ids outside the model count as unknown, null lists as empty."""
    model = Model.load(path)

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                part = batch.slice(at, 500)
                column = part.column(ids_col)
                ids = column.flatten().fill_null(model.unknown).to_numpy(zero_copy_only=False)
                ids = np.where((ids >= 0) & (ids < len(model.pieces)), ids, model.unknown)
                cuts = np.concatenate([[0], np.cumsum(pc.list_value_length(column).fill_null(0).to_numpy())])
                out, total = model.decode(ids, cuts)
                data = out.tobytes()
                texts = [data[a:b].decode("utf-8", "replace") for a, b in zip(total[:-1], total[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([part.column(id_col), pa.array(texts, pa.string())], ["doc_id", "text"])

    return rows.select(named(id_col), named(ids_col)).mapInArrow(run, f"doc_id {rows.schema[id_col].dataType.simpleString()}, text string")


def round_trip(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_ids, ids, decoded_sha256 (of the decoded text), exact (decoding gives the text back) of every row."""
    model = Model.load(path)

    def run(batches):
        for batch in slices(batches, text_col, SLICE):
            ids, cuts = model.encode(batch.column(text_col))
            out, total = model.decode(ids, cuts)
            buf, offsets = buffer_of(batch.column(text_col))
            view, back = memoryview(buf), memoryview(np.ascontiguousarray(out))
            pairs = list(zip(total[:-1], total[1:], offsets[:-1], offsets[1:], strict=True))
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column(id_col),
                    pa.array(np.diff(cuts)),
                    pa.ListArray.from_arrays(pa.array(cuts.astype(np.int32)), pa.array(ids)),
                    pa.array([hashlib.sha256(back[a:b]).hexdigest() for a, b, _, _ in pairs], pa.string()),
                    pa.array([back[a:b] == view[c:d] for a, b, c, d in pairs], pa.bool_()),
                ],
                ["doc_id", "n_ids", "ids", "decoded_sha256", "exact"],
            )

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(named(id_col), named(text_col)).mapInArrow(run, f"doc_id {kind}, n_ids long, ids array<int>, decoded_sha256 string, exact boolean")
