"""Vectorised text primitives over Arrow string columns: byte buffers, word bounds, hashes, slices bounded by bytes."""

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Text handled at once in a worker; temporaries are about 60 times this.
SLICE_BYTES = 1_000_000

# The code points of [\x20\x09-\x0D].
WHITE = (9, 10, 11, 12, 13, 32)

U64 = np.uint64


def white_table() -> np.ndarray:
    table = np.zeros(256, bool)
    table[list(WHITE)] = True
    return table


def lower_table() -> np.ndarray:
    table = np.arange(256, dtype=np.uint8)
    table[65:91] += 32
    return table


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    x = x ^ (x >> U64(30))
    x *= U64(0xBF58476D1CE4E5B9)
    x ^= x >> U64(27)
    x *= U64(0x94D049BB133111EB)
    x ^= x >> U64(31)
    return x


def odd(n: int, seed: int) -> np.ndarray:
    """n odd multipliers."""
    return mix(np.arange(1, n + 1, dtype=U64) * U64(0x9E3779B97F4A7C15) + U64(seed)) | U64(1)


def buffer_of(column) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and n + 1 offsets of a string or binary column, nulls empty; eight zero bytes follow the last."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks() if column.num_chunks != 1 else column.chunk(0)
    column = column.cast(pa.large_binary()).fill_null(b"")
    n = len(column)
    if not n:
        return np.zeros(8, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + n + 1]
    data = np.frombuffer(column.buffers()[2], np.uint8) if column.buffers()[2] else np.zeros(0, np.uint8)
    out = np.zeros(offsets[-1] - offsets[0] + 8, np.uint8)
    out[:-8] = data[offsets[0] : offsets[-1]]
    return out, offsets - offsets[0]


def slices(batches, text: str, limit: int = SLICE_BYTES):
    """Record batches cut so that each holds about ``limit`` bytes of ``text``, or one row."""
    for batch in batches:
        sizes = pc.binary_length(batch.column(text)).fill_null(0).to_numpy(zero_copy_only=False)
        total = np.concatenate([[0], np.cumsum(sizes, dtype=np.int64)])
        at = 0
        while at < batch.num_rows:
            end = max(at + 1, int(np.searchsorted(total, total[at] + limit, "right")) - 1)
            yield batch.slice(at, end - at)
            at = end


def cut_text(data: bytes, limit: int, marks: bytes = bytes(WHITE)):
    """Parts of a long text of about ``limit`` bytes, cut before one of some ASCII bytes; a part without any goes on to the next one."""
    at = 0
    while at < len(data):
        end = at + limit
        if end < len(data):
            before = max(data.rfind(bytes([m]), at + 1, end) for m in marks)
            after = min((x for m in marks if (x := data.find(bytes([m]), end)) >= 0), default=len(data))
            end = before if before > at else after
        yield data[at:end]
        at = min(end, len(data)) if end > at else len(data)


def eights(buf: np.ndarray) -> np.ndarray:
    """The little-endian 64-bit integer at every byte."""
    return np.ndarray((len(buf) - 7,), "<u8", buf, strides=(1,))


def word_bounds(buf: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the words of all rows, and each row's first word (n + 1 positions)."""
    n = int(offsets[-1])
    solid = ~white_table()[buf[:n]]
    edge = np.zeros(n + 1, bool)
    edge[offsets] = True  # words never cross rows
    before = np.zeros(n, bool)
    before[1:] = solid[:-1]
    starts = np.flatnonzero(solid & (~before | edge[:n]))
    after = np.zeros(n, bool)
    after[:-1] = solid[1:]
    ends = np.flatnonzero(solid & (~after | edge[1:])) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def hash_ranges(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray, seed: int = 0) -> np.ndarray:
    """64-bit hashes of byte ranges of any length."""
    at = eights(buf)
    size = (ends - starts).astype(np.int64)
    out = mix(size.astype(U64) + odd(1, seed)[0])
    live, k = np.arange(len(starts)), 0
    while len(live):
        left = size[live] - 8 * k
        word = at[starts[live] + 8 * k]
        short = left < 8
        if short.any():
            keep = (U64(1) << (left[short].astype(U64) * U64(8))) - U64(1)
            word[short] &= keep
        out[live] = mix((out[live] ^ word) * U64(0x9FB21C651E98DF25) + U64(k + 1))
        k += 1
        live = live[left > 8]
    return out


def rolled(values: np.ndarray, k: int, seed: int) -> np.ndarray:
    """Hashes of k consecutive values, at every position that has k."""
    n = len(values) - k + 1
    if n <= 0:
        return np.zeros(0, U64)
    total = np.zeros(n, U64)
    for j, m in enumerate(odd(k, seed)):
        total += values[j : j + n] * m
    return mix(total)


def window_min(values: np.ndarray, w: int) -> np.ndarray:
    """Minimum of w consecutive values, at every position that has w."""
    n = len(values) - w + 1
    if n <= 0:
        return np.zeros(0, values.dtype)
    reach, low = 1, values
    while 2 * reach <= w:
        low = np.minimum(low[:-reach], low[reach:])
        reach *= 2
    return np.minimum(low[:n], low[w - reach : w - reach + n])


def owners(bounds: np.ndarray) -> np.ndarray:
    """The row of each element, from n + 1 bounds."""
    return np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))


def ragged(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """All positions of the ranges, one after the other."""
    sizes = sizes.astype(np.int64)
    total = int(sizes.sum())
    if not total:
        return np.zeros(0, np.int64)
    shift = np.repeat(starts - np.concatenate([[0], np.cumsum(sizes)[:-1]]), sizes)
    return np.arange(total) + shift
