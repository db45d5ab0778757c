"""Token counts: encoding in Arrow functions that return lengths only.

Texts are cut at ASCII white space, a safe boundary for a tokenizer that drops white space and never
merges across it; a slice of about a million bytes at a time is split, its distinct pieces are encoded in batches
balanced by bytes, and the lengths are added up by document. A worker remembers the lengths of up
to ``REMEMBERED`` pieces; what is forgotten is encoded again.

Null or empty text: 0 bytes, 0 tokens. Null or repeated identifiers and repeated rows: one output row for
each input row. A long text is cut at white space into parts of about a million bytes, so memory doesn't follow its length; a run
without white space is encoded whole. An empty table gives an empty result. Columns besides the identifier and the text are ignored.
"""

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from .arrays import SLICE_BYTES, buffer_of, cut_text, slices, word_bounds
from .tables import named

REMEMBERED = 400_000
BATCH_BYTES = 200_000


def balanced(pieces: list, limit: int = BATCH_BYTES):
    """Runs of pieces of about ``limit`` bytes."""
    run, size = [], 0
    for piece in pieces:
        run.append(piece)
        size += len(piece)
        if size >= limit:
            yield run
            run, size = [], 0
    if run:
        yield run


def lengths(encode, pieces: pa.Array, known: dict) -> np.ndarray:
    texts = pieces.to_pylist()
    new = [x for x in texts if x not in known]
    if new:
        if len(known) + len(new) > REMEMBERED:
            known.clear()
            new = texts
        for run in balanced(new):
            for x, n in zip(run, encode(run), strict=True):
                known[x] = n
    return np.fromiter((known[x] for x in texts), np.int64, len(texts))


def count_tokens(docs: DataFrame, path: str, limit: int = 2048, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for every row. path: a tokenizers file whose pre-tokenizer drops white space."""

    def run(batches):
        from tokenizers import Tokenizer

        tokenizer = Tokenizer.from_file(path)
        tokenizer.no_truncation()
        tokenizer.no_padding()
        known: dict = {}

        def encode(texts):
            return [len(x) for x in tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

        def counted(column) -> np.ndarray:
            buf, offsets = buffer_of(column)
            starts, ends, first = word_bounds(buf, offsets)
            # each word reaches to the next one's start: the piece keeps its white space off by the stripped end
            sizes = (ends - starts).astype(np.int32)
            spread = np.zeros(len(buf) + 1, np.int8)
            np.add.at(spread, starts, 1)
            np.add.at(spread, ends, -1)
            packed = buf[np.cumsum(spread[:-1], dtype=np.int8).astype(bool)]
            cuts = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)
            words = pa.StringArray.from_buffers(len(sizes), pa.py_buffer(cuts), pa.py_buffer(packed))
            coded = words.dictionary_encode()
            each = lengths(encode, coded.dictionary, known)[coded.indices.to_numpy(zero_copy_only=False)] if len(words) else np.zeros(0, np.int64)
            total = np.concatenate([[0], np.cumsum(each)])
            return total[first[1:]] - total[first[:-1]]

        for batch in slices(batches, text_col):
            column = batch.column(text_col)
            sizes = pc.binary_length(column).fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
            if batch.num_rows == 1 and sizes[0] > 2 * SLICE_BYTES:
                n = np.array([sum(int(counted(pa.array([part]))[0]) for part in cut_text(column[0].as_buffer().to_pybytes(), SLICE_BYTES))])
            else:
                n = counted(column)
            yield pa.RecordBatch.from_arrays([batch.column(id_col), pa.array(sizes), pa.array(n), pa.array(n > limit)], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(named(id_col), named(text_col)).mapInArrow(run, f"doc_id {kind}, n_bytes long, n_tokens long, over_limit boolean")
