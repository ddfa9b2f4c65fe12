"""Cost-balanced packing of token ids into sequences.

Every text is turned into ids once, in the task that reads it, and closed by an end id. Whole sequences are cut off a
document's front; what remains, shorter than a sequence, is its tail. Tails wait in a window of bounded size; a window
opens exactly the sequences that its tails fill, and gives the tails, longest first, to the open sequence of lowest
estimated attention cost (linear plus quadratic in the lengths of its pieces) that still has room. A tail that fits
nowhere whole is cut over the roomiest sequences. The room of a window equals its ids: full sequences, and for the rest
sequences at powers of two, which need no padding. Nothing is shuffled, so the work grows with the input alone; a lost
task repeats the same pieces, since its rows and their order are those of its input split.
"""

from __future__ import annotations

import base64
import os
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from uncertainseq.llm.common import text_of

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
SEQUENCE, WINDOW, END_ID = 1024, 4096, 0
SPECIAL, SPECIAL_ID = "<|endoftext|>", 50256
#: Below this code point both libraries split texts alike; texts with others go to the slower one.
COMMON = 0x370


def default_vocabulary() -> tuple[str, str]:
    """Paths of the public 50k byte-level vocabulary, as a tokenizer file and as ranks."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_50k.tiktoken")


class Encoder:
    """Ids of texts by the tokenizer file; the same vocabulary as ranks, several times as fast, serves texts of common letters."""

    def __init__(self, tokenizer_file: str, ranks_file: str | None):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.exact = Tokenizer.from_file(tokenizer_file)
        self.fast = None
        if ranks_file:
            import public_tokenizers
            import tiktoken

            with open(ranks_file, "rb") as f:
                ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
            self.fast = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={SPECIAL: SPECIAL_ID})

    def __call__(self, text: str) -> np.ndarray:
        if self.fast is not None and (text.isascii() or ord(max(text)) < COMMON):
            return self.fast.encode_to_numpy(text, allowed_special="all").astype("<u4")
        return np.array(self.exact.encode(text, add_special_tokens=False).ids, dtype="<u4")


def room(total: int, sequence: int) -> list[int]:
    """Sequences that ``total`` ids fill without padding: full ones, then the powers of two of the rest."""
    rest = total % sequence
    return [sequence] * (total // sequence) + [1 << b for b in range(rest.bit_length() - 1, -1, -1) if rest >> b & 1]


def assign(lengths: np.ndarray, sequence: int, linear: float, quadratic: float) -> list[tuple[int, int, int, int, int]]:
    """Pieces (tail, start in the tail, length, sequence, offset in it) for tails of the given lengths."""
    sizes = np.array(room(int(lengths.sum()), sequence), dtype=np.int64)
    left, cost, out = sizes.copy(), np.zeros(len(sizes)), []

    def put(tail: int, start: int, n: int, to: int) -> None:
        out.append((tail, start, n, to, int(sizes[to] - left[to])))
        left[to] -= n
        cost[to] += linear * n + quadratic * n * n

    for tail in np.lexsort((np.arange(len(lengths)), -lengths)):
        start, n = 0, int(lengths[tail])
        while n:
            fits = left >= n
            to = int(np.argmin(np.where(fits, cost, np.inf))) if fits.any() else int(np.argmax(left))
            part = min(n, int(left[to]))
            put(int(tail), start, part, to)
            start, n = start + part, n - part
    return out


def pack(docs: DataFrame, tokenizer_file: str | None = None, ranks_file: str | None = None, sequence: int = SEQUENCE, window: int = WINDOW, linear: float = 1.0, quadratic: float = 1.0 / SEQUENCE) -> DataFrame:
    """Pieces of all documents (columns doc_id, text; others are ignored).

    Null text is empty: its only id is the end id. Null, repeated or tied doc_ids are packed row by row, each row's ids
    in exactly one piece. No rows give no pieces. ``sequence`` must be a power of two.
    """
    default = default_vocabulary()
    tokenizer_file, ranks_file = (tokenizer_file, ranks_file) if tokenizer_file else default
    names = [x.split()[0] for x in PIECES.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, task = Encoder(tokenizer_file, ranks_file), TaskContext.get().partitionId() << 40
        opened = 0
        tails: list[tuple] = []
        rows: list[tuple] = []

        def close_window() -> None:
            nonlocal opened
            for tail, start, n, to, offset in assign(np.array([len(x[3]) for x in tails]), sequence, linear, quadratic):
                doc, before, total, ids = tails[tail]
                rows.append((doc, before + start, n, zlib.crc32(ids[start : start + n].tobytes()), total, task + opened + to, offset))
            opened += len(room(sum(len(x[3]) for x in tails), sequence))
            tails.clear()

        def flush() -> pa.RecordBatch:
            out = pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*rows, strict=True)], names=names)
            rows.clear()
            return out

        for batch in batches:
            for doc, text in zip(batch.column(0), batch.column(1), strict=True):
                doc, text = doc.as_py(), text.as_py()
                ids = np.append(encode(text) if text else np.zeros(0, "<u4"), np.array([END_ID], "<u4"))
                whole = len(ids) // sequence * sequence
                for start in range(0, whole, sequence):
                    rows.append((doc, start, sequence, zlib.crc32(ids[start : start + sequence].tobytes()), len(ids), task + opened, 0))
                    opened += 1
                if whole < len(ids):
                    tails.append((doc, whole, len(ids), ids[whole:].copy()))
                if len(tails) >= window:
                    close_window()
                if len(rows) >= 10_000:
                    yield flush()
        if tails:
            close_window()
        if rows:
            yield flush()

    return docs.select("doc_id", text_of().alias("text")).mapInArrow(run, PIECES)
