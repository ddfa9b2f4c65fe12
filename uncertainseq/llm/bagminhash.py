"""Near-duplicate documents by BagMinHash signatures of their runs of five words, taken as multisets.

A run that occurs w times has weight w. Weights are discretised at the whole numbers, and the axis of weights is split
into (0, 1], (1, 2], (2, 4], (4, 8] and so on. On each part every run has a Poisson process of its own, seeded by run and
part alone, with ``size`` points a unit of weight; a point holds a component and a place on the axis, and counts in a
document where its place is within the run's weight there. A component of the signature is the least point that counts:
two documents agree in it with the probability of their weighted Jaccard similarity. Points come in ascending order, so a
run stops as soon as its next point lies beyond the largest component of its document; long documents cost about one
point a run. All texts of a batch advance together, one point of every unfinished run for each numpy step.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from uncertainseq.llm.common import materialise, text_of
from uncertainseq.llm.jaccard import partner_sizes, verified_jaccard
from uncertainseq.llm.linking import classes
from uncertainseq.llm.textnp import U64, mix, shingle_hashes, slices, string_bytes, word_hashes

BANDS, ROWS, WORDS, THRESHOLD, SEED = 24, 5, 5, 0.8, 5


def weights(grams: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Document, run and weight of the distinct runs of each document."""
    docs = np.repeat(np.arange(len(at) - 1), np.diff(at))
    order = np.lexsort((grams, docs))
    d, g = docs[order], grams[order]
    new = np.ones(len(g), bool)
    new[1:] = (g[1:] != g[:-1]) | (d[1:] != d[:-1])
    first = np.flatnonzero(new)
    return d[first], g[first], np.diff(np.append(first, len(g)))


def signatures(column: pa.Array, size: int, seed: int = SEED, k: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """(texts, size) components as floats, infinite where the text has no words; and each text's number of runs."""
    out, runs = np.full((len(column), size), np.inf), np.zeros(len(column), np.int64)
    for begin, to in slices(column):
        grams, at = shingle_hashes(*word_hashes(column.slice(begin, to - begin)), k)
        runs[begin:to] = np.diff(at)
        if len(grams):
            sign(*weights(grams, at), out[begin:to], seed)
    return out, runs


def sign(docs: np.ndarray, grams: np.ndarray, weight: np.ndarray, out: np.ndarray, seed: int) -> None:
    """Lower the components ``out`` (document, component) by the points of weighted runs; documents ascend."""
    size = out.shape[1]
    flat = out.reshape(-1)
    levels = np.ceil(np.log2(np.maximum(weight, 1))).astype(np.int64)  # parts of the axis beyond the first
    pick = np.repeat(np.arange(len(docs)), levels + 1)
    part = np.arange(len(pick)) - np.repeat(np.concatenate([[0], np.cumsum(levels + 1)[:-1]]), levels + 1)
    low = np.where(part > 0, 2.0 ** (part - 1), 0.0)
    wide = np.where(part > 0, low, 1.0)
    state = mix(grams[pick] ^ mix(part.astype(U64) * U64(0xA0761D6478BD642F) + U64(seed)))
    doc, top = docs[pick], weight[pick] - low
    point = np.zeros(len(pick))
    while len(doc):
        state = mix(state + U64(0x9E3779B97F4A7C15))
        point = point - np.log(((state >> U64(11)).astype(np.float64) + 0.5) * 2.0**-53) / (size * wide)
        other = mix(state ^ U64(0xE7037ED1A0B428DB))
        most = out.max(axis=1)
        on = point < most[doc]
        state, doc, top, wide, point, other = state[on], doc[on], top[on], wide[on], point[on], other[on]
        counts = (other >> U64(40)).astype(np.float64) * 2.0**-24 * wide < top
        at = doc[counts] * size + ((other[counts] & U64(0xFFFFFFFF)) * U64(size) >> U64(32)).astype(np.int64)
        np.minimum.at(flat, at, point[counts])


def band_keys(signed: np.ndarray, bands: int) -> np.ndarray:
    """(texts, bands) hashes of consecutive components."""
    bits = signed.view(U64).reshape(len(signed), bands, -1)
    total = np.zeros(bits.shape[:2], U64)
    for j in range(bits.shape[2]):
        total = mix(total * U64(65_537) + bits[:, :, j])
    return total.view(np.int64)


def sketch(docs: DataFrame, bands: int = BANDS, rows: int = ROWS, seed: int = SEED) -> DataFrame:
    """(doc_id, key of equal texts, bands): bands is null where a text has no words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = batch.column(1)
            signed, runs = signatures(column, bands * rows, seed)
            data, at = string_bytes(column)
            keys = [hashlib.blake2b(data[a:b], digest_size=16).hexdigest() for a, b in zip(at, at[1:], strict=False)]
            keyed = band_keys(signed, bands)
            lists = [x if n else None for x, n in zip(keyed, runs, strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(keys), pa.array(lists, pa.list_(pa.int64()))], names=["doc_id", "key", "bands"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of().alias("text")).mapInArrow(run, "doc_id long, key string, bands array<long>")


def near_duplicates(docs: DataFrame, threshold: float = THRESHOLD, bands: int = BANDS, rows: int = ROWS, seed: int = SEED) -> DataFrame:
    """(doc_id, class_id) of every document; class_id is the least doc_id of those joined by links of ``threshold`` or more.

    Equal texts share a class, empty ones and those without words too; a text of fewer than five words is one run. Null
    text is empty. A null doc_id has no class (null); rows of one doc_id are one document. No rows give no rows; other
    columns are ignored.
    """
    signed = materialise(sketch(docs, bands, rows, seed), "bagminhash")
    return classes(signed, lambda pairs, texts: verified_jaccard(pairs, texts, threshold, weighted=True), docs, lambda texts: partner_sizes(texts, threshold, weighted=True))


def keep_one(docs: DataFrame, **options) -> DataFrame:
    """The documents without those whose class has a smaller doc_id; all columns stay. Rows of null doc_id stay."""
    found = near_duplicates(docs, **options).filter("class_id < doc_id").select("doc_id").distinct()
    return docs.join(found, "doc_id", "left_anti").select(docs.columns)
