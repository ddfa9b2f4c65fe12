"""MinHash fingerprints of documents and of edited texts, likeness of fingerprints, and verified near pairs by bands.

A fingerprint is the smallest value of each of ``size`` universal hash functions (a x + b modulo 2**64, upper bits) over
the hashes of all runs of five words; a text without words counts as one run, its bytes. Equal texts have equal
fingerprints, and the share of equal components estimates the Jaccard similarity of the texts' runs.
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
from uncertainseq.llm.textnp import U64, mix, shingle_hashes, slices, span_hashes, string_bytes, word_spans

SIZE, WORDS, SEED, BANDS = 64, 5, 20, 16
LEAST = -(1 << 63)


def permutations(size: int, seed: int = SEED) -> tuple[np.ndarray, np.ndarray]:
    """Odd multipliers and addends of ``size`` universal hash functions."""
    drawn = mix(np.arange(1, 2 * size + 1, dtype=U64) * U64(0x9E3779B97F4A7C15) + U64(seed))
    return drawn[:size] | U64(1), drawn[size:]


def shingles_of(column: pa.Array, k: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all runs of k words of each text; of the whole text where it has bytes but no words."""
    data, offsets = string_bytes(column)
    first, end, texts = word_spans(data, offsets)
    grams, at = shingle_hashes(span_hashes(data, first, end), texts, k)
    bare = np.flatnonzero((np.diff(texts) == 0) & (np.diff(offsets) > 0))
    if len(bare):
        grams = np.insert(grams, at[bare], span_hashes(data, offsets[bare], offsets[bare + 1]))
        at = at + np.concatenate([[0], np.cumsum(np.isin(np.arange(len(texts) - 1), bare))])
    return grams, at


def signatures(column: pa.Array, size: int = SIZE, seed: int = SEED) -> np.ndarray:
    """(texts, size) 16-bit components; those of an empty text are all 65535."""
    a, b = permutations(size, seed)
    out = np.full((len(column), size), 0xFFFF, np.uint16)
    for begin, to in slices(column):
        grams, at = shingles_of(column.slice(begin, to - begin))
        some = np.flatnonzero(np.diff(at))
        if not len(some):
            continue
        for j in range(size):
            least = np.minimum.reduceat(grams * a[j] + b[j], at[some])
            out[begin + some, j] = mix(least).astype(np.uint16)
    return out


def in_bytes(signature: np.ndarray) -> bytes:
    return signature.astype(">u2").tobytes()


def likeness(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Share of equal components, row by row."""
    return (a == b).mean(axis=1)


def edited(text: str, after: str) -> str:
    """The last half of the code points (rounded down) gives way to the first as many of ``after``, or all."""
    n = len(text) // 2
    return text[: len(text) - n] + after[:n]


def in_order(docs: DataFrame) -> DataFrame:
    """Rows in buckets of consecutive doc_ids, each followed by the row after it (``ahead``), the last bucket by the first row.

    Bounds of buckets are quantiles, four buckets a shuffle partition; only bounds and each bucket's least doc_id reach the
    driver, and both lists are as long as there are buckets. Null doc_ids come first, ties go by text.
    """
    spark = docs.sparkSession
    rows = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(LEAST)).alias("key"), "doc_id", text_of().alias("text"))
    n = 4 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    bounds = rows.select(F.percentile_approx("key", [k / n for k in range(1, n)], 20 * n)).first()[0] or []
    bounds = sorted(set(bounds))
    placed = rows.withColumn("bounds", F.lit(bounds or [0])).withColumn("bucket", place(len(bounds))).drop("bounds")
    firsts = sorted((r["bucket"], r["key"]) for r in placed.groupBy("bucket").agg(F.min("key").alias("key")).collect())
    before = [(key, firsts[k - 1][0]) for k, (_, key) in enumerate(firsts)]
    ahead = spark.createDataFrame(before, "key long, before int")
    both = placed.join(F.broadcast(ahead), "key", "left")
    copies = F.when(F.col("before").isNull(), F.array(F.struct("bucket", F.lit(False).alias("ahead")))).otherwise(F.array(F.struct("bucket", F.lit(False).alias("ahead")), F.struct(F.col("before").alias("bucket"), F.lit(True).alias("ahead"))))
    out = both.select("key", "doc_id", "text", F.explode(copies).alias("at")).select(F.col("at.bucket").alias("bucket"), F.col("at.ahead").alias("ahead"), "key", "doc_id", "text")
    return out.repartition(n // 4, "bucket").sortWithinPartitions("bucket", "ahead", "key", "text")


def place(n: int):
    """Number of bounds below the key, by halving."""
    steps = n.bit_length()
    expr = "0"
    for k in range(steps - 1, -1, -1):
        expr = f"transform(array({expr}), q -> q + if(q + {1 << k} <= {n} and element_at(bounds, least(q + {1 << k}, {n})) < key, {1 << k}, 0))[0]"
    return F.expr(f"cast({expr} as int)")


def fingerprint_table(docs: DataFrame, size: int = SIZE, seed: int = SEED) -> DataFrame:
    """``fingerprint_bytes`` with hashes and fingerprints in lower-case hex."""
    return spelled(fingerprint_bytes(docs, size, seed))


def spelled(rows: DataFrame) -> DataFrame:
    return rows.withColumns({c: F.lower(F.hex(c)) for c in ("edited_sha256", "fingerprint", "edited_fingerprint")})


def fingerprint_bytes(docs: DataFrame, size: int = SIZE, seed: int = SEED) -> DataFrame:
    """Fingerprints of every text, of its edited text, and their likeness to each other and to the next document's.

    The next document is that of the next doc_id, after the last the first; a single document follows itself. Null text is
    empty, and two empty texts are alike (1.0). Rows with null doc_id come before all others; equal doc_ids go by text.
    No rows give no rows; columns other than doc_id and text are ignored.
    """
    schema = "doc_id long, n_chars long, edited_sha256 binary, fingerprint binary, edited_fingerprint binary, near_edited double, near_next double"
    names = [x.split()[0] for x in schema.split(", ")]

    def described(rows: list[tuple], after: str) -> pa.RecordBatch:
        """Rows (doc_id, text) that follow each other, and the text after the last."""
        texts = [x[1] for x in rows] + [after]
        changed = [edited(a, b) for a, b in zip(texts, texts[1:], strict=False)]
        own, other = signatures(pa.array(texts, pa.large_string()), size, seed), signatures(pa.array(changed, pa.large_string()), size, seed)
        return pa.RecordBatch.from_arrays([
            pa.array([x[0] for x in rows], pa.int64()), pa.array([len(x[1]) for x in rows], pa.int64()), pa.array([hashlib.sha256(x.encode()).digest() for x in changed]),
            pa.array([in_bytes(x) for x in own[:-1]]), pa.array([in_bytes(x) for x in other]), pa.array(likeness(own[:-1], other)), pa.array(likeness(own[:-1], own[1:])),
        ], names=names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        bucket, closed, weight = None, False, 0
        for batch in batches:
            for b, ahead, doc, text in zip(*(batch.column(k) for k in (0, 1, 3, 4)), strict=True):
                b, ahead, doc, text = b.as_py(), ahead.as_py(), doc.as_py(), text.as_py()
                if b != bucket:
                    bucket, closed = b, False
                if closed:
                    continue
                if ahead:
                    yield described(held, text)
                    held, closed, weight = [], True, 0
                elif weight > 1 << 21:
                    yield described(held, text)
                    held, weight = [(doc, text)], len(text)
                else:
                    held.append((doc, text))
                    weight += len(text)

    return in_order(docs).mapInArrow(run, schema)


def near_pairs(docs: DataFrame, threshold: float = 0.8, size: int = SIZE, bands: int = BANDS, seed: int = SEED) -> DataFrame:
    """Classes of documents whose runs of five words have Jaccard similarity ``threshold`` or more: (doc_id, class_id).

    Signature bands are joined in Spark, and candidate pairs verified on the texts' runs; see ``linking``.
    """
    rows = size // bands
    schema = "doc_id long, key string, bands array<long>"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = batch.column(1)
            signed = signatures(column, size, seed).reshape(len(column), bands, rows).astype(U64)
            total = np.broadcast_to(np.arange(bands, dtype=U64), signed.shape[:2])
            for j in range(rows):
                total = mix(total * U64(65_537) + signed[:, :, j])
            keys = [hashlib.sha256(x.as_py().encode()).hexdigest() for x in column]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(keys), pa.array(list(total.view(np.int64)), pa.list_(pa.int64()))], names=["doc_id", "key", "bands"])

    signed = materialise(docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of().alias("text")).mapInArrow(run, schema), "minhash")
    return classes(signed, lambda pairs, texts: verified_jaccard(pairs, texts, threshold, weighted=False), docs, lambda texts: partner_sizes(texts, threshold, weighted=False))


def fingerprints_and_classes(docs: DataFrame, threshold: float = 0.8, size: int = SIZE, bands: int = BANDS, seed: int = SEED) -> DataFrame:
    """``fingerprint_table`` with class_id, the least doc_id of the near-duplicates that bands and verification find (``near_pairs``); null for a null doc_id.

    Rows are joined as bytes, half as long as hex, and spelled out after the join.
    """
    found = near_pairs(docs, threshold, size, bands, seed).filter("doc_id is not null").groupBy("doc_id").agg(F.min("class_id").alias("class_id"))
    return spelled(fingerprint_bytes(docs, size, seed).join(found, "doc_id", "left"))
