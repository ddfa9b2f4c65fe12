"""Exact Jaccard similarity of candidate pairs, on hashes of runs of words."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from uncertainseq.llm.common import discard, materialise
from uncertainseq.llm.textnp import shingle_hashes, word_hashes

#: Parts, a power of two, that bound what two texts share.
PARTS = 32


def verified_jaccard(pairs: DataFrame, texts: DataFrame, threshold: float, weighted: bool, k: int = 5) -> DataFrame:
    """The pairs (a, b) whose runs of k words have (weighted: multiset) Jaccard similarity of at least ``threshold``."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for at in range(0, batch.num_rows, 128):
                part = batch.slice(at, 128)
                grams, bounds = shingle_hashes(*word_hashes(pa.concat_arrays([part.column(2).cast(pa.large_string()), part.column(3).cast(pa.large_string())])), k)
                n = part.num_rows
                for i in range(n):
                    one, two = grams[bounds[i] : bounds[i + 1]], grams[bounds[n + i] : bounds[n + i + 1]]
                    if min(len(one), len(two)) < threshold * max(len(one), len(two)) and weighted:
                        continue
                    if jaccard(one, two, weighted) >= threshold - 1e-12:
                        keep.append(at + i)
            yield pa.RecordBatch.from_arrays([batch.column(k).take(pa.array(keep, pa.int64())) for k in (0, 1)], names=["a", "b"])

    one = pairs.join(texts.select(F.col("doc_id").alias("a"), F.col("text").alias("text_a")), "a")
    two = one.join(texts.select(F.col("doc_id").alias("b"), F.col("text").alias("text_b")), "b")
    return two.select("a", "b", "text_a", "text_b").mapInArrow(run, "a long, b long")


def shared_sizes(texts: DataFrame, weighted: bool, k: int = 5) -> DataFrame:
    """(id, size, common, parts) of texts (doc_id, text): the number of runs of k words, and of those that some other text here has too.

    Runs of one text alone are found by an aggregate on the runs, so a run that all texts share costs a row a partition.
    ``parts`` splits ``common`` by a hash of the run into ``PARTS``; what two texts share is at most the sum over the parts
    of the smaller of both. ``common`` bounds what a text can share with any other one here: see ``partner_sizes``.
    """
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 128):
                part = batch.slice(at, 128)
                grams, bounds = shingle_hashes(*word_hashes(part.column(1).cast(pa.large_string())), k)
                for i in range(part.num_rows):
                    held, n = np.unique(grams[bounds[i] : bounds[i + 1]], return_counts=True)
                    ids = np.full(len(held), part.column(0)[i].as_py(), np.int64)
                    yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(held.view(np.int64)), pa.array((n if weighted else np.ones_like(n)).astype(np.int64))], names=["id", "gram", "n"])

    held = materialise(texts.select("doc_id", "text").mapInArrow(run, "id long, gram long, n long"), "runs")
    alone = held.groupBy("gram").agg(F.count("*").alias("texts"), F.min("id").alias("id"), F.sum("n").alias("n")).filter("texts = 1")
    part = F.col("gram").bitwiseAND(F.lit(PARTS - 1)).cast("int").alias("part")
    both = held.select("id", part, "n", F.col("n").alias("common")).union(alone.select("id", part, F.lit(0).cast("long"), -F.col("n")))
    sums = both.groupBy("id", "part").agg(F.sum("n").alias("n"), F.sum("common").alias("common"))
    whole = sums.groupBy("id").agg(F.sum("n").alias("size"), F.sum("common").alias("common"), F.map_from_entries(F.collect_list(F.struct("part", "common"))).alias("by"))
    parts = F.transform(F.sequence(F.lit(0), F.lit(PARTS - 1)), lambda g: F.coalesce(F.try_element_at("by", g), F.lit(0).cast("long")).cast("int"))
    sized = materialise(whole.select("id", "size", "common", parts.alias("parts")), "shared-sizes")
    discard(held)
    return sized


def partner_sizes(texts: DataFrame, threshold: float, weighted: bool, k: int = 5) -> DataFrame:
    """(id, size, most, half, parts): a text shares at most ``common`` of its runs, so a partner at ``threshold`` has at most ``most`` runs; both must share the sum of their halves."""
    known = shared_sizes(texts, weighted, k)
    most = F.col("common") * ((1 + threshold) / threshold) - F.col("size") + 1e-6
    half = F.col("size") * (threshold / (1 + threshold)) - 1e-6
    return known.select("id", F.col("size").cast("double").alias("size"), most.alias("most"), half.alias("half"), "parts")


def jaccard(one: np.ndarray, two: np.ndarray, weighted: bool) -> float:
    """Jaccard similarity of two collections of hashes, as multisets if ``weighted``; 0 where one is empty."""
    if not len(one) or not len(two):
        return 0.0
    x, n = np.unique(one, return_counts=True)
    y, m = np.unique(two, return_counts=True)
    if not weighted:
        n, m = np.ones_like(n), np.ones_like(m)
    _, i, j = np.intersect1d(x, y, assume_unique=True, return_indices=True)
    shared = np.minimum(n[i], m[j]).sum()
    return float(shared / (n.sum() + m.sum() - shared))


def brute_jaccard(one: str, two: str, weighted: bool, k: int = 5) -> float:
    """The same on words spelled out, for tests."""
    import re

    def runs(text: str) -> Counter:
        words = re.findall(r"[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text))
        return Counter(tuple(words[i : i + k]) for i in range(max(1, len(words) - k + 1))) if words else Counter()

    a, b = runs(one), runs(two)
    a, b = (a, b) if weighted else (Counter(dict.fromkeys(a, 1)), Counter(dict.fromkeys(b, 1)))
    both = (a & b).total()
    return both / ((a | b).total() or 1)
