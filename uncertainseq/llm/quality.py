"""Quality scores from document statistics: random Fourier features, ridge by summed normal equations, isotonic calibration.

Statistics of a text (sizes, shares of kinds of bytes, repetition of words, of runs and of lines) are standardised and
mapped to cosines at random frequencies, whose products approximate a Gaussian kernel. Partitions send sums of their
normal equations by fold; folds solved without themselves give the scores on which an isotonic curve is fitted. Fitting
uses at most ``bound`` labelled rows, chosen by a hash of doc_id; scoring covers all documents in the pass that reads them.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from uncertainseq.llm.common import fresh, materialise, text_of
from uncertainseq.llm.textnp import shingle_hashes, slices, span_hashes, string_bytes, word_spans

FREQUENCIES, WIDTH, RIDGE, FOLDS, BOUND, SEED, BINS, TASKS = 256, 6.0, 1.0, 5, 20_000, 2, 400, 8
KINDS = ("upper", "lower", "digit", "wide", "space", "line", "stop", "mark", "bracket", "symbol")
# The bytes of each kind; "wide" is all bytes of characters beyond ASCII.
BYTES = {
    "upper": b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", "lower": b"abcdefghijklmnopqrstuvwxyz", "digit": b"0123456789", "wide": bytes(range(128, 256)),
    "space": b" \t\r", "line": b"\n", "stop": b".,;:", "mark": b"!?", "bracket": b"()[]{}<>\"'", "symbol": b"#$%&*+-/=@\\^_`|~",
}
STATISTICS = ("log_bytes", "log_words", "word_length", *KINDS, "distinct_words", "distinct_runs", "line_length", "distinct_lines", "words_a_line", "longest_word", "bare_words")
_kind = np.full(256, len(KINDS), np.int64)
for _i, _name in enumerate(KINDS):
    _kind[list(BYTES[_name])] = _i


def distinct(hashes: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Number of distinct hashes in each text."""
    texts = np.repeat(np.arange(len(at) - 1), np.diff(at))
    order = np.lexsort((hashes, texts))
    h, t = hashes[order], texts[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (t[1:] != t[:-1])
    return np.bincount(t[new], minlength=len(at) - 1)


def statistics(column: pa.Array) -> np.ndarray:
    """(texts, statistics); an empty text has zeros."""
    out = np.zeros((len(column), len(STATISTICS)))
    for begin, to in slices(column):
        data, at = string_bytes(column.slice(begin, to - begin))
        n = len(at) - 1
        size = np.diff(at)
        counts = np.zeros((n, len(KINDS) + 1))
        sums = np.zeros(len(data) + 1, np.int64)
        kinds = _kind[data]
        for k in range(len(KINDS)):
            np.cumsum(kinds == k, out=sums[1:])
            counts[:, k] = sums[at[1:]] - sums[at[:-1]]
        first, end, texts = word_spans(data, at)
        words = span_hashes(data, first, end)
        number = np.diff(texts)
        runs, runs_at = shingle_hashes(words, texts)
        breaks = np.flatnonzero(data == 10)
        starts = np.sort(np.concatenate([at[:-1][size > 0], breaks[~np.isin(breaks + 1, at)] + 1]))
        ends = np.append(starts[1:], len(data))
        lines = span_hashes(data, starts, ends) if len(starts) else np.zeros(0, np.uint64)
        line_texts = np.searchsorted(starts, at)
        n_lines = np.maximum(np.diff(line_texts), 1)
        length = end - first
        longest = np.zeros(n)
        some = number > 0
        if some.any():
            longest[some] = np.maximum.reduceat(length, texts[:-1][some])
        after = np.append(data, 32)[end]
        plain = np.concatenate([[0], np.cumsum((after == 32) | (after == 10))])
        safe, w = np.maximum(size, 1), np.maximum(number, 1)
        out[begin:to] = np.column_stack([
            np.log1p(size), np.log1p(number), np.bincount(np.repeat(np.arange(n), number), length, n) / w, *(counts[:, k] / safe for k in range(len(KINDS))),
            distinct(words, texts) / w, distinct(runs, runs_at) / np.maximum(np.diff(runs_at), 1), np.log1p(size / n_lines), distinct(lines, line_texts) / n_lines, np.log1p(number / n_lines), np.log1p(longest), (plain[texts[1:]] - plain[texts[:-1]]) / w,
        ])
        out[begin:to][size == 0] = 0
    return out


def fourier(x: np.ndarray, frequencies: np.ndarray, phases: np.ndarray) -> np.ndarray:
    """Cosine features and a constant."""
    return np.column_stack([np.cos(x @ frequencies + phases) * np.sqrt(2 / frequencies.shape[1]), np.ones(len(x))])


def isotonic(x: np.ndarray, y: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Knots of the non-decreasing curve nearest to means y of n rows at ascending x: pools of adjacent violators, at their mean x."""
    pools: list[list[float]] = []
    for a, b, c in zip(x, y, n, strict=True):
        pools.append([a * c, b * c, c])
        while len(pools) > 1 and pools[-2][1] * pools[-1][2] >= pools[-1][1] * pools[-2][2]:
            last = pools.pop()
            pools[-1] = [u + v for u, v in zip(pools[-1], last, strict=True)]
    return np.array([p[0] / p[2] for p in pools]), np.array([p[1] / p[2] for p in pools])


@dataclass
class Model:
    mean: np.ndarray
    scale: np.ndarray
    frequencies: np.ndarray
    phases: np.ndarray
    weights: np.ndarray
    knots: np.ndarray
    values: np.ndarray

    def raw(self, x: np.ndarray) -> np.ndarray:
        return fourier(np.clip((x - self.mean) / self.scale, -8, 8), self.frequencies, self.phases) @ self.weights

    def __call__(self, x: np.ndarray) -> np.ndarray:
        return np.clip(np.interp(self.raw(x), self.knots, self.values), 0, 1) if len(self.knots) > 1 else np.full(len(x), self.values[0])


def held_out(doc_id) -> F.Column:
    return F.pmod(F.crc32(F.col(doc_id).cast("string").cast("binary")), F.lit(3)) == 1


def training_rows(docs: DataFrame, labels: DataFrame, label: str, bound: int) -> DataFrame:
    """(doc_id, text, y): labelled documents outside the held-out third, at most ``bound``, those of the least hashes."""
    known = labels.filter(F.col(label).isin(0, 1)).groupBy("doc_id").agg(F.max(label).alias("y")).filter(~held_out("doc_id"))
    chosen = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(bound)
    return docs.select("doc_id", text_of().alias("text")).join(F.broadcast(chosen), "doc_id")


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", bound: int = BOUND, size: int = FREQUENCIES, width: float = WIDTH, ridge: float = RIDGE, seed: int = SEED) -> Model:
    """A model of ``label``; without rows of both classes its scores are the rows' mean, 0.5 without rows."""
    d = len(STATISTICS)

    def measured(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([zlib.crc32(str(x).encode()) // 3 % FOLDS for x in b.column(0)], pa.int32()), b.column(2).cast(pa.float64()), pa.array(list(statistics(b.column(1))), pa.list_(pa.float64()))], names=["fold", "y", "x"])

    rows = materialise(training_rows(docs, labels, label, bound).select("doc_id", "text", "y").mapInArrow(measured, "fold int, y double, x array<double>"), "statistics")
    sums = rows.agg(F.count("*").alias("n"), F.sum("y").alias("y"), *[f(F.get("x", F.lit(i))).alias(f"{k}{i}") for k, f in (("m", F.avg), ("s", F.stddev_pop)) for i in range(d)]).first()
    rng = np.random.default_rng(seed)
    frequencies, phases = rng.normal(size=(d, size)) / width, rng.uniform(0, 2 * np.pi, size)
    flat = Model(np.zeros(d), np.ones(d), frequencies, phases, np.zeros(size + 1), np.zeros(1), np.array([sums["y"] / sums["n"] if sums["n"] else 0.5]))
    if not sums["n"] or sums["y"] in (0, sums["n"]):
        return flat
    mean, scale = np.array([sums[f"m{i}"] for i in range(d)]), np.array([sums[f"s{i}"] or 1.0 for i in range(d)])
    model = Model(mean, np.where(scale > 1e-9, scale, 1), frequencies, phases, np.zeros(size + 1), np.zeros(1), np.zeros(1))

    def matrix(b: pa.RecordBatch) -> np.ndarray:
        x = np.array(b.column(2).to_pylist()).reshape(-1, d)
        return fourier(np.clip((x - model.mean) / model.scale, -8, 8), frequencies, phases)

    def normal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        left, right = np.zeros((FOLDS, size + 1, size + 1)), np.zeros((FOLDS, size + 1))
        for b in batches:
            z, y, fold = matrix(b), b.column(1).to_numpy(), b.column(0).to_numpy()
            for k in range(FOLDS):
                left[k] += z[fold == k].T @ z[fold == k]
                right[k] += z[fold == k].T @ y[fold == k]
        yield pa.RecordBatch.from_arrays([pa.array(range(FOLDS), pa.int32()), pa.array([x.tobytes() for x in left]), pa.array([x.tobytes() for x in right])], names=["fold", "xx", "xy"])

    left, right = np.zeros((FOLDS, size + 1, size + 1)), np.zeros((FOLDS, size + 1))
    for r in rows.coalesce(TASKS).mapInArrow(normal, "fold int, xx binary, xy binary").toLocalIterator():  # FOLDS rows from each of TASKS tasks at most
        left[r["fold"]] += np.frombuffer(r["xx"]).reshape(size + 1, -1)
        right[r["fold"]] += np.frombuffer(r["xy"])
    solve = lambda a, b: np.linalg.solve(a + ridge * np.diag(np.append(np.ones(size), 1e-6)), b)
    without = [solve(left.sum(0) - left[k], right.sum(0) - right[k]) for k in range(FOLDS)]

    def out_of_fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            z, fold = matrix(b), b.column(0).to_numpy()
            scores = np.einsum("ij,ij->i", z, np.array(without)[fold])
            yield pa.RecordBatch.from_arrays([pa.array(np.round(np.clip(scores, -1, 2) * BINS).astype(np.int32)), b.column(1)], names=["bin", "y"])

    bins = sorted(tuple(r) for r in rows.mapInArrow(out_of_fold, "bin int, y double").groupBy("bin").agg(F.avg("y"), F.count("*")).collect())  # 3 BINS + 1 rows at most
    knots, values = isotonic(*(np.array(x, float) for x in zip(*[(b / BINS, y, n) for b, y, n in bins], strict=True)))
    model.weights, model.knots, model.values = solve(left.sum(0), right.sum(0)), knots, values
    return model


def score(docs: DataFrame, model: Model, keep: list[str] | None = None, names: tuple[str, str] = ("score", "predicted")) -> DataFrame:
    """The columns ``keep`` (doc_id), and score and predicted under ``names``, of every row, in the pass that reads them."""
    keep = keep or ["doc_id"]
    text = fresh(docs, "text")
    source = docs.select(*keep, text_of().alias(text))
    schema = source.drop(text).withColumns({names[0]: F.lit(0.0), names[1]: F.lit(0)}).schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            s = model(statistics(b.column(len(keep))))
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(s), pa.array((s >= 0.5).astype(np.int32))], names=[*keep, *names])

    return source.mapInArrow(run, schema)


def quality_table(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every document.

    Null text is empty, and empty texts have a score. Null doc_ids are scored, never learned from, and not held out. Labels
    other than 0 and 1 are ignored; of several labels of a doc_id the largest counts. No rows give no rows.
    """
    scored = score(docs, fit(docs, labels, **options))
    return scored.select("doc_id", F.coalesce(held_out("doc_id"), F.lit(False)).alias("held_out"), "score", "predicted")


def keep_good(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """The documents that the classifier does not reject, with their columns."""
    names = (fresh(docs, "score"), fresh(docs, "predicted"))
    return score(docs, fit(docs, labels, **options), docs.columns, names).filter(F.col(names[1]) == 1).select(docs.columns)
