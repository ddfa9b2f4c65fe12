"""Toxicity categories by a classifier chain.

Links are linear (logistic) models over the presence of vocabulary terms and a few sums. A term is a word or the first
4 to 7 bytes of one, so inflected forms share terms. The vocabulary is learned: the terms whose presence in the labelled documents tells toxic ones from others best, by log-likelihood ratio, counted over
all rows of the training sample. Categories come in a fixed order, toxicity last; each link also sees the probabilities of
the links before it. For training those are out-of-fold predictions, as at scoring time a link's inputs are predictions
too. A category's label is the toxic label together with a word of that category.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from uncertainseq.llm.common import materialise, text_of
from uncertainseq.llm.quality import held_out, training_rows
from uncertainseq.llm.textnp import mix, slices, span_hashes, string_bytes, word_spans

# Words that place a toxic document in a category; toxicity itself is learned from labels alone.
CATEGORIES = {
    "insult": "idiot idiots moron morons fool clown clowns stupid imbecile dumb loser losers jerk",
    "contempt": "worthless pathetic disgusting trash scum garbage vermin filth filthy useless vile",
    "threat": "kill die hurt destroy beat attack burn shoot hang stab",
}
CHAIN = (*CATEGORIES, "toxic")
BOUND, VOCABULARY, LEAST, FOLDS, RIDGE, STEPS = 20_000, 128, 5, 5, 1.0, 8
PREFIXES = (4, 5, 6, 7)


def terms(column: pa.Array) -> tuple[list[tuple[np.ndarray, np.ndarray]], np.ndarray]:
    """Pairs (hashes, text of each), one of whole words and one for each length of prefix; and the number of words of each text."""
    data, offsets = string_bytes(column)
    first, end, at = word_spans(data, offsets)
    texts = np.repeat(np.arange(len(at) - 1), np.diff(at))
    out = [(span_hashes(data, first, end), texts)]
    for n in PREFIXES:
        some = end - first >= n
        out.append((mix(span_hashes(data, first[some], first[some] + n) + np.uint64(n)), texts[some]))
    return out, np.diff(at)


def hash_words(words: list[str]) -> np.ndarray:
    return terms(pa.array([" ".join(words)]))[0][0][0]


@dataclass
class Chain:
    vocabulary: np.ndarray  # ascending hashes
    weights: list[np.ndarray]

    def probabilities(self, x: np.ndarray) -> np.ndarray:
        """(texts, links) for features x: each link after those before it."""
        out = np.zeros((len(x), len(self.weights)))
        for k, w in enumerate(self.weights):
            out[:, k] = sigmoid(np.column_stack([x, out[:, :k]]) @ w)
        return out


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


def features(column: pa.Array, vocabulary: np.ndarray) -> np.ndarray:
    """(texts, vocabulary + 3): presence of each term, a logarithm of how many of them there are, one of the words, a constant."""
    n = len(vocabulary)
    out = np.zeros((len(column), n + 3))
    out[:, -1] = 1
    for begin, to in slices(column):
        found, number = terms(column.slice(begin, to - begin))
        out[begin:to, n + 1] = np.log1p(number) / 10
        if not n:
            continue
        total = np.zeros(to - begin)
        for hashes, texts in found:
            place = np.minimum(np.searchsorted(vocabulary, hashes), n - 1)
            hit = vocabulary[place] == hashes
            out[begin + texts[hit], place[hit]] = 1
            total += np.bincount(texts[hit], minlength=to - begin)
        out[begin:to, n] = np.log1p(total)
    return out


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = RIDGE, steps: int = STEPS) -> np.ndarray:
    """Weights of a ridge-penalised logistic regression by Newton's steps; the last column of x but for chain inputs is not special."""
    w = np.zeros(x.shape[1])
    penalty = ridge * np.eye(x.shape[1])
    for _ in range(steps):
        p = sigmoid(x @ w)
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + penalty, x.T @ (y - p) - ridge * w)
        w = w + step
        if np.abs(step).max() < 1e-4:
            break
    return w


def fit(docs: DataFrame, labels: DataFrame, label: str = "toxic", bound: int = BOUND, size: int = VOCABULARY) -> Chain:
    """A chain fitted on at most ``bound`` labelled documents outside the held-out third. Without both classes every link gives the share of 1 or 0.5."""
    rows = training_rows(docs, labels, label, bound)

    def unique(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lists = []
            for begin, to in slices(b.column(1)):
                found, number = terms(b.column(1).slice(begin, to - begin))
                hashes, texts = (np.concatenate(x) for x in zip(*found, strict=True))
                order = np.argsort(texts, kind="stable")
                at = np.searchsorted(texts[order], np.arange(len(number) + 1))
                lists += [np.unique(hashes[order[i:j]]).view(np.int64) for i, j in zip(at, at[1:], strict=False)]
            yield pa.RecordBatch.from_arrays([pa.array([zlib.crc32(str(x).encode()) // 3 % FOLDS for x in b.column(0)], pa.int32()), b.column(2).cast(pa.int64()), pa.array(lists, pa.list_(pa.int64())), b.column(1)], names=["fold", "y", "words", "text"])

    held = materialise(rows.select("doc_id", "text", "y").mapInArrow(unique, "fold int, y long, words array<long>, text string"), "toxic-rows")
    total = held.agg(F.count("*").alias("n"), F.sum("y").alias("y")).first()
    n, positive = total["n"], total["y"] or 0
    if not n or positive in (0, n):
        share = positive / n if n else 0.5
        bias = np.log((share + 1e-6) / (1 - share + 1e-6))
        return Chain(np.zeros(0, np.uint64), [np.concatenate([[0, 0, bias], np.zeros(k)]) for k in range(len(CHAIN))])
    counts = held.select("y", F.explode("words").alias("word")).groupBy("word").agg(F.sum("y").alias("a"), F.count("*").alias("c"))
    part = lambda k, e: F.when(k > 0, k * F.log(k / e)).otherwise(0.0)
    a, b = F.col("a").cast("double"), (F.col("c") - F.col("a")).cast("double")
    ratio = part(a, F.col("c") * (positive / n)) + part(b, F.col("c") * (1 - positive / n))
    telling = counts.filter((F.col("a") >= LEAST) & (a / F.col("c") > 2 * positive / n)).orderBy(ratio.desc(), "word").limit(size)
    known = hash_words([w for words in CATEGORIES.values() for w in words.split()])
    vocabulary = np.unique(np.concatenate([np.array([r["word"] for r in telling.collect()], np.int64).view(np.uint64), known]))
    sets = [hash_words(words.split()) for words in CATEGORIES.values()]

    def prepared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = features(batch.column(2), vocabulary).astype(np.float32)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([r.tobytes() for r in x], pa.binary())], names=["fold", "y", "x"])

    sample = held.select("fold", "y", "text").mapInArrow(prepared, "fold int, y long, x binary").toPandas()  # ``bound`` rows of fixed size at most
    x = np.stack([np.frombuffer(v, np.float32) for v in sample["x"]]).astype(float)
    fold, toxic = sample["fold"].to_numpy(), sample["y"].to_numpy()
    goals = [toxic * x[:, :-3][:, np.isin(vocabulary, s)].any(axis=1) for s in sets] + [toxic]
    before = np.zeros((len(x), 0))
    weights = []
    for goal in goals:
        z, goal = np.column_stack([x, before]), np.asarray(goal, float)
        weights.append(logistic(z, goal))
        blind = np.zeros(len(x))
        for k in range(FOLDS):
            out = fold == k
            if out.any():
                blind[out] = sigmoid(z[out] @ (logistic(z[~out], goal[~out]) if (~out).any() else weights[-1]))
        before = np.column_stack([before, blind])
    return Chain(vocabulary, weights)


def toxicity_table(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """(doc_id, held_out, a probability for each link, score, predicted) of every document; score is the last link's.

    Null text is empty. Null doc_ids are scored, never learned from. Labels other than 0 and 1 are ignored; of several
    labels of a doc_id the largest counts. No rows give no rows; other columns are ignored.
    """
    chain = fit(docs, labels, **options)
    names = [f"p_{c}" for c in CHAIN]
    source = docs.select("doc_id", text_of().alias("text"))
    schema = source.drop("text").withColumns({c: F.lit(0.0) for c in [*names, "score"]} | {"predicted": F.lit(0)}).schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                part = batch.slice(at, 1000)
                p = chain.probabilities(features(part.column(1), chain.vocabulary))
                yield pa.RecordBatch.from_arrays([part.column(0), *(pa.array(c) for c in p.T), pa.array(p[:, -1]), pa.array((p[:, -1] >= 0.5).astype(np.int32))], names=["doc_id", *names, "score", "predicted"])

    scored = source.mapInArrow(run, schema)
    return scored.withColumn("held_out", F.coalesce(held_out("doc_id"), F.lit(False)))
