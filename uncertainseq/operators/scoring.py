"""Expected supports of many patterns: five scorers with one meaning.

``packed``: one scan of whole sequences as sparse arrays (``passes.score_packed``), a trie level at a time. ``trie``: one scan; each Arrow batch walks the shared-prefix trie depth first over dense arrays (rows x events), a running
maximum for a new event. ``fold``: one column expression a pattern. ``levels``: sparse rows a trie level, a window for the
running maximum. ``pairwise``: as levels, with all position pairs of a sequence, the quadratic way of the prior miner.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from uncertainseq.functions.sequences import best_match
from uncertainseq.model import Pattern, PatternTrie
from uncertainseq.operators.passes import pack, score_packed

CELLS = 1 << 18
FOLD_MOST = 40


def expected_supports(db: DataFrame, patterns: list[Pattern], scorer: str = "auto", flat: DataFrame | None = None, packed: DataFrame | None = None) -> dict[Pattern, float]:
    """Support of each pattern in the nested database ``db``; ``levels`` and ``pairwise`` read ``flat``, ``packed`` the rows that ``pack`` or ``blocked`` gives."""
    if not patterns:
        return {}
    if scorer == "auto":
        scorer = "packed" if packed is not None else "fold" if len(patterns) <= FOLD_MOST and max(p.n_items for p in patterns) <= 3 else "trie"
    if scorer == "fold":
        return score_fold(db, patterns)
    trie = PatternTrie(patterns)
    nodes = dict(trie.walk())
    if scorer == "trie":
        rows = score_trie(db, trie)
    elif scorer == "packed":
        rows = score_packed(packed if packed is not None else pack(flat), trie)
    elif scorer in ("levels", "pairwise"):
        rows = score_levels(flat, trie, quadratic=scorer == "pairwise")
    else:
        raise ValueError("scorer is auto, packed, fold, trie, levels or pairwise")
    found = {r["node"]: r["support"] for r in rows.collect()}  # a row a pattern
    return {p: found.get(n, 0.0) for n, p in nodes.items()}


def score_fold(db: DataFrame, patterns: list[Pattern]) -> dict[Pattern, float]:
    row = db.agg(*[F.coalesce(F.sum(best_match(p)), F.lit(0.0)).alias(f"s{k}") for k, p in enumerate(patterns)]).first()
    return dict(zip(patterns, row, strict=True))


def dense(events: pa.Array, items: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(row, event, slot, p) of the items of interest, from a column of events."""
    lengths = np.asarray(events.value_lengths().fill_null(0))
    inner = events.flatten()
    counts = np.asarray(inner.value_lengths().fill_null(0))
    leaf = inner.flatten()
    item, p = leaf.field("item_id").to_numpy(zero_copy_only=False), leaf.field("p").to_numpy(zero_copy_only=False)
    row_of_event = np.repeat(np.arange(len(lengths)), lengths)
    place = np.arange(len(counts)) - np.repeat(np.concatenate([[0], np.cumsum(lengths)[:-1]]), lengths)
    slot = np.searchsorted(items, item)
    known = (slot < len(items)) & (items[np.minimum(slot, len(items) - 1)] == item)
    return np.repeat(row_of_event, counts)[known], np.repeat(place, counts)[known], slot[known], p[known]


def walk(children: dict, terminal: set, slots: dict[int, int], row: np.ndarray, place: np.ndarray, slot: np.ndarray, p: np.ndarray, n: int, wide: int, out: dict[int, float]) -> None:
    """Add the supports of n sequences of at most ``wide`` events to ``out``."""
    order = np.argsort(slot, kind="stable")
    row, place, slot, p = row[order], place[order], slot[order], p[order]
    bounds = np.searchsorted(slot, np.arange(len(slots) + 1))

    def matrix(item: int) -> np.ndarray | None:
        a, b = bounds[slots[item]], bounds[slots[item] + 1]
        if a == b:
            return None
        m = np.zeros((n, wide))
        np.maximum.at(m, (row[a:b], place[a:b]), p[a:b])
        return m

    matrices: dict[int, np.ndarray | None] = {}
    stack: list[tuple[int, np.ndarray | None]] = [(0, None)]
    while stack:
        node, own = stack.pop()
        before = None
        for (item, kind), child in children[node].items():
            if item not in matrices:
                matrices[item] = matrix(item)
            m = matrices[item]
            if m is None:
                continue
            if own is None:
                value = m
            elif kind == "i":
                value = own * m
            else:
                if before is None:
                    before = np.zeros_like(own)
                    np.maximum.accumulate(own[:, :-1], axis=1, out=before[:, 1:])
                value = before * m
            best = value.max(axis=1)
            total = float(best.sum())
            if total == 0:
                continue
            if child in terminal:
                out[child] = out.get(child, 0.0) + total
            if children[child]:
                stack.append((child, value))


def score_trie(db: DataFrame, trie: PatternTrie) -> DataFrame:
    """(node, support): one scan of ``db``, one row a node and task, then a sum."""
    children, terminal = trie.children, trie.terminal
    items = np.array(sorted({x for c in children.values() for x, _ in c}), np.int64)
    slots = {int(x): k for k, x in enumerate(items)}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, float] = {}
        for batch in batches:
            events = batch.column(0)
            lengths = np.asarray(events.value_lengths().fill_null(0))
            order = np.argsort(lengths, kind="stable")  # rows of like length together, so padding is bounded
            at = 0
            while at < len(order):
                to = at + 1
                while to < len(order) and (to + 1 - at) * max(1, lengths[order[to]]) <= CELLS:
                    to += 1
                wide = int(lengths[order[to - 1]])
                if wide:
                    walk(children, terminal, slots, *dense(events.take(pa.array(order[at:to])), items), to - at, wide, sums)
                at = to
        yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int64()), pa.array(list(sums.values()), pa.float64())], names=["node", "part"])

    return db.select("events").mapInArrow(run, "node long, part double").groupBy("node").agg(F.sum("part").alias("support"))


def score_levels(flat: DataFrame, trie: PatternTrie, quadratic: bool = False) -> DataFrame:
    """(node, support) by one join a level; rows (sequence, node, event, best probability ending there)."""
    spark = flat.sparkSession
    edges = trie.to_edges()
    table = spark.createDataFrame(edges, "node long, parent long, item_id int, kind string, depth int, terminal boolean")
    rows = flat.select("seq_id", "eid", "item_id", "p")
    state, sums = None, []
    for depth in range(1, max(e[4] for e in edges) + 1):
        level = F.broadcast(table.filter(F.col("depth") == depth).select("node", "parent", "item_id", "kind"))
        if state is None:
            state = rows.join(level, "item_id").select("seq_id", "node", "eid", F.col("p").alias("v"))
        else:
            old = state.select("seq_id", F.col("node").alias("parent"), "eid", "v")
            joined = old.filter("v > 0").join(level.filter("kind = 'i'"), "parent").join(rows, ["seq_id", "eid", "item_id"]).select("seq_id", "node", "eid", (F.col("v") * F.col("p")).alias("v"))
            later = rows.select("seq_id", F.col("eid").alias("at"), "item_id", "p")
            if quadratic:
                pairs = old.join(level.filter("kind = 's'"), "parent").join(later, ["seq_id", "item_id"]).filter("at > eid")
                opened = pairs.groupBy("seq_id", "node", "at").agg(F.max(F.col("v") * F.col("p")).alias("v")).withColumnRenamed("at", "eid")
            else:
                ahead = Window.partitionBy("seq_id", "parent").orderBy("eid").rowsBetween(Window.unboundedPreceding, Window.currentRow)
                until = old.withColumn("v", F.max("v").over(ahead)).withColumn("next", F.lead("eid").over(Window.partitionBy("seq_id", "parent").orderBy("eid")))
                opened = until.join(level.filter("kind = 's'"), "parent").join(later, ["seq_id", "item_id"]).filter("at > eid and (next is null or at <= next)").select("seq_id", "node", F.col("at").alias("eid"), (F.col("v") * F.col("p")).alias("v"))
            state = joined.unionByName(opened)
        sums.append(state.groupBy("node", "seq_id").agg(F.max("v").alias("v")).groupBy("node").agg(F.sum("v").alias("support")))
    out = sums[0]
    for s in sums[1:]:
        out = out.unionByName(s)
    return out.join(F.broadcast(table.filter("terminal").select("node")), "node")


def node_visits(flat: DataFrame, items: int) -> DataFrame:
    """(events, sequences, linear, pairwise) by length of sequence, for all patterns of two events of one of ``items`` items each.

    linear: nodes times events, what a walk of the trie visits; pairwise: occurrences, and pairs of them with the second in a later event.
    Pairs are counted by running sums, not made.
    """
    by_event = flat.groupBy("seq_id", "eid").agg(F.count("*").alias("held"))
    until = Window.partitionBy("seq_id").orderBy("eid").rowsBetween(Window.unboundedPreceding, -1)
    before = by_event.withColumn("before", F.coalesce(F.sum("held").over(until), F.lit(0)))
    whole = before.groupBy("seq_id").agg(F.count("*").alias("events"), F.sum(F.col("held") * (F.col("before") + 1)).alias("pairs"))
    counted = whole.groupBy("events").agg(F.count("*").alias("sequences"), F.sum("pairs").alias("pairwise"))
    return counted.select("events", "sequences", (F.col("events") * F.col("sequences") * (items + items * items)).alias("linear"), "pairwise")
