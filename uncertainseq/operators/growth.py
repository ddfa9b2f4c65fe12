"""Growth of candidate patterns by caps, a level at a time.

A level is one pass over whole sequences (``passes.grown_sums``): only sums a (prefix, extension) are shuffled. Those sums give the caps
where they are; only what survives them reaches the driver, a row a candidate. All match ends count: an item may join an event
that is not the prefix's first match.

Where small projections end in one task (``local_rows``), projections are tables, held by pointers: (prefix, sequence, events where a match of
the prefix ends), joined a level at a time with the flat table, which is hash-partitioned by sequence and kept.
"""

from __future__ import annotations

import time
from dataclasses import dataclass

from py4j.protocol import Py4JJavaError
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F

from uncertainseq.functions.sequences import suffix_max
from uncertainseq.model import EPSILON, Pattern, Stats
from uncertainseq.operators.passes import blocked, grown_sums, pack


@dataclass
class Candidate:
    pattern: Pattern
    peak: float  # peak product of the whole pattern
    support_cap: float
    weight_cap: float
    ident: int

    @property
    def joint_cap(self) -> float:
        return self.support_cap * self.weight_cap


def prepare(flat: DataFrame, partitions: int | None = None) -> DataFrame:
    """Suffix maxima, kept on disk and in memory, partitioned by sequence: the one shuffle of the data."""
    n = partitions or int(flat.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return suffix_max(flat.select("seq_id", "eid", "item_id", "p").repartition(n, "seq_id")).select("seq_id", "eid", "item_id", F.col("later").alias("p")).persist(StorageLevel.MEMORY_AND_DISK)


def extensions(frontier: DataFrame, rows: DataFrame, prefixes: DataFrame) -> DataFrame:
    """(prefix, sequence, kind, item, best, ends) of every extension in every projected sequence."""
    joined = frontier.join(rows, "seq_id").join(prefixes, "prefix")
    opens, joins = F.col("eid") > F.array_min("ends"), F.array_contains("ends", F.col("eid")) & (F.col("item_id") > F.col("last"))
    kinds = F.explode(F.filter(F.array(F.when(opens, F.lit("s")), F.when(joins, F.lit("i"))), lambda k: k.isNotNull()))
    return joined.select("prefix", "seq_id", kinds.alias("kind"), "item_id", "p", "eid").groupBy("prefix", "seq_id", "kind", "item_id").agg(F.max("p").alias("best"), F.collect_list("eid").alias("ends"))


def summed(grown: DataFrame) -> DataFrame:
    """(prefix, kind, item, total, peak, n) over projected sequences."""
    return grown.groupBy("prefix", "kind", "item_id").agg(F.sum("best").alias("total"), F.max("best").alias("peak"), F.count("*").alias("n"))


#: Rows of a few numbers that may be sent to every executor; a larger frontier is joined by a shuffle.
SENT_MOST = 200_000


def sent(rows: list[tuple], schema: str, like: DataFrame) -> DataFrame:
    """A table of the driver's rows, marked for broadcast where they are few enough."""
    made = like.sparkSession.createDataFrame(rows, schema)
    return F.broadcast(made) if len(rows) <= SENT_MOST else made


def capped(known: DataFrame, floor: float, cap: str, top: float | None) -> DataFrame:
    """The extensions whose joint cap reaches ``floor``: (prefix, kind, item_id, peak, support_cap, weight_cap).

    ``known``: their sums with w, parent_peak and parent_weight (the largest in the prefix); ``top``: one weight bound for all, else the
    largest of the prefix's projection.
    """
    heaviest: Column = F.lit(top) if top is not None else F.max("w").over(Window.partitionBy("prefix"))
    part = F.col("total") if cap == "tight" else F.col("peak") * F.col("n")
    caps = known.select(
        "prefix", "kind", "item_id", (F.col("parent_peak") * F.col("peak")).alias("peak"), (F.col("parent_peak") * part).alias("support_cap"),
        F.greatest(heaviest, F.col("parent_weight"), F.col("w")).alias("weight_cap"),
    )
    return caps.filter("kind <> 'w'").filter(F.col("support_cap") * F.col("weight_cap") >= floor - EPSILON)


def observed(seen: Observation) -> int:
    """The rows that ``seen`` counted; of a level without any, Spark drops the count from its plan and has no row to give."""
    try:
        return seen.get["rows"] or 0
    except Py4JJavaError:
        return 0


class FrontierTooLarge(RuntimeError):
    """A level holds more candidates than the caller allows; the answer would not be whole."""


def grown_locally(frontier: DataFrame, rows: DataFrame, level: list[Candidate], most: int, growth, weights: dict[int, float], stats: Stats) -> tuple[set[int], list]:
    """Prefixes of ``level`` whose projections hold at most ``most`` occurrences, and the candidates below them."""
    sizes = frontier.join(rows.groupBy("seq_id").agg(F.count("*").alias("held")), "seq_id").groupBy("prefix").agg(F.sum("held").alias("held"))
    small = {r["prefix"] for r in sizes.filter(F.col("held") <= most).select("prefix").collect()}  # a row a prefix, as in ``level``
    known = [(c.ident, c.pattern.steps[-1][0], c.pattern.n_items, float(c.peak), max(weights[x] for x, _ in c.pattern.steps)) for c in level if c.ident in small]
    if not known:
        return small, []
    table = sent(known, "prefix long, last int, depth int, parent_peak double, parent_weight double", rows)
    stats.local_prefixes += len(known)
    joined = frontier.join(table, "prefix").join(rows, "seq_id")
    return small, joined.groupBy("prefix").applyInPandas(growth, "prefix long, steps string, peak double, support_cap double, weight_cap double").collect()


def grow(flat: DataFrame, weights: dict[int, float], floor: float, cap: str = "tight", weight_mode: str = "projected", max_len: int | None = None, max_frontier: int | None = None, stats: Stats | None = None, local_rows: int = 0, packed: DataFrame | None = None) -> list[Candidate]:
    """All candidates: patterns whose joint cap, and that of every prefix, reaches ``floor``.

    ``cap``: tight (peak of the prefix times the sum of the extension's maxima) or loose (times its peak and count).
    ``weight_mode``: projected, or global for the largest weight of all items. ``max_len`` bounds the items of a
    pattern, and ``stats`` tells where it was met; a level of more than ``max_frontier`` candidates is an error, since no part of it may be left out.
    Prefixes whose projected sequences hold at most ``local_rows`` occurrences together are grown to their end in one task each (0: none).
    ``packed``: the rows of ``flat`` as ``pack`` or ``blocked`` gives them, where the caller keeps these.
    """
    if cap not in ("tight", "loose") or weight_mode not in ("projected", "global"):
        raise ValueError("cap is tight or loose, weight_mode is projected or global")
    stats = stats if stats is not None else Stats()
    if local_rows:
        return grow_by_joins(flat, weights, floor, cap, weight_mode, max_len, max_frontier, stats, local_rows)
    rows = blocked(pack(flat)).persist(StorageLevel.MEMORY_AND_DISK) if packed is None else packed
    top = max(weights.values(), default=0.0)
    out: list[Candidate] = []
    above: list[Candidate] = []  # the level before, in the order of its numbers
    steps: list[list[tuple[int, str, int]]] = []
    items: set[int] | None = None  # those that may still extend: a cap never tops the item's own, nor a weight bound that of the first level
    while True:
        began = time.perf_counter()
        seen = Observation()
        heads = [(c.peak, max(weights[x] for x, _ in c.pattern.steps)) for c in above] or [(1.0, 0.0)]
        sums = grown_sums(rows, steps, weights, heads, items).observe(seen, F.sum("n").alias("rows"))
        level: list[Candidate] = []
        named: list[tuple[int, str, int]] = []
        for r in sorted(capped(sums, floor, cap, top if weight_mode == "global" else None).collect(), key=lambda r: (r["prefix"], r["kind"], r["item_id"])):
            pattern = above[r["prefix"]].pattern.extend(r["item_id"], r["kind"]) if above else Pattern(((r["item_id"], "s"),))
            level.append(Candidate(pattern, r["peak"], r["support_cap"], r["weight_cap"], len(out) + len(level) + 1))
            named.append((r["prefix"], r["kind"], r["item_id"]))
        stats.levels += 1
        stats.peak_frontier_rows = max(stats.peak_frontier_rows, observed(seen))
        out += level
        stats.seconds[f"level {stats.levels}"] = time.perf_counter() - began
        if max_frontier and len(level) > max_frontier:
            raise FrontierTooLarge(f"{len(level)} candidates of {stats.levels} items, {max_frontier} allowed")
        if not level or (max_len and stats.levels >= max_len):
            stats.max_len_hit |= bool(level)
            break
        items = items if items is not None else {x for _, _, x in named}
        above, steps = level, [*steps, named]
    if packed is None:
        rows.unpersist()
    stats.n_candidates = len(out)
    return out


def grow_by_joins(flat: DataFrame, weights: dict[int, float], floor: float, cap: str, weight_mode: str, max_len: int | None, max_frontier: int | None, stats: Stats, local_rows: int) -> list[Candidate]:
    """``grow`` over projections that are tables; those of at most ``local_rows`` occurrences end in one task each."""
    from uncertainseq.operators.local import local_growth, parsed_steps

    began = time.perf_counter()
    rows = prepare(flat)
    top = max(weights.values(), default=0.0)
    out: list[Candidate] = []
    firsts = rows.groupBy("seq_id", "item_id").agg(F.max("p").alias("best"), F.collect_list("eid").alias("ends"))
    grown = firsts.select(F.lit(0).cast("long").alias("prefix"), "seq_id", F.lit("s").alias("kind"), "item_id", "best", "ends").persist(StorageLevel.MEMORY_AND_DISK)
    parents: dict[int, Candidate | None] = {0: None}
    kept = []
    stats.seconds["prepare"] = time.perf_counter() - began
    weighed = sent([(k, float(w)) for k, w in weights.items()], "item_id int, w double", flat)
    while True:
        began = time.perf_counter()
        above = sent([(k, c.peak if c else 1.0, max((weights[x] for x, _ in c.pattern.steps), default=0.0) if c else 0.0) for k, c in parents.items()], "prefix long, parent_peak double, parent_weight double", flat)
        seen = Observation()
        watched = grown.observe(seen, F.count(F.lit(1)).alias("rows"))
        survivors = capped(summed(watched).join(weighed, "item_id").join(above, "prefix"), floor, cap, top if weight_mode == "global" else None)
        level: list[Candidate] = []
        for r in sorted(survivors.collect(), key=lambda r: (r["prefix"], r["kind"], r["item_id"])):
            parent = parents[r["prefix"]]
            pattern = parent.pattern.extend(r["item_id"], r["kind"]) if parent else Pattern(((r["item_id"], "s"),))
            level.append(Candidate(pattern, r["peak"], r["support_cap"], r["weight_cap"], len(out) + len(level) + 1))
        stats.levels += 1
        stats.peak_frontier_rows = max(stats.peak_frontier_rows, seen.get["rows"])
        out += level
        stats.seconds[f"level {stats.levels}"] = time.perf_counter() - began
        if max_frontier and len(level) > max_frontier:
            raise FrontierTooLarge(f"{len(level)} candidates of {stats.levels} items, {max_frontier} allowed")
        if not level or (max_len and stats.levels >= max_len):
            stats.max_len_hit |= bool(level)
            break
        parents = {c.ident: c for c in level}
        lookup = {p.pattern.steps: k for k, p in kept[-1][1].items()} if kept else {}
        named = [(lookup.get(c.pattern.steps[:-1], 0), c.pattern.steps[-1][1], c.pattern.steps[-1][0], c.ident) for c in level]
        survivors = sent(named, "prefix long, kind string, item_id int, ident long", flat)
        frontier = grown.join(survivors, ["prefix", "kind", "item_id"]).select(F.col("ident").alias("prefix"), "seq_id", "ends")
        if local_rows:
            ended = grown_locally(frontier, rows, level, local_rows, local_growth(weights, floor, cap, top if weight_mode == "global" else None, max_len), weights, stats)
            for r in ended[1]:
                head = parents[r["prefix"]].pattern.steps
                out.append(Candidate(Pattern((*head, *parsed_steps(r["steps"]))), r["peak"], r["support_cap"], r["weight_cap"], 0))
            level = [c for c in level if c.ident not in ended[0]]
            stats.max_len_hit |= any(c.pattern.n_items == max_len for c in out)
            if not level:
                break
        prefixes = sent([(c.ident, c.pattern.steps[-1][0]) for c in level], "prefix long, last int", flat)
        new = extensions(frontier, rows, prefixes).persist(StorageLevel.MEMORY_AND_DISK)
        kept.append((grown, parents))
        if len(kept) > 1:
            kept[-2][0].unpersist()
        grown = new
    for g, _ in kept:
        g.unpersist()
    grown.unpersist()
    rows.unpersist()
    stats.n_candidates = len(out)
    return out
