"""The static miner, the loose-cap baseline, grouped mining and a naive enumerator."""

from __future__ import annotations

import time
from dataclasses import dataclass, field
from functools import reduce
from itertools import pairwise, product

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from uncertainseq.functions.sequences import match_in, to_sequences
from uncertainseq.model import EPSILON, Params, Pattern, Scored, Stats, Totals, floors
from uncertainseq.operators.growth import Candidate, grow
from uncertainseq.operators.passes import blocked, counted, pack
from uncertainseq.operators.scoring import expected_supports


@dataclass
class Database:
    """A database in both forms, the weights of its items and their names."""

    flat: DataFrame
    weights: dict[int, float]
    names: dict[int, str]
    nested: DataFrame | None = None
    _totals: Totals | None = field(default=None, repr=False)
    #: What this is a part of, and the condition on sequences that makes it.
    whole: Database | None = field(default=None, repr=False)
    condition: str = "true"
    #: ``flat`` as ``pack`` gives it.
    _packed: DataFrame | None = field(default=None, repr=False)
    #: Ranges (after, to) of sequence ids that this part takes, None for no end; parts whose ranges do not meet make up one as ``pieces``.
    spans: list[tuple[int | None, int | None]] = field(default_factory=list)
    pieces: list[Database] = field(default_factory=list, repr=False)
    _blocks: DataFrame | None = field(default=None, repr=False)

    def sequences(self) -> DataFrame:
        if self.nested is None:
            self.nested = to_sequences(self.flat)
        return self.nested

    def packed(self) -> DataFrame:
        """The rows by sequence, in order and kept; a part takes its own from the whole's."""
        if self._packed is None:
            self._packed = self.whole.packed().filter(self.condition) if self.whole else pack(self.flat).persist(StorageLevel.MEMORY_AND_DISK)
        return self._packed

    def blocks(self) -> DataFrame:
        """The packed rows as arrays, kept; what is made up of pieces takes theirs."""
        if self._blocks is None:
            if self.pieces:
                union = reduce(DataFrame.unionAll, [p.blocks() for p in self.pieces])
                self._blocks = union.coalesce(int(union.sparkSession.conf.get("spark.sql.shuffle.partitions")))
            elif self.whole is not None and self.condition == "true":
                self._blocks = self.whole.blocks()
            else:
                self._blocks = blocked(self.packed()).persist(StorageLevel.MEMORY_AND_DISK)
        return self._blocks

    def release(self) -> None:
        """Keep the packed rows and their arrays no longer."""
        if self._packed is not None and self.whole is None:
            self._packed.unpersist()
        if self._blocks is not None and not self.pieces and (self.whole is None or self.condition != "true"):
            self._blocks.unpersist()
            self._blocks = None

    def totals(self) -> Totals:
        """Number of sequences and of occurrences, and the occurrences' weight: one row for each item reaches the driver."""
        if self._totals is None and self.pieces:
            self._totals = sum((p.totals() for p in self.pieces), Totals())
        if self._totals is None and self.tidy():
            held = {r["item_id"]: r["n"] for r in counted(self.blocks()).collect()}  # a row an item
            n = held.pop(None, 0)
            self._totals = Totals(n, sum(held.values()), sum(k * self.weights[x] for x, k in held.items()))
        if self._totals is None:
            n = self.flat.select("seq_id").distinct().count()
            counts = self.flat.groupBy("item_id").count().collect()
            self._totals = Totals(n, sum(r["count"] for r in counts), sum(r["count"] * self.weights[r["item_id"]] for r in counts))
        return self._totals

    def tidy(self) -> bool:
        """Whether ``flat`` came in order and clean, so that its rows are the packed ones."""
        return self.whole.tidy() if self.whole is not None else self._packed is self.flat

    def part(self, condition: str) -> Database:
        return Database(self.flat.filter(condition), self.weights, self.names, whole=self, condition=condition)

    def between(self, after: int | None, to: int | None) -> Database:
        """The part of the sequences with ids above ``after`` and not above ``to``."""
        ends = ([f"seq_id > {after}"] if after is not None else []) + ([f"seq_id <= {to}"] if to is not None else [])
        out = self.part(" and ".join(ends) or "true")
        out.spans = [(after, to)]
        return out

    def joined(self, other: Database) -> Database:
        """Both databases' sequences; parts of one whole stay a part of it."""
        if self.whole is not None and self.whole is other.whole:
            out = self.whole.part(f"({self.condition}) or ({other.condition})")
            spans = sorted(self.spans + other.spans, key=lambda s: (s[0] is not None, s[0] or 0))
            if self.spans and other.spans and all(a[1] is not None and b[0] is not None and a[1] <= b[0] for a, b in pairwise(spans)):
                out.spans, out.pieces = spans, [*(self.pieces or [self]), *(other.pieces or [other])]
            return out
        return Database(self.flat.unionByName(other.flat), other.weights, other.names)

    def unit(self) -> Database:
        """The same with all weights one."""
        return Database(self.flat, dict.fromkeys(self.weights, 1.0), self.names, self.nested, whole=self)


@dataclass
class MiningResult:
    patterns: list[Scored]
    candidates: list[Candidate]
    supports: dict[Pattern, float]
    floor: float
    stats: Stats

    def frame(self, spark: SparkSession, names: dict[int, str]) -> DataFrame:
        from uncertainseq.model import RESULT

        return spark.createDataFrame([(s.pattern.text(names), s.pattern.n_items, s.pattern.n_events, float(s.support), s.weight, s.score, s.status) for s in self.patterns], RESULT)

    def false_positive_rate(self) -> tuple[int, float]:
        """Candidates that are not frequent, and their share in percent."""
        wrong = len(self.candidates) - len(self.patterns)
        return wrong, 100.0 * wrong / len(self.candidates) if self.candidates else 0.0


def mine_static(db: Database, params: Params, cap: str = "tight", weight_mode: str = "projected", scorer: str = "auto", max_frontier: int | None = None, floor: float | None = None, local_rows: int = 0) -> MiningResult:
    """All patterns whose weighted support reaches ``params.buffer_ratio`` of the frequent floor; those below that floor are ``semi``."""
    stats = Stats()
    total = db.totals()
    limits = floors(total, params)
    low = limits.buffer if floor is None else floor
    if not total.sequences or low <= 0:
        return MiningResult([], [], {}, low, stats)
    found = grow(db.flat, db.weights, low, cap, weight_mode, params.max_len, max_frontier, stats, local_rows, db.blocks())
    began = time.perf_counter()
    supports = expected_supports(db.sequences(), [c.pattern for c in found], scorer, db.flat, db.blocks())
    stats.seconds["scoring"] = time.perf_counter() - began
    scored = [Scored(c.pattern, supports[c.pattern], c.pattern.weight(db.weights)) for c in found]
    kept = [s for s in scored if s.score >= low - EPSILON]
    if floor is None:
        for s in kept:
            s.status = "frequent" if s.score >= limits.frequent - EPSILON else "semi"
    stats.n_frequent, stats.trie_nodes = len(kept), len(found)
    return MiningResult(kept, found, supports, low, stats)


def mine_loose(db: Database, params: Params, weight_floor: float | None = None, scorer: str = "pairwise") -> MiningResult:
    """The prior miner: looser caps, weights as a filter of their own, quadratic scoring."""
    out = mine_static(db, params, cap="loose", weight_mode="global", scorer=scorer)
    if weight_floor is not None:
        out.patterns = [s for s in out.patterns if s.weight >= weight_floor]
        out.stats.n_frequent = len(out.patterns)
    return out


def mine_candidates(db: Database, params: Params, cap: str = "tight", weight_mode: str = "projected") -> list[Candidate]:
    """Growth without scoring."""
    return grow(db.flat, db.weights, floors(db.totals(), params).buffer, cap, weight_mode, params.max_len, packed=db.blocks())


def enumerate_exact(sequences: list[list[dict[int, float]]], weights: dict[int, float], floor: float, max_len: int) -> dict[Pattern, float]:
    """Weighted supports of all patterns that reach ``floor``, by plain recursion over expected support; for tests and small inputs."""
    items = sorted({x for s in sequences for e in s for x in e})
    rows = [[[{"item_id": x, "p": p} for x, p in e.items()] for e in s] for s in sequences]
    top = max(weights.values(), default=0.0)
    out: dict[Pattern, float] = {}
    level = [Pattern(((x, "s"),)) for x in items]
    while level:
        below = []
        for p in level:
            support = sum(match_in(s, p) for s in rows)
            if support * p.weight(weights) >= floor - EPSILON:
                out[p] = support * p.weight(weights)
            if support * top >= floor - EPSILON and p.n_items < max_len:
                below += [p.extend(x, k) for x, k in product(items, "si") if k == "s" or x > p.steps[-1][0]]
        level = below
    return out


def mine_by_group(db: Database, key: DataFrame, params: Params) -> DataFrame:
    """Frequent single items and pairs of each group of sequences (``key``: seq_id, segment), each group against its own floor."""
    spark = db.flat.sparkSession
    w = spark.createDataFrame([(k, float(v), db.names[k]) for k, v in db.weights.items()], "item_id int, w double, item string")
    rows = db.flat.join(key, "seq_id").join(F.broadcast(w), "item_id")
    total = rows.groupBy("segment").agg(F.countDistinct("seq_id").alias("n"), F.avg("w").alias("mean"))
    limit = total.select("segment", (F.col("n") * F.col("mean") * params.min_sup * params.factor).alias("floor"))
    singles = rows.groupBy("segment", "seq_id", "item", "w").agg(F.max("p").alias("p")).groupBy("segment", "item", "w").agg(F.sum("p").alias("support"))
    singles = singles.select("segment", F.concat(F.lit("("), "item", F.lit(")")).alias("pattern"), "support", "w")
    second = rows.select("segment", "seq_id", F.col("eid").alias("eid2"), F.col("item").alias("item2"), F.col("p").alias("p2"), F.col("w").alias("w2"), F.col("item_id").alias("id2"))
    pairs = rows.join(second, ["segment", "seq_id"]).filter("eid2 > eid or (eid2 = eid and id2 > item_id)")
    text = F.when(F.col("eid2") > F.col("eid"), F.concat(F.lit("("), "item", F.lit(")("), "item2", F.lit(")"))).otherwise(F.concat(F.lit("("), "item", F.lit(","), "item2", F.lit(")")))
    best = pairs.groupBy("segment", "seq_id", text.alias("pattern"), ((F.col("w") + F.col("w2")) / 2).alias("w")).agg(F.max(F.col("p") * F.col("p2")).alias("p"))
    doubles = best.groupBy("segment", "pattern", "w").agg(F.sum("p").alias("support")).select("segment", "pattern", "support", "w")
    return singles.unionByName(doubles).join(limit, "segment").filter(F.col("support") * F.col("w") >= F.col("floor") - EPSILON).select("segment", "pattern", "support", F.col("w").alias("pattern_weight"))


