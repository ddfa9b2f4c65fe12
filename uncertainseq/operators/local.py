"""Mining where a group or a projection is small enough for one task: plain Python over rows that Spark has brought together."""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Callable, Iterator, Mapping

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from uncertainseq.model import EPSILON, Params, Pattern
from uncertainseq.operators.mining import Database, MiningResult, mine_static

Steps = tuple[tuple[int, str], ...]
#: Match values of a prefix by sequence, then by the event where the match ends.
Matches = dict[int, dict[int, float]]


def mine_rows(sequences: Mapping[int, Mapping[int, Mapping[int, float]]], weights: Mapping[int, float], floor: float, max_len: int | None = None) -> Iterator[tuple[Pattern, float]]:
    """(pattern, expected support) of all patterns whose weighted support reaches ``floor``, depth first.

    ``sequences``: id to event number to item to probability. Supports are exact at every step, so a prefix is left as soon as
    its support times the largest weight misses the floor.
    """
    top = max(weights.values(), default=0.0)

    def longer(found: Matches | None, last: int) -> dict[tuple[int, str], Matches]:
        out: dict[tuple[int, str], Matches] = defaultdict(lambda: defaultdict(dict))
        for s in sequences if found is None else found:
            ends, before = (found[s] if found is not None else {}), 1.0 if found is None else 0.0
            for eid in sorted(sequences[s]):
                here = ends.get(eid, 0.0)
                for item, p in sequences[s][eid].items():
                    if before * p > 0:
                        out[item, "s"][s][eid] = before * p
                    if here * p > 0 and item > last:
                        out[item, "i"][s][eid] = here * p
                before = max(before, here)
        return out

    stack: list[tuple[Steps, Matches | None]] = [((), None)]
    while stack:
        steps, found = stack.pop()
        for (item, kind), matches in sorted(longer(found, steps[-1][0] if steps else -1).items(), reverse=True):
            support = sum(max(ends.values()) for ends in matches.values())
            pattern = Pattern((*steps, (item, kind)))
            if support * pattern.weight(weights) >= floor - EPSILON:
                yield pattern, support
            if support * top >= floor - EPSILON and (max_len is None or len(pattern.steps) < max_len):
                stack.append((pattern.steps, matches))


def local_growth(weights: Mapping[int, float], floor: float, cap: str, top: float | None, max_len: int | None) -> Callable[[pd.DataFrame], pd.DataFrame]:
    """For ``applyInPandas`` on the projection of one prefix: all candidates that ``grow`` would find below it, by the same caps.

    Rows: prefix, seq_id, ends, eid, item_id, p (suffix maximum), last, depth, parent_peak, parent_weight. Gives (prefix, steps, peak,
    support_cap, weight_cap), steps being those after the prefix.
    """

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        ident, last, depth, peak, heavy = (rows[c].iloc[0] for c in ("prefix", "last", "depth", "parent_peak", "parent_weight"))
        sequences: dict[int, list[tuple[int, int, float]]] = defaultdict(list)
        ends: dict[int, set[int]] = {}
        for s, e, eid, item, p in zip(*(rows[c].tolist() for c in ("seq_id", "ends", "eid", "item_id", "p")), strict=True):
            sequences[s].append((eid, item, p))
            if s not in ends:
                ends[s] = {int(x) for x in e}
        out, stack = [], [((), int(last), ends, float(peak), float(heavy))]
        while stack:
            steps, final, where, above, heaviest_above = stack.pop()
            best: dict[tuple[int, str], dict[int, float]] = defaultdict(dict)
            at: dict[tuple[int, str], dict[int, set[int]]] = defaultdict(lambda: defaultdict(set))
            for s, held in where.items():
                first = min(held)
                for eid, item, p in sequences[s]:
                    for kind in ("s",) * (eid > first) + ("i",) * (eid in held and item > final):
                        best[item, kind][s] = max(best[item, kind].get(s, 0.0), p)
                        at[item, kind][s].add(eid)
            heaviest = top if top is not None else max((weights[x] for x, _ in best), default=0.0)
            for (item, kind), by in best.items():
                most = max(by.values())
                support = above * (sum(by.values()) if cap == "tight" else most * len(by))
                weight = max(heaviest, heaviest_above, weights[item])
                if support * weight < floor - EPSILON:
                    continue
                below = (*steps, (int(item), kind))
                out.append((int(ident), ";".join(f"{x}{k}" for x, k in below), above * most, support, weight))
                if max_len is None or depth + len(below) < max_len:
                    stack.append((below, item, at[item, kind], above * most, max(heaviest_above, weights[item])))
        return pd.DataFrame(out, columns=["prefix", "steps", "peak", "support_cap", "weight_cap"])

    return run


def parsed_steps(text: str) -> Steps:
    return tuple((int(s[:-1]), s[-1]) for s in text.split(";"))


#: Groups that ``mine_groups`` takes, one after the other.
GROUPS_MOST = 1_000


def mine_groups(db: Database, key: DataFrame, params: Params, most: int = GROUPS_MOST) -> dict[str, MiningResult]:
    """The static miner on each group of sequences (``key``: seq_id, segment) against the group's own floor; patterns of any length.

    Every group is mined by all tasks, so none need fit into one; more than ``most`` groups are an error. A sequence without a segment is in none.
    """
    names = [r["segment"] for r in key.filter("segment is not null").select("segment").distinct().limit(most + 1).collect()]
    if len(names) > most:
        raise ValueError(f"more than {most} groups")
    out = {}
    for name in sorted(names):
        ids = key.filter(F.col("segment") == F.lit(name)).select("seq_id").distinct()
        group = Database(db.flat.join(ids, "seq_id", "left_semi"), db.weights, db.names)
        out[name] = mine_static(group, params)
        group.release()
    return out


#: Occurrences that the table function takes into one task.
ROWS_MOST = 2_000_000


def register_table_function(spark: SparkSession, weights: Mapping[int, float], most: int = ROWS_MOST) -> None:
    """SQL table function weighted_patterns(TABLE(rows) PARTITION BY (segment), min_sup, max_len) over rows (segment, seq_id, eid, item_id, p).

    It gives (segment, pattern over item ids, n_items, expected_support, pattern_weight). A partition is mined in one task; more
    than ``most`` occurrences in one are an error, for which ``mine_groups`` is the way.
    """
    from pyspark.sql.functions import udtf

    known = dict(weights)

    @udtf(returnType="segment string, pattern string, n_items int, expected_support double, pattern_weight double")
    class WeightedPatterns:
        def __init__(self):
            self.rows, self.held, self.segment, self.min_sup, self.max_len = defaultdict(lambda: defaultdict(dict)), 0, None, None, None

        def eval(self, row, min_sup: float, max_len: int):
            self.segment, self.min_sup, self.max_len = row["segment"], float(min_sup), max_len
            if row["p"] and row["p"] > 0:
                event = self.rows[row["seq_id"]][row["eid"]]
                event[row["item_id"]] = max(event.get(row["item_id"], 0.0), row["p"])
                self.held += 1
                if self.held > most:
                    raise ValueError(f"more than {most} occurrences in a partition")

        def terminate(self):
            worth = [known[x] for events in self.rows.values() for e in events.values() for x in e]
            if worth:
                floor = self.min_sup * len(self.rows) * sum(worth) / len(worth)
                for pattern, support in mine_rows(self.rows, known, floor, self.max_len):
                    yield self.segment, pattern.text({x: str(x) for x in known}), pattern.n_items, float(support), float(pattern.weight(known))

    spark.udtf.register("weighted_patterns", WeightedPatterns)
