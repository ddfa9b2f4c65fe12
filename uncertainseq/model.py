"""Patterns, weights, floors and parameters."""

from __future__ import annotations

import re
from collections.abc import Iterable, Mapping
from dataclasses import dataclass, field

from pyspark.sql import types as T

ITEM = T.StructType([T.StructField("item_id", T.IntegerType()), T.StructField("p", T.DoubleType())])
FLAT = T.StructType([T.StructField("seq_id", T.LongType()), T.StructField("batch_id", T.IntegerType()), T.StructField("eid", T.IntegerType()), T.StructField("item_id", T.IntegerType()), T.StructField("p", T.DoubleType())])
SEQUENCES = T.StructType([T.StructField("seq_id", T.LongType()), T.StructField("batch_id", T.IntegerType()), T.StructField("events", T.ArrayType(T.ArrayType(ITEM)))])
RESULT = "pattern string, n_items int, n_events int, expected_support double, pattern_weight double, weighted_support double, status string"
EPSILON = 1e-9


@dataclass(frozen=True)
class Pattern:
    """An ordered list of itemsets, held as steps (item, kind): kind ``s`` opens an event, ``i`` joins the last one."""

    steps: tuple[tuple[int, str], ...]

    @classmethod
    def of(cls, *events: Iterable[int]) -> Pattern:
        return cls(tuple((x, "i" if k else "s") for e in events for k, x in enumerate(sorted(e))))

    @classmethod
    def parse(cls, text: str, ids: Mapping[str, int]) -> Pattern:
        """From the text form (a)(b,c)."""
        return cls.of(*[[ids[x] for x in e.split(",")] for e in re.findall(r"\(([^()]*)\)", text)])

    def text(self, names: Mapping[int, str]) -> str:
        return "".join((")(" if k == "s" and n else "(" if k == "s" else ",") + names[x] for n, (x, k) in enumerate(self.steps)) + ")"

    @property
    def n_items(self) -> int:
        return len(self.steps)

    @property
    def n_events(self) -> int:
        return sum(k == "s" for _, k in self.steps)

    @property
    def events(self) -> list[list[int]]:
        out: list[list[int]] = []
        for x, k in self.steps:
            out.append([x]) if k == "s" else out[-1].append(x)
        return out

    def extend(self, item: int, kind: str) -> Pattern:
        if kind == "i" and item <= self.steps[-1][0]:
            raise ValueError("an item joins an event only after the event's last item")
        return Pattern((*self.steps, (item, kind)))

    def is_prefix_of(self, other: Pattern) -> bool:
        return other.steps[: len(self.steps)] == self.steps

    def contains(self, other: Pattern) -> bool:
        """Whether ``other``'s events are subsets of some of this pattern's events, in order."""
        at = 0
        mine = [set(e) for e in self.events]
        for e in other.events:
            while at < len(mine) and not set(e) <= mine[at]:
                at += 1
            if at == len(mine):
                return False
            at += 1
        return True

    def weight(self, weights: Mapping[int, float]) -> float:
        return sum(weights[x] for x, _ in self.steps) / len(self.steps)


@dataclass(frozen=True)
class Params:
    """min_sup, factor on the floor, buffer ratio, factor of the local floor, longest pattern (None: any)."""

    min_sup: float
    factor: float = 1.0
    buffer_ratio: float = 1.0
    local_factor: float = 2.0
    max_len: int | None = None


@dataclass
class Totals:
    """What the floors need of a database; additive over increments."""

    sequences: int = 0
    occurrences: int = 0
    weight: float = 0.0

    def __add__(self, other: Totals) -> Totals:
        return Totals(self.sequences + other.sequences, self.occurrences + other.occurrences, self.weight + other.weight)

    @property
    def mean_weight(self) -> float:
        return self.weight / self.occurrences if self.occurrences else 0.0


@dataclass(frozen=True)
class Floors:
    frequent: float
    buffer: float
    local: float


def floors(total: Totals, params: Params, increment: Totals | None = None) -> Floors:
    """The frequent floor, its buffered part, and the floor for patterns mined inside one increment, by the increment's own mean weight."""
    frequent = params.min_sup * total.sequences * total.mean_weight * params.factor
    local = params.local_factor * params.min_sup * params.buffer_ratio * increment.sequences * increment.mean_weight * params.factor if increment else 0.0
    return Floors(frequent, params.buffer_ratio * frequent, local)


@dataclass
class Stats:
    """Counters of one run."""

    n_candidates: int = 0
    n_frequent: int = 0
    peak_frontier_rows: int = 0
    trie_nodes: int = 0
    levels: int = 0
    max_len_hit: bool = False
    local_prefixes: int = 0
    seconds: dict[str, float] = field(default_factory=dict)


@dataclass
class Scored:
    """A pattern with its measures."""

    pattern: Pattern
    support: float
    weight: float
    status: str = "frequent"
    since: int = 0

    @property
    def score(self) -> float:
        return self.support * self.weight


class PatternTrie:
    """Patterns sharing prefixes. A node may be there for its children alone."""

    def __init__(self, patterns: Iterable[Pattern] = ()):
        self.children: dict[int, dict[tuple[int, str], int]] = {0: {}}
        self.terminal: set[int] = set()
        self.parent: dict[int, tuple[int, tuple[int, str]]] = {}
        self._next = 1
        for p in patterns:
            self.insert(p)

    def __len__(self) -> int:
        return len(self.terminal)

    def insert(self, pattern: Pattern) -> int:
        node = 0
        for step in pattern.steps:
            if step not in self.children[node]:
                self.children[node][step] = self._next
                self.children[self._next] = {}
                self.parent[self._next] = (node, step)
                self._next += 1
            node = self.children[node][step]
        self.terminal.add(node)
        return node

    def find(self, pattern: Pattern) -> int | None:
        node = 0
        for step in pattern.steps:
            node = self.children[node].get(step, -1)
            if node < 0:
                return None
        return node if node in self.terminal else None

    def delete(self, pattern: Pattern) -> bool:
        """Remove a pattern, and from the leaf upwards the nodes that nothing needs any more."""
        node = self.find(pattern)
        if node is None:
            return False
        self.terminal.discard(node)
        while node and not self.children[node] and node not in self.terminal:
            up, step = self.parent.pop(node)
            del self.children[up][step], self.children[node]
            node = up
        return True

    def walk(self) -> Iterable[tuple[int, Pattern]]:
        """Terminal nodes and their patterns, depth first."""
        stack: list[tuple[int, tuple]] = [(0, ())]
        while stack:
            node, steps = stack.pop()
            if node in self.terminal:
                yield node, Pattern(steps)
            stack += [(child, (*steps, step)) for step, child in sorted(self.children[node].items(), reverse=True)]

    def to_edges(self) -> list[tuple[int, int, int, str, int, bool]]:
        """(node, parent, item, kind, depth, terminal), parents first."""
        out, level = [], [(0, 0)]
        while level:
            below = []
            for node, depth in level:
                for (item, kind), child in sorted(self.children[node].items()):
                    out.append((child, node, item, kind, depth + 1, child in self.terminal))
                    below.append((child, depth + 1))
            level = below
        return out

    @classmethod
    def from_edges(cls, edges: Iterable[tuple[int, int, int, str, int, bool]]) -> PatternTrie:
        out, steps = cls(), {0: ()}
        for node, parent, item, kind, _, terminal in edges:
            steps[node] = (*steps[parent], (item, kind))
            if terminal:
                out.insert(Pattern(steps[node]))
        return out
