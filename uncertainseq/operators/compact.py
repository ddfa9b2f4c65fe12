"""Smaller forms of a mined set: maximal and closed patterns. All work is on the answer, which the driver holds already."""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator, Sequence

from uncertainseq.model import EPSILON, Scored


def _larger(patterns: Sequence[Scored]) -> Iterator[tuple[Scored, Iterator[Scored]]]:
    """Every pattern with the larger ones that contain it; only patterns that hold all its items are compared."""
    holding: dict[int, set[int]] = defaultdict(set)
    for k, s in enumerate(patterns):
        for item, _ in s.pattern.steps:
            holding[item].add(k)
    for s in patterns:
        shared = set.intersection(*(holding[item] for item, _ in s.pattern.steps)) if s.pattern.steps else set(range(len(patterns)))
        yield s, (o for o in (patterns[k] for k in shared) if o.pattern.n_items > s.pattern.n_items and o.pattern.contains(s.pattern))


def maximal(patterns: Sequence[Scored]) -> list[Scored]:
    """The patterns that no other of the set contains."""
    return [s for s, larger in _larger(patterns) if not any(True for _ in larger)]


def closed(patterns: Sequence[Scored]) -> list[Scored]:
    """The patterns that none of the set contains at the same expected support: with them all supports of the set are known.

    Supports count alike if they differ by no more than rounding. Weights play no part, as a larger pattern's mean differs.
    """
    return [s for s, larger in _larger(patterns) if not any(o.support >= s.support - EPSILON for o in larger)]
