"""Passes over a database's occurrences, whole sequences at a time: sums of extensions for growth, expected supports for scoring.

A pass is one scan of ``pack``'s rows, or of ``blocked``'s arrays of them. Each task holds some whole sequences as arrays and follows the
prefixes of a level from their first step on, so no projection is written, sent or kept between levels: only sums a (prefix, extension) or
a pattern are shuffled.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from uncertainseq.functions.sequences import clean
from uncertainseq.model import PatternTrie
from uncertainseq.runtime import ship

#: Occurrences and pairs that a task holds at once; a longer sequence is still held whole, its pairs a prefix at a time.
OCCURRENCES, PAIRS, CELLS = 200_000, 1 << 20, 1 << 22
S, I = 0, 1


def pack(flat: DataFrame) -> DataFrame:
    """Cleaned rows with each sequence in one partition, in order: the one shuffle of the data."""
    rows = clean(flat).select("seq_id", "batch_id", "eid", "item_id", "p") if "batch_id" in flat.columns else clean(flat.withColumn("batch_id", F.lit(0)))
    return in_order(rows.repartition("seq_id"))


def in_order(flat: DataFrame) -> DataFrame:
    return flat.select("seq_id", "batch_id", "eid", "item_id", "p").sortWithinPartitions("seq_id", "batch_id", "eid", "item_id")


@dataclass
class Rows:
    """Occurrences of whole sequences: number of the sequence, event, slot of the item, probability; by sequence, event and item."""

    seq: np.ndarray
    eid: np.ndarray
    slot: np.ndarray
    p: np.ndarray
    wide: int  # more than any event number
    late: tuple[np.ndarray, np.ndarray, np.ndarray] | None = None  # what ``later`` gives, where it is known; other items do not change it

    @property
    def at(self) -> np.ndarray:
        return self.seq * self.wide + self.eid

    def where(self, keep: np.ndarray) -> Rows:
        late = self.late and (self.late[0][keep], self.late[1][keep], self.late[2][keep])
        return Rows(self.seq[keep], self.eid[keep], self.slot[keep], self.p[keep], self.wide, late)


def sequences(batches: Iterable[pa.RecordBatch], items: np.ndarray) -> Iterator[Rows]:
    """Rows of some 200,000 occurrences, cut between sequences; items not among ``items`` are left out."""
    for whole in chunks(batches):
        item = whole.slot
        whole.slot = np.minimum(np.searchsorted(items, item), max(len(items) - 1, 0))
        known = items[whole.slot] == item if len(items) else np.zeros(len(item), bool)
        yield whole if known.all() else whole.where(known)


def chunks(batches: Iterable[pa.RecordBatch]) -> Iterator[Rows]:
    """Whole sequences, with items for slots, of rows or of blocks."""
    batches = iter(batches)
    for batch in batches:
        if batch.schema.names[0] != BLOCK:
            for a, new in gathered(chain([batch], batches)):
                yield numbered(a, new)
            return
        for block in batch.column(0):
            yield unblocked(block.as_buffer())


def numbered(a: list[np.ndarray], new: np.ndarray) -> Rows:
    eid = a[2].astype(np.int64)
    eid -= eid.min()
    return Rows(np.cumsum(new) - 1, eid, a[3], a[4], int(eid.max()) + 2)


def gathered(batches: Iterable[pa.RecordBatch]) -> Iterator[tuple[list[np.ndarray], np.ndarray]]:
    """Columns of some 200,000 rows, cut between sequences, and where a sequence starts."""
    held: list[list[np.ndarray]] = []
    n = 0

    def starts(a: list[np.ndarray]) -> np.ndarray:
        new = np.ones(len(a[0]), bool)
        new[1:] = (a[0][1:] != a[0][:-1]) | (a[1][1:] != a[1][:-1])
        return new

    for batch in batches:
        if not batch.num_rows:
            continue
        held.append([c.to_numpy(zero_copy_only=False) for c in batch.columns])
        n += batch.num_rows
        if n >= OCCURRENCES:
            whole = [np.concatenate(c) for c in zip(*held, strict=True)]
            new = starts(whole)
            cut = int(np.flatnonzero(new)[-1])
            if cut:
                yield [c[:cut] for c in whole], new[:cut]
            held, n = [[c[cut:] for c in whole]], len(whole[0]) - cut if cut else 0
    if held:
        whole = [np.concatenate(c) for c in zip(*held, strict=True)]
        yield whole, starts(whole)


#: The column of ``blocked``, and the forms of its arrays; event numbers take eight bytes where four are too few.
BLOCK, FORMS = "block", ("<i4", "<i4", "<f8", "<f8", "?")


def blocked(rows: DataFrame) -> DataFrame:
    """``pack``'s rows as blocks, one array of bytes for some 200,000 of them: a pass reads a block at once, and what ``later`` gives is in it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        before = None
        for a, new in gathered(batches):
            whole = numbered(a, new)
            first = np.flatnonzero(new)
            ids = a[0][first]
            named = int((ids[1:] != ids[:-1]).sum()) + int(before is None or before != ids[0])  # a sequence's batches are neighbours
            before = ids[-1]
            most, record, since = later(whole)
            event = "<i4" if whole.wide < 1 << 31 else "<i8"
            head = np.array([len(whole.seq), named, whole.wide], "<i8")
            parts = [x.astype(form).tobytes() for x, form in zip((whole.seq, whole.slot, whole.p, most, record), FORMS, strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array([b"".join([head.tobytes(), *parts, whole.eid.astype(event).tobytes(), since.astype(event).tobytes()])], pa.binary())], names=[BLOCK])

    return scanned(rows).mapInArrow(run, f"{BLOCK} binary")


def unblocked(block: pa.Buffer) -> Rows:
    n, _, wide = (int(x) for x in np.frombuffer(block, "<i8", 3))
    at, out = 24, []
    for form in (*FORMS, *["<i4" if wide < 1 << 31 else "<i8"] * 2):
        out.append(np.frombuffer(block, form, n, at))
        at += out[-1].nbytes
    seq, item, p, most, record, eid, since = out
    return Rows(seq.astype(np.int64), eid.astype(np.int64), item, p, wide, (most, record, since.astype(np.int64)))


def counted(blocks: DataFrame) -> DataFrame:
    """(item_id, n): occurrences of each item, and the number of sequences where item_id is null."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int | None, int] = {None: 0}
        for batch in batches:
            for block in batch.column(0):
                held[None] += int(np.frombuffer(block.as_buffer(), "<i8", 3)[1])
                for item, n in zip(*(x.tolist() for x in np.unique(unblocked(block.as_buffer()).slot, return_counts=True)), strict=True):
                    held[item] = held.get(item, 0) + n
        yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.int32()), pa.array(list(held.values()), pa.int64())], names=["item_id", "n"])

    return scanned(blocks).mapInArrow(run, "item_id int, n long").groupBy("item_id").agg(F.sum("n").alias("n"))


def pairs(low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(left, right): each place k of the arrays with every number from low[k] to before high[k]."""
    n = np.maximum(high - low, 0)
    left = np.repeat(np.arange(len(n)), n)
    return left, np.arange(len(left)) - np.repeat(np.cumsum(n) - n - low, n)


def slices(n: np.ndarray, group: np.ndarray | None = None) -> Iterator[slice]:
    """Runs of places whose ``n`` add up to about PAIRS, cut between equal neighbours of ``group`` only where these differ."""
    total, start = np.cumsum(n), 0
    while start < len(n):
        done = total[start - 1] if start else 0
        stop = max(start + 1, int(np.searchsorted(total, done + PAIRS, "right")))
        if group is not None and stop < len(n):
            first = int(np.searchsorted(group, group[stop]))
            stop = first if first > start else int(np.searchsorted(group, group[stop], "right"))
        yield slice(start, stop)
        start = stop


def later(rows: Rows) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For each row: the item's largest probability from here on, whether all later ones are less, and the event of the last such row before (-1: none)."""
    if rows.late is not None:
        return rows.late
    if not len(rows.seq):
        return rows.p, np.zeros(0, bool), rows.eid
    values, rank = np.unique(rows.p, return_inverse=True)
    order = np.lexsort((-rows.eid, rows.slot, rows.seq))  # latest first
    new = np.ones(len(order), bool)
    new[1:] = (rows.seq[order][1:] != rows.seq[order][:-1]) | (rows.slot[order][1:] != rows.slot[order][:-1])
    base = (np.cumsum(new) - 1) * len(values)
    most = np.maximum.accumulate(rank[order] + base)
    record = new.copy()
    record[1:] |= most[1:] > most[:-1]
    before = np.full(len(order), -1, np.int64)
    kept = np.flatnonzero(record)
    same = ~new[kept[1:]] if len(kept) > 1 else np.zeros(0, bool)
    before[kept[:-1][same]] = rows.eid[order][kept[1:][same]]
    out = np.empty(len(order)), np.empty(len(order), bool), np.empty(len(order), np.int64)
    out[0][order], out[1][order], out[2][order] = values[most - base], record, before
    return out


def most_from(value: np.ndarray, group: np.ndarray) -> np.ndarray:
    """The largest value from each place to the end of its group; ``group`` never falls."""
    values, rank = np.unique(value, return_inverse=True)
    base = (group.max(initial=0) - group[::-1]) * len(values)
    return values[(np.maximum.accumulate(rank[::-1] + base) - base)[::-1]]


def heaviest(left: Matches, m: Matches, rows: Rows, worth: np.ndarray, last: np.ndarray, out: np.ndarray) -> None:
    """Raise ``out`` (a place a prefix) to the largest weight of any occurrence after a prefix's first match or, past its last item, in an event where one ends."""
    at = rows.at
    place = np.searchsorted(at, left.at(rows.wide), "right")
    ok = np.append(rows.seq, -1)[place] == left.seq
    np.maximum.at(out, left.node[ok], most_from(worth, rows.seq)[place[ok]])
    n = int(max(rows.slot.max(), last.max())) + 1
    place = np.searchsorted(at * n + rows.slot, m.at(rows.wide) * n + last[m.node], "right")
    ok = np.append(at, -1)[place] == m.at(rows.wide)
    np.maximum.at(out, m.node[ok], most_from(worth, at)[place[ok]])


class Level:
    """Steps from the prefixes of one length to those of the next: (parent, kind, slot) to child; numbers count from 0 in a level."""

    def __init__(self, parent: np.ndarray, kind: np.ndarray, slot: np.ndarray, n_parents: int, n_slots: int):
        self.n_slots, self.n, self.slots = n_slots, len(parent), np.unique(slot)
        self.kinds = [bool((kind == k).any()) for k in (S, I)]
        key = (parent * 2 + kind) * n_slots + slot
        self.table = None
        if n_parents * 2 * n_slots <= CELLS:
            self.table = np.full(n_parents * 2 * n_slots, -1, np.int32)
            self.table[key] = np.arange(len(key))
        self.order = np.argsort(key)
        self.key = key[self.order]

    def child(self, parent: np.ndarray, kind: int, slot: np.ndarray) -> np.ndarray:
        """The child, or -1."""
        key = (parent.astype(np.int64) * 2 + kind) * self.n_slots + slot
        if self.table is not None:
            return self.table[key]
        at = np.minimum(np.searchsorted(self.key, key), self.n - 1)
        return np.where(self.key[at] == key, self.order[at], -1)


@dataclass
class Matches:
    """Where matches of a level's prefixes end: sequence, prefix, event, value; by sequence, prefix and event."""

    seq: np.ndarray
    node: np.ndarray
    eid: np.ndarray
    value: np.ndarray

    @classmethod
    def of(cls, parts: list[tuple[np.ndarray, ...]]) -> Matches:
        seq, node, eid, value = (np.concatenate(c) for c in zip(*parts, strict=True))
        wide, nodes = int(eid.max()) + 1, int(node.max()) + 1
        # one number to sort by, where it fits
        order = np.argsort((seq * nodes + node) * wide + eid, kind="stable") if (int(seq.max()) + 1) * nodes * wide < 1 << 62 else np.lexsort((eid, node, seq))
        return cls(seq[order], node[order], eid[order], value[order])

    def firsts(self) -> np.ndarray:
        """Whether a row is the first of its sequence and prefix."""
        new = np.ones(len(self.seq), bool)
        new[1:] = (self.seq[1:] != self.seq[:-1]) | (self.node[1:] != self.node[:-1])
        return new

    def at(self, wide: int) -> np.ndarray:
        return self.seq * wide + self.eid

    def where(self, keep: np.ndarray) -> Matches:
        return Matches(self.seq[keep], self.node[keep], self.eid[keep], self.value[keep])


def rising(m: Matches) -> tuple[Matches, np.ndarray, np.ndarray]:
    """Rows whose value tops all before them in their sequence and prefix, the event of the next such row (-1: none), and their group's number."""
    new = m.firsts()
    values, rank = np.unique(m.value, return_inverse=True)
    group = np.cumsum(new) - 1
    most = np.maximum.accumulate(rank + group * len(values))
    keep = new.copy()
    keep[1:] |= most[1:] > most[:-1]
    out, group = m.where(keep), group[keep]
    until = np.full(len(group), -1, np.int64)
    same = group[1:] == group[:-1]
    until[:-1][same] = out.eid[1:][same]
    return out, until, group


def spans(m: Matches, until: np.ndarray, at: np.ndarray, wide: int) -> tuple[np.ndarray, np.ndarray]:
    """Range of the places in ``at`` (sequence and event) that come after each match and not after ``until`` (-1: to the sequence's end)."""
    end = np.where(until >= 0, m.seq * wide + until, m.seq * wide + wide - 1)
    return np.searchsorted(at, m.at(wide), "right"), np.searchsorted(at, end, "right")


def followed(m: Matches, level: Level, rows: Rows, last: np.ndarray, valued: bool) -> Matches | None:
    """Matches of the next level; with ``valued`` false only where they end counts."""
    rows = rows.where(np.isin(rows.slot, level.slots))
    at, parts = rows.at, []
    if level.kinds[S]:
        if valued:
            left, until, _ = rising(m)
        else:
            left = m.where(m.firsts())
            until = np.full(len(left.seq), -1, np.int64)
        low, high = spans(left, until, at, rows.wide)
        for part in slices(high - low):
            k, r = pairs(low[part], high[part])
            k += part.start
            child = level.child(left.node[k], S, rows.slot[r])
            ok = child >= 0
            k, r = k[ok], r[ok]
            parts.append((left.seq[k], child[ok], rows.eid[r], left.value[k] * rows.p[r] if valued else rows.p[r]))
    if level.kinds[I]:
        low, high = np.searchsorted(at, m.at(rows.wide)), np.searchsorted(at, m.at(rows.wide), "right")
        for part in slices(high - low):
            k, r = pairs(low[part], high[part])
            k += part.start
            child = level.child(m.node[k], I, rows.slot[r])
            ok = (child >= 0) & (rows.slot[r] > last[m.node[k]])
            k, r = k[ok], r[ok]
            parts.append((m.seq[k], child[ok], rows.eid[r], m.value[k] * rows.p[r] if valued else rows.p[r]))
    return Matches.of(parts) if parts and sum(len(x[0]) for x in parts) else None


def started(level: Level, rows: Rows) -> Matches | None:
    child = level.child(np.zeros(len(rows.slot), np.int64), S, rows.slot)
    ok = child >= 0
    return Matches.of([(rows.seq[ok], child[ok], rows.eid[ok], rows.p[ok])]) if ok.any() else None


def largest(seq: np.ndarray, node: np.ndarray, value: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(node, number, largest value) of each sequence and node that occurs; ``number`` counts the sequences from 0 and is no more than a name."""
    first = int(seq.min())
    high = int(seq.max()) - first + 1
    if high * n <= min(CELLS, 8 * len(seq)):
        best = np.zeros(high * n)
        np.maximum.at(best, (seq - first) * n + node, value)
        at = np.flatnonzero(best)
        return at % n, at // n, best[at]
    key = seq * n + node
    order = np.argsort(key, kind="stable")
    new = np.ones(len(key), bool)
    new[1:] = key[order][1:] != key[order][:-1]
    at = np.flatnonzero(new)
    return node[order][at], seq[order][at], np.maximum.reduceat(value[order], at)


class Sums:
    """Sum, largest and number of values by key, in arrays where the keys are few, else handed on a part at a time."""

    def __init__(self, span: int):
        self.span = span
        self.dense = (np.zeros(span), np.zeros(span), np.zeros(span, np.int64)) if span <= CELLS // 4 else None

    def add(self, key: np.ndarray, value: np.ndarray) -> Iterator[tuple[np.ndarray, ...]]:
        if not len(key):
            return
        if self.dense:
            np.add.at(self.dense[0], key, value)
            np.maximum.at(self.dense[1], key, value)
            np.add.at(self.dense[2], key, 1)
            return
        order = np.argsort(key, kind="stable")
        key, value = key[order], value[order]
        at = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
        yield key[at], np.add.reduceat(value, at), np.maximum.reduceat(value, at), np.diff(np.append(at, len(key)))

    def rest(self) -> Iterator[tuple[np.ndarray, ...]]:
        if self.dense:
            at = np.flatnonzero(self.dense[2])
            yield at, self.dense[0][at], self.dense[1][at], self.dense[2][at]


def steps_of(levels: list[list[tuple[int, str, int]]], items: np.ndarray) -> tuple[list[tuple[np.ndarray, ...]], list[np.ndarray]]:
    """Arrays (parent, kind, slot) of each level's steps, and the slots of the last steps."""
    out = []
    for level in levels:
        parent, kind, item = zip(*level, strict=True)
        out.append((np.array(parent, np.int64), np.array([S if k == "s" else I for k in kind], np.int64), np.searchsorted(items, np.array(item, np.int64))))
    return out, [a[2] for a in out]


def scanned(rows: DataFrame) -> DataFrame:
    ship(rows.sparkSession)
    if rows.columns == [BLOCK]:
        return rows
    return rows.select(F.coalesce("seq_id", F.lit(-(1 << 63))).alias("seq_id"), F.coalesce("batch_id", F.lit(0)).alias("batch_id"), "eid", "item_id", "p")


def grown_sums(rows: DataFrame, levels: list[list[tuple[int, str, int]]], weights: dict[int, float], above: list[tuple[float, float]], items: set[int] | None = None) -> DataFrame:
    """(prefix, kind, item_id, w, parent_peak, parent_weight, total, peak, n) of every extension of the last level's prefixes, over projected sequences.

    ``levels``: the prefixes as steps (parent, kind, item) from each length to the next, parents and prefixes by their place in their level
    (none: the empty prefix); ``above``: peak and largest weight of the last level's prefixes. total and peak: sum and largest of the
    extension's largest probability after (or at) the ends of a match. With ``items`` only these get sums; what all others do to the weight
    bound is in a row of kind ``w`` a prefix, whose w is the largest weight of any extension.
    """
    every = np.array(sorted(weights), np.int64)
    worth = np.array([float(weights[x]) for x in sorted(weights)])
    known = every if items is None else np.array(sorted(items), np.int64)
    width, heads = len(known), np.array(above, float).reshape(-1, 2)
    spot = np.searchsorted(every, known)  # place of a known item among all
    heavy = worth[spot]
    made, lasts = steps_of(levels, known)
    n_last = len(above)
    names = ["prefix", "kind", "item_id", "w", "parent_peak", "parent_weight", "total", "peak", "n"]

    def emitted(parts: Iterable[tuple[np.ndarray, ...]]) -> Iterator[pa.RecordBatch]:
        for key, total, peak, n in parts:
            if len(key):
                prefix, kind, slot = key // (2 * width), key // width % 2, key % width
                kinds = pa.DictionaryArray.from_arrays(pa.array(kind, pa.int32()), pa.array(["s", "i"])).cast(pa.string())
                yield pa.RecordBatch.from_arrays([pa.array(prefix), kinds, pa.array(known[slot], pa.int32()), *map(pa.array, (heavy[slot], heads[prefix, 0], heads[prefix, 1], total, peak, n))], names=names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = [Level(*a, n_parents=len(levels[k - 1]) if k else 1, n_slots=width) for k, a in enumerate(made)]
        sums = Sums(n_last * 2 * width)
        bound = np.zeros(n_last)
        slot_of = np.full(len(every), -1, np.int64)
        slot_of[spot] = np.arange(width)
        for whole in sequences(batches, every):
            chunk = whole if items is None else whole.where(slot_of[whole.slot] >= 0)
            chunk = Rows(chunk.seq, chunk.eid, slot_of[chunk.slot], chunk.p, chunk.wide, chunk.late)
            if not len(chunk.seq):
                continue
            most, record, before = later(chunk)
            if not tables:
                first = record & (before < 0)
                yield from emitted(sums.add(chunk.slot[first], chunk.p[first]))
                continue
            m = started(tables[0], chunk)
            for k, level in enumerate(tables[1:]):
                m = followed(m, level, chunk, lasts[k], False) if m is not None else None
            if m is None:
                continue
            some = chunk.where(record)
            left = m.where(m.firsts())
            if items is not None:
                heaviest(left, m, whole, worth[whole.slot], spot[lasts[-1]], bound)
            low, high = spans(left, np.full(len(left.seq), -1, np.int64), some.at, chunk.wide)
            since = before[record]
            for part in slices(high - low):
                a, r = pairs(low[part], high[part])
                a += part.start
                ok = since[r] <= left.eid[a]  # the first of the item's records after the match has its largest probability
                a, r = a[ok], r[ok]
                yield from emitted(sums.add(left.node[a].astype(np.int64) * 2 * width + some.slot[r], some.p[r]))
            at = chunk.at
            low, high = np.searchsorted(at, m.at(chunk.wide)), np.searchsorted(at, m.at(chunk.wide), "right")
            group = np.cumsum(m.firsts()) - 1
            for part in slices(high - low, group):
                a, r = pairs(low[part], high[part])
                a += part.start
                ok = chunk.slot[r] > lasts[-1][m.node[a]]
                a, r = a[ok], r[ok]
                if len(a):
                    key, _, best = largest(m.seq[a], (m.node[a].astype(np.int64) * 2 + I) * width + chunk.slot[r], most[r], n_last * 2 * width)
                    yield from emitted(sums.add(key, best))
        yield from emitted(sums.rest())
        at = np.flatnonzero(bound)
        if len(at):
            none = np.zeros(len(at))
            yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(["w"] * len(at)), pa.nulls(len(at), pa.int32()), *map(pa.array, (bound[at], heads[at, 0], heads[at, 1], none, none, none.astype(np.int64)))], names=names)

    grown = scanned(rows).mapInArrow(run, "prefix long, kind string, item_id int, w double, parent_peak double, parent_weight double, total double, peak double, n long")
    return grown.groupBy("prefix", "kind", "item_id").agg(*[F.max(c).alias(c) for c in names[3:6]], F.sum("total").alias("total"), F.max("peak").alias("peak"), F.sum("n").alias("n"))


def score_packed(rows: DataFrame, trie: PatternTrie) -> DataFrame:
    """(node, support) of the trie's nodes: values of matches from level to level, in sequences that hold the step's items."""
    levels: list[list[tuple[int, str, int]]] = []
    nodes: list[list[int]] = []
    place = {0: 0}
    for node, parent, item, kind, depth, _ in trie.to_edges():
        if depth > len(levels):
            levels.append([])
            nodes.append([])
        place[node] = len(levels[depth - 1])
        levels[depth - 1].append((place[parent], kind, item))
        nodes[depth - 1].append(node)
    known = np.array(sorted({x for level in levels for _, _, x in level}), np.int64)
    made, lasts = steps_of(levels, known)
    names = [np.array(n, np.int64) for n in nodes]
    bearing = [np.unique(a[0]) for a in made[1:]]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = [Level(*a, n_parents=len(levels[k - 1]) if k else 1, n_slots=len(known)) for k, a in enumerate(made)]
        sums = [np.zeros(len(n)) for n in names]

        def add(k: int, seq: np.ndarray, node: np.ndarray, value: np.ndarray) -> None:
            if len(seq):
                found, _, best = largest(seq, node.astype(np.int64), value, len(names[k]))
                np.add.at(sums[k], found, best)

        for chunk in sequences(batches, known):
            m = started(tables[0], chunk)
            record = later(chunk)[1]
            k = 0
            while m is not None:
                at = np.flatnonzero(m.firsts())
                np.add.at(sums[k], m.node[at], np.maximum.reduceat(m.value, at))
                if k + 1 == len(tables):
                    break
                m = m.where(np.isin(m.node, bearing[k]))
                k += 1
                if not len(m.seq):
                    break
                if k + 1 < len(tables):
                    m = followed(m, tables[k], chunk, lasts[k - 1], True)
                    continue
                ends(m, tables[k], chunk, record, lasts[k - 1], lambda *found, k=k: add(k, *found))
                break
        node, part = np.concatenate(names), np.concatenate(sums)
        at = np.flatnonzero(part)
        yield pa.RecordBatch.from_arrays([pa.array(node[at]), pa.array(part[at])], names=["node", "part"])

    return scanned(rows).mapInArrow(run, "node long, part double").groupBy("node").agg(F.sum("part").alias("support"))


def ends(m: Matches, level: Level, rows: Rows, record: np.ndarray, last: np.ndarray, add) -> None:
    """Values of the longest patterns, a prefix and sequence at a time: of a new event's items only records can be best."""
    wanted = np.isin(rows.slot, level.slots)
    if level.kinds[S]:
        some = rows.where(wanted & record)
        left, until, group = rising(m)
        low, high = spans(left, until, some.at, rows.wide)
        for part in slices(high - low, group):
            k, r = pairs(low[part], high[part])
            k += part.start
            child = level.child(left.node[k], S, some.slot[r])
            ok = child >= 0
            k, r = k[ok], r[ok]
            add(left.seq[k], child[ok], left.value[k] * some.p[r])
    if level.kinds[I]:
        some = rows.where(wanted)
        at, group = some.at, np.cumsum(m.firsts()) - 1
        low, high = np.searchsorted(at, m.at(rows.wide)), np.searchsorted(at, m.at(rows.wide), "right")
        for part in slices(high - low, group):
            k, r = pairs(low[part], high[part])
            k += part.start
            child = level.child(m.node[k], I, some.slot[r])
            ok = (child >= 0) & (some.slot[r] > last[m.node[k]])
            k, r = k[ok], r[ok]
            add(m.seq[k], child[ok], m.value[k] * some.p[r])
