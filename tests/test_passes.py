"""Passes over whole sequences against plain Python and against the joins they replaced."""

import random

import numpy as np
import pytest

from uncertainseq.functions.sequences import match_in
from uncertainseq.model import Params, Pattern, floors
from uncertainseq.operators import passes
from uncertainseq.operators.growth import grow
from uncertainseq.operators.incremental import RemineBaseline
from uncertainseq.operators.mining import Database, enumerate_exact, mine_static
from uncertainseq.operators.scoring import expected_supports
from uncertainseq.plans.workloads import slice_batches
from uncertainseq.sources.adapters import ADAPTERS, literal, load, occurrences


def drawn(seed: int, sequences: int = 25, events: int = 9) -> dict:
    """Repeated items, many equal probabilities, sequences of one event."""
    rng = random.Random(seed)
    return {s: [{x: rng.choice((0.2, 0.5, 0.5, 0.9)) for x in rng.sample("abcdef", rng.randint(1, 3))} for _ in range(rng.randint(1, events))] for s in range(1, sequences)}


WEIGHTS = {"a": 0.9, "b": 0.3, "c": 0.6, "d": 0.5, "e": 0.2, "f": 0.7}


@pytest.fixture(params=[(200_000, 1 << 20, 1 << 22), (20, 7, 16)], ids=["whole", "in small parts"])
def bounds(request, monkeypatch):
    """Bounds that cut chunks and pairs and leave no table dense, too; workers get them since the module's code reads them there."""
    for name, value in zip(("OCCURRENCES", "PAIRS", "CELLS"), request.param, strict=True):
        monkeypatch.setattr(passes, name, value)


def record_batches(db):
    rows = db.packed().toPandas().sort_values(["seq_id", "batch_id", "eid", "item_id"])
    import pyarrow as pa

    whole = pa.RecordBatch.from_pandas(rows, preserve_index=False)
    return [whole.slice(k, 11) for k in range(0, whole.num_rows, 11)]


class Local:
    """Stands in for a table: runs a pass here on batches, so that the bounds set by a test hold."""

    def __init__(self, batches):
        self.batches, self.out = batches, None

    def mapInArrow(self, run, schema):  # noqa: N802
        self.out = list(run(iter(self.batches)))
        return self

    def groupBy(self, *_):  # noqa: N802
        return self

    def agg(self, *_):
        return self


def test_supports_in_parts(spark, bounds, monkeypatch):
    data = drawn(3)
    db = literal(spark, data, WEIGHTS)
    ids = {n: k for k, n in db.names.items()}
    rows = [[[{"item_id": ids[x], "p": p} for x, p in e.items()] for e in s] for s in data.values()]
    patterns = [p for p in enumerate_exact([[{ids[x]: v for x, v in e.items()} for e in s] for s in data.values()], db.weights, 0.5, 3)]
    trie = passes.PatternTrie(patterns)
    monkeypatch.setattr(passes, "scanned", lambda rows: rows)
    local = Local(record_batches(db))
    passes.score_packed(local, trie)
    got: dict[int, float] = {}
    for b in local.out:
        for r in b.to_pylist():
            got[r["node"]] = got.get(r["node"], 0.0) + r["part"]
    want = {n: sum(match_in(s, p) for s in rows) for n, p in trie.walk()}
    assert len(want) > 100 and {n: got[n] for n in want} == pytest.approx(want)


def test_sums_in_parts(spark, bounds, monkeypatch):
    """Totals of extensions of (a) and (a)(c) by brute force over suffix maxima."""
    data = drawn(5)
    db = literal(spark, data, WEIGHTS)
    ids = {n: k for k, n in db.names.items()}
    monkeypatch.setattr(passes, "scanned", lambda rows: rows)
    local = Local(record_batches(db))
    kept = {ids[x] for x in "acdf"}
    passes.grown_sums(local, [[(0, "s", ids["a"])], [(0, "s", ids["c"])]], db.weights, [(1.0, 0.9)], kept)
    got, bound = {}, 0.0
    for b in local.out:
        for r in b.to_pylist():
            if r["kind"] == "w":
                bound = max(bound, r["w"])
                continue
            old = got.get((r["kind"], r["item_id"]), (0.0, 0.0, 0))
            got[r["kind"], r["item_id"]] = (old[0] + r["total"], max(old[1], r["peak"]), old[2] + r["n"])
    want, heavy = {}, 0.0
    for s in data.values():
        first = next((k for k, e in enumerate(s) if "a" in e), len(s))
        ends = [k for k, e in enumerate(s) if k > first and "c" in e]
        for x in WEIGHTS:
            for kind, at in (("s", [k for k, e in enumerate(s) if ends and k > ends[0] and x in e]), ("i", [k for k in ends if x in s[k] and x > "c"])):
                if at:
                    heavy = max(heavy, WEIGHTS[x])
                    if ids[x] in kept:
                        best = max(e[x] for e in s[min(at):] if x in e)
                        old = want.get((kind, ids[x]), (0.0, 0.0, 0))
                        want[kind, ids[x]] = (old[0] + best, max(old[1], best), old[2] + 1)
    assert got.keys() == want.keys() and bound == heavy
    for k in want:
        assert got[k] == pytest.approx(want[k])


@pytest.mark.parametrize(("cap", "mode"), [("tight", "projected"), ("tight", "global"), ("loose", "projected")])
def test_candidates_equal_those_of_joins(spark, cap, mode):
    db = literal(spark, drawn(7), WEIGHTS)
    low = floors(db.totals(), Params(0.08)).frequent
    name = lambda found: {c.pattern: pytest.approx((c.peak, c.support_cap, c.weight_cap)) for c in found}
    by_passes, by_joins = grow(db.flat, db.weights, low, cap, mode, 4), grow(db.flat, db.weights, low, cap, mode, 4, local_rows=1)
    assert len(by_passes) > 50 and {c.pattern: (c.peak, c.support_cap, c.weight_cap) for c in by_passes} == name(by_joins)


def test_all_patterns_of_any_length(spark):
    data = drawn(11, 15, 5)
    db = literal(spark, data, WEIGHTS)
    ids = {n: k for k, n in db.names.items()}
    params = Params(0.1)
    want = enumerate_exact([[{ids[x]: v for x, v in e.items()} for e in s] for s in data.values()], db.weights, floors(db.totals(), params).frequent, 9)
    assert {s.pattern: s.score for s in mine_static(db, params).patterns} == pytest.approx(want)
    few = list(want)[:5]
    assert expected_supports(db.sequences(), few, "packed", db.flat) == pytest.approx(expected_supports(db.sequences(), few, "fold"))


def test_parts_of_one_whole_are_joined_without_a_union(spark):
    db = literal(spark, drawn(13), WEIGHTS)
    both = db.part("seq_id <= 9").joined(db.part("seq_id > 9 and seq_id <= 20"))
    assert both.whole is db and both.totals() == db.part("seq_id <= 20").totals()
    m = RemineBaseline(Params(0.1, max_len=2))
    m.start(db.part("seq_id <= 9"))
    got = m.update(db.part("seq_id > 9"), 1)
    assert {p: s.score for p, s in got.items()} == pytest.approx({s.pattern: s.score for s in mine_static(db, Params(0.1, max_len=2)).patterns})


def test_a_long_sequence_stays_whole():
    import pyarrow as pa

    n = 3 * passes.OCCURRENCES
    batch = pa.RecordBatch.from_arrays([pa.array(np.zeros(n, np.int64)), pa.array(np.zeros(n, np.int32)), pa.array(np.arange(n)), pa.array(np.zeros(n, np.int32)), pa.array(np.full(n, 0.5))], names=list("abcde"))
    assert [len(r.seq) for r in passes.sequences([batch.slice(k, 10_000) for k in range(0, n, 10_000)], np.array([0]))] == [n]


def test_orders_are_ranked_without_one_task_for_all(spark, sf_dir):
    """F8: no window over all orders; the numbers are those of one dense rank."""
    rows = occurrences(spark, sf_dir, "basket_drift")
    plan = rows._jdf.queryExecution().sparkPlan().toString()
    ranks = [line for line in plan.splitlines() if "Window [dense_rank" in line]
    assert len(ranks) == 2 and all(line.count("], [") == 2 for line in ranks)  # each has keys to part by
    got = {r["seq_id"] for r in rows.select("seq_id").distinct().collect()}
    a = ADAPTERS["basket_drift"]
    want = spark.sql(f"select cast({a.seq} as bigint) seq_id, {a.item} item from {a.source}")
    left = rows.select("seq_id", "item").distinct()
    assert got == set(range(1, len(got) + 1)) and left.exceptAll(want.distinct()).isEmpty() and want.distinct().exceptAll(left).isEmpty()


def test_pattern_kinds_at_one_place(spark):
    db = literal(spark, {1: [{"a": 0.5, "b": 0.4}, {"b": 0.9}]}, {"a": 0.5, "b": 0.5})
    wanted = {Pattern(((0, "s"), (1, "i"))): 0.2, Pattern(((0, "s"), (1, "s"))): 0.45}
    assert expected_supports(db.sequences(), list(wanted), "packed", db.flat) == pytest.approx(wanted)


def test_written_sequences_come_from_the_events(spark, sf_dir):
    """what is parsed is read from the events, not made up."""
    from uncertainseq.plans.around import parsed_sequences

    got = parsed_sequences(spark, sf_dir)
    assert got.inputFiles() and all(f.endswith("events.parquet") for f in got.inputFiles())
    want = occurrences(spark, sf_dir, "click_type").select("seq_id", "eid", "item", "p")
    assert not want.isEmpty() and got.exceptAll(want).isEmpty() and want.exceptAll(got).isEmpty()


def test_blocks_hold_what_rows_give(spark, bounds, monkeypatch):
    batches = record_batches(literal(spark, drawn(6), WEIGHTS))
    monkeypatch.setattr(passes, "scanned", lambda rows: rows)
    blocks = passes.blocked(Local(batches)).out
    assert sum(np.frombuffer(b.column(0)[0].as_buffer(), "<i8", 2)[1] for b in blocks) == 24
    for items in (np.arange(6), np.array([1, 4])):
        for got, want in zip(passes.sequences(iter(blocks), items), passes.sequences(iter(batches), items), strict=True):
            assert got.late is not None and want.late is None and got.wide == want.wide
            for a, b in zip((got.seq, got.eid, got.slot, got.p, *got.late), (want.seq, want.eid, want.slot, want.p, *passes.later(want)), strict=True):
                assert a.tolist() == b.tolist()


def test_parts_are_read_as_blocks(spark, sf_dir):
    db = load(spark, sf_dir, "basket_drift")
    plain = Database(db.flat, db.weights, db.names).totals()
    one, two, three = slice_batches(db, [400, 1000, plain.sequences])
    both = one.joined(two).joined(three)
    assert both.pieces == [one, two, three] and both.blocks().count() * 100 < db.packed().count()
    assert vars(both.totals()) == pytest.approx(vars(plain)) and vars(db.totals()) == pytest.approx(vars(plain))
    assert not one.joined(db.between(None, 10)).pieces  # their sequences overlap
    floor = floors(plain, Params(0.002)).frequent
    caps = [{c.pattern: (c.support_cap, c.weight_cap) for c in grow(db.flat, db.weights, floor, packed=rows)} for rows in (db.packed(), both.blocks())]
    assert caps[0].keys() == caps[1].keys() and all(caps[0][p] == pytest.approx(caps[1][p]) for p in caps[0])
