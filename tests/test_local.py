import random

import pytest
from pyspark.sql import functions as F

from uncertainseq.model import Params, Stats, floors
from uncertainseq.operators.growth import grow
from uncertainseq.operators.local import mine_groups, mine_rows, register_table_function
from uncertainseq.operators.mining import Database, enumerate_exact, mine_static
from uncertainseq.plans.workloads import WORKED, WORKED_PARAMS, WORKED_WEIGHTS
from uncertainseq.sources.adapters import literal

NAMES = "abcdef"


def drawn(spark, seed, n=14):
    rng = random.Random(seed)
    rows = {s: [{x: rng.randint(1, 9) / 10 for x in rng.sample(NAMES, rng.randint(1, 3))} for _ in range(rng.randint(1, 5))] for s in range(n)}
    return literal(spark, rows, {x: rng.randint(3, 10) / 10 for x in NAMES})


def as_lists(db, ids=None):
    kept = [r for r in db.sequences().collect() if ids is None or r.seq_id in ids]
    return [[{x.item_id: x.p for x in e} for e in r.events] for r in kept]


def as_dicts(lists):
    return {k: {e: items for e, items in enumerate(s, 1)} for k, s in enumerate(lists)}


@pytest.mark.parametrize("seed", [1, 2])
def test_local_miner_against_the_enumerator(spark, seed):
    db = drawn(spark, seed)
    for floor, longest in ((1.0, 4), (2.0, 5)):
        lists = as_lists(db)
        got = dict(mine_rows(as_dicts(lists), db.weights, floor, longest))
        want = enumerate_exact(lists, db.weights, floor, longest)
        assert {p: pytest.approx(s * p.weight(db.weights)) for p, s in got.items()} == want
    assert dict(mine_rows({}, db.weights, 1.0)) == {}


@pytest.mark.parametrize(("cap", "mode"), [("tight", "projected"), ("loose", "global")])
def test_hybrid_growth_finds_the_same_candidates(spark, cap, mode):
    for db, low, longest in ((literal(spark, WORKED, WORKED_WEIGHTS), None, None), (drawn(spark, 3), 1.5, 4)):
        low = low or floors(db.totals(), WORKED_PARAMS).buffer
        shape = lambda found: {c.pattern: (pytest.approx(c.peak), pytest.approx(c.support_cap), pytest.approx(c.weight_cap)) for c in found}
        whole = grow(db.flat, db.weights, low, cap, mode, longest)
        for most in (20, 50, 10_000):
            stats = Stats()
            found = grow(db.flat, db.weights, low, cap, mode, longest, stats=stats, local_rows=most)
            assert shape(found) == {c.pattern: (c.peak, c.support_cap, c.weight_cap) for c in whole} and len(found) == len(whole)
            assert (stats.local_prefixes > 0 or most < 10_000) and stats.n_candidates == len(whole)
    params = Params(0.2, max_len=3)
    assert {s.pattern: s.score for s in mine_static(db, params).patterns} == pytest.approx({s.pattern: s.score for s in mine_static(db, params, local_rows=10_000).patterns})


def test_groups_and_table_function_agree_with_the_enumerator(spark):
    db = drawn(spark, 4, 20)
    key = db.flat.select("seq_id").distinct().select("seq_id", F.when(F.col("seq_id") < 18, F.concat(F.lit("g"), F.col("seq_id") % 2)).alias("segment"))
    params = Params(0.04, max_len=4)
    found = mine_groups(db, key, params)
    register_table_function(spark, db.weights)
    db.flat.join(key, "seq_id").filter("segment is not null").select("segment", "seq_id", "eid", "item_id", "p").createOrReplaceTempView("grouped")
    rows = spark.sql("select * from weighted_patterns(table(grouped) partition by (segment), 0.04, 4)").collect()
    assert sorted(found) == ["g0", "g1"]
    for name, out in found.items():
        ids = {s for s in range(18) if s % 2 == int(name[1])}
        part = Database(db.flat.filter(F.col("seq_id").isin(ids)), db.weights, db.names)
        want = enumerate_exact(as_lists(db, ids), db.weights, floors(part.totals(), params).frequent, 4)
        assert {s.pattern: s.score for s in out.patterns} == pytest.approx(want) and any(p.n_items > 2 for p in want)
        ids_only = {x: str(x) for x in db.names}
        by_function = {r.pattern: r.expected_support * r.pattern_weight for r in rows if r.segment == name}
        assert by_function == pytest.approx({p.text(ids_only): s for p, s in want.items()})
    with pytest.raises(ValueError, match="more than 1 groups"):
        mine_groups(db, key, params, most=1)
