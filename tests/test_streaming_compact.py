import pytest

from uncertainseq.model import Pattern, Scored
from uncertainseq.operators.compact import closed, maximal
from uncertainseq.operators.incremental import PromisingIncrementalMiner, StateStore
from uncertainseq.plans.workloads import WORKED, WORKED_INCREMENTS, WORKED_PARAMS, WORKED_WEIGHTS
from uncertainseq.sources.adapters import literal
from uncertainseq.streaming.mining import FLAT, read_increments, run_stream


def put(spark, db, folder):
    db.flat.selectExpr("cast(seq_id as long) seq_id", "cast(eid as long) eid", "cast(item_id as int) item_id", "cast(p as double) p").coalesce(1).write.mode("append").parquet(folder)


def test_stream_equals_batches_and_survives_a_restart(spark, tmp_path):
    dbs = [literal(spark, s, WORKED_WEIGHTS) for s in (WORKED, *WORKED_INCREMENTS)]
    plain = PromisingIncrementalMiner(WORKED_PARAMS)
    plain.start(dbs[0], 0)
    for k, db in enumerate(dbs[1:], 1):
        plain.update(db, k)
    source, marks, store = str(tmp_path / "in"), str(tmp_path / "marks"), StateStore(str(tmp_path / "state"))
    for k, db in enumerate(dbs):
        assert db.names == dbs[0].names
        put(spark, db, source)
        if k == 1:
            odd = spark.createDataFrame([(900, 1, 99, 0.5), (901, 1, None, 0.5), (902, 1, 0, 0.0), (903, 1, 0, None)], FLAT)
            odd.coalesce(1).write.mode("overwrite").parquet(str(tmp_path / "odd"))
        miner = PromisingIncrementalMiner(WORKED_PARAMS)  # a driver that starts anew every time
        run_stream(miner, read_increments(spark, source), db.weights, db.names, marks, store).awaitTermination()
        assert miner.batches == list(range(k + 1))
    run_stream(odd_miner := PromisingIncrementalMiner(WORKED_PARAMS), read_increments(spark, str(tmp_path / "odd")), dbs[0].weights, dbs[0].names, str(tmp_path / "odd-marks")).awaitTermination()
    assert odd_miner.batches == [] and odd_miner.state == {}
    assert {p: (pytest.approx(s.score), s.status) for p, s in plain.state.items()} == {p: (s.score, s.status) for p, s in miner.state.items()}


def test_maximal_and_closed_against_all_pairs():
    forms = [([1],), ([2],), ([1], [2]), ([1, 2],), ([1], [1, 2]), ([3],), ([1], [2], [1])]
    supports = [2.0, 1.0, 1.0, 0.5, 0.5, 0.7, 1.0]
    found = [Scored(Pattern.of(*f), s, 1.0) for f, s in zip(forms, supports, strict=True)]

    def above(s):
        return [o for o in found if o is not s and o.pattern.contains(s.pattern)]

    assert maximal(found) == [s for s in found if not above(s)]
    assert closed(found) == [s for s in found if not any(o.support == s.support for o in above(s))]
    assert [s.pattern for s in maximal(found)] == [Pattern.of(*f) for f in (forms[4], forms[5], forms[6])]
    assert maximal([]) == closed([]) == []
