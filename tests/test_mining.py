import random

import pytest

from uncertainseq.functions.sequences import match_in
from uncertainseq.model import Params, Pattern, PatternTrie, floors
from uncertainseq.operators.growth import grow
from uncertainseq.operators.incremental import BufferedIncrementalMiner, PromisingIncrementalMiner, RemineBaseline, StateStore, completeness, precision
from uncertainseq.operators.mining import enumerate_exact, mine_loose, mine_static
from uncertainseq.operators.scoring import expected_supports
from uncertainseq.plans import workloads
from uncertainseq.plans.catalogue import QUERIES
from uncertainseq.plans.workloads import WORKED, WORKED_INCREMENTS, WORKED_PARAMS, WORKED_WEIGHTS
from uncertainseq.sources.adapters import literal, load


@pytest.fixture(scope="module")
def worked(spark):
    return literal(spark, WORKED, WORKED_WEIGHTS)


def pattern(db, text):
    return Pattern.parse(text, {v: k for k, v in db.names.items()})


def test_worked_floors(worked):
    total = worked.totals()
    assert (total.sequences, total.occurrences, round(total.weight, 6)) == (6, 31, 27.2)
    assert floors(total, Params(0.2, 0.75)).frequent == pytest.approx(0.78968, abs=1e-5)
    assert floors(total, WORKED_PARAMS).buffer == pytest.approx(0.7370, abs=1e-4)


@pytest.mark.parametrize("scorer", ["fold", "trie", "levels", "pairwise"])
def test_scorers_agree_on_worked_supports(worked, scorer):
    expected = {"(a)(b)": 0.57, "(a,c)": 1.20, "(a)": 2.8, "(c)(a)": None, "(a,c)(a)": None}
    patterns = {t: pattern(worked, t) for t in expected}
    got = expected_supports(worked.sequences(), list(patterns.values()), scorer, worked.flat)
    rows = [[[{"item_id": x.item_id, "p": x.p} for x in e] for e in r.events] for r in worked.sequences().collect()]
    for text, value in expected.items():
        brute = sum(match_in(s, patterns[text]) for s in rows)
        assert got[patterns[text]] == pytest.approx(brute if value is None else value)
        assert got[patterns[text]] == pytest.approx(brute)


def test_worked_candidates(worked):
    found = grow(worked.flat, worked.weights, floors(worked.totals(), WORKED_PARAMS).buffer)
    caps = {c.pattern.text(worked.names): round(c.joint_cap, 2) for c in found}
    assert caps == {"(a)": 2.80, "(b)": 1.40, "(c)": 2.00, "(d)": 0.80, "(a)(a)": 2.25, "(a,b)": 0.81, "(a)(b)": 1.08, "(a,c)": 1.80, "(a)(c)": 0.90, "(a,c)(a)": 0.81, "(c)(a)": 0.90}


def test_worked_simulation(spark):
    dbs = [literal(spark, s, WORKED_WEIGHTS) for s in (WORKED, *WORKED_INCREMENTS)]
    expected = {
        BufferedIncrementalMiner: [
            {"frequent": {"(a)": 4.56, "(c)": 4.50, "(a)(a)": 1.90, "(a,c)": 1.99}, "semi": {"(b)": 1.40}},
            {"frequent": {"(a)": 6.16, "(a)(a)": 2.26, "(c)": 5.76}, "semi": {"(a,c)": 2.05, "(b)": 2.20}},
        ],
        PromisingIncrementalMiner: [
            {"frequent": {"(a)": 4.56, "(c)": 4.50, "(a)(a)": 1.90, "(a,c)": 1.99, "(c)(a)": 1.83, "(f)": 1.98}, "semi": {"(b)": 1.40, "(d)": 1.53, "(c)(d)": 1.23, "(c)(f)": 1.25}, "promising": {"(a)(f)": 0.99, "(f)(c)": 0.96}},
            {"frequent": {"(a)": 6.16, "(a)(a)": 2.26, "(c)": 5.76, "(c)(a)": 2.82, "(d)": 2.88, "(f)": 2.61}, "semi": {"(a,c)": 2.05, "(b)": 2.20, "(c)(d)": 2.12}, "promising": {"(a)(d)": 1.15, "(c)(f)": 1.41, "(a)(f)": 1.22, "(e)": 0.77, "(f)(c)": 1.03, "(c)(a)(d)": 0.77}},
        ],
    }
    exact = RemineBaseline(WORKED_PARAMS)
    miners = {m: m(WORKED_PARAMS) for m in expected}
    for k, db in enumerate(dbs):
        truth = set((exact.update(db, k) if k else exact.start(db, k)) and exact.frequent())
        for kind, miner in miners.items():
            state = miner.update(db, k) if k else miner.start(db, k)
            if not k:
                assert {p.text(db.names): round(s.score, 2) for p, s in state.items()} == {"(a)": 2.24, "(b)": 1.40, "(c)": 1.80, "(a)(a)": 1.03, "(a,c)": 1.02}
                continue
            got: dict = {}
            for p, s in state.items():
                got.setdefault(s.status, {})[p.text(db.names)] = s.score
            want = expected[kind][k - 1]
            assert {c: set(v) for c, v in got.items()} == {c: set(v) for c, v in want.items()}
            for c, values in want.items():
                for text, value in values.items():
                    assert got[c][text] == pytest.approx(value, abs=0.0051)
            assert precision(miner.frequent(), truth) == 100
            assert completeness(miner.frequent(), truth) == pytest.approx({BufferedIncrementalMiner: [400 / 7, 300 / 7], PromisingIncrementalMiner: [600 / 7, 600 / 7]}[kind][k - 1])
            before = dict(miner.state)
            assert miner.update(db, k) == before  # the same batch again


def random_database(seed):
    rng = random.Random(seed)
    weights = {x: rng.choice([0.1, 0.4, 0.7, 1.0]) for x in "abcd"}
    rows = {n: [{x: rng.choice([0.1, 0.3, 0.5, 0.8, 1.0]) for x in rng.sample("abcd", rng.randint(1, 3))} for _ in range(rng.randint(1, 5))] for n in range(8)}
    return rows, weights


@pytest.mark.parametrize("seed", range(6))
def test_growth_finds_what_enumeration_finds(spark, seed):
    rows, weights = random_database(seed)
    db = literal(spark, rows, weights)
    params = Params(0.15, max_len=3)
    floor = floors(db.totals(), params).frequent
    names = {v: k for k, v in db.names.items()}
    exact = enumerate_exact([[{names[x]: p for x, p in e.items()} for e in s] for s in rows.values()], db.weights, floor, 3)
    tight, loose = mine_static(db, params, scorer="trie"), mine_loose(db, params)
    for found in (tight, loose):
        assert {s.pattern: round(s.score, 9) for s in found.patterns} == {p: round(v, 9) for p, v in exact.items()}
    assert {c.pattern for c in tight.candidates} <= {c.pattern for c in loose.candidates}
    for c in tight.candidates:
        assert c.support_cap >= tight.supports[c.pattern] - 1e-9


def test_join_at_a_later_match(spark):
    db = literal(spark, {1: [{"a": 0.4}, {"d": 0.1}, {"a": 0.5, "c": 0.6}]}, {"a": 1.0, "c": 1.0, "d": 1.0})
    found = {s.pattern.text(db.names) for s in mine_static(db, Params(0.25)).patterns}
    assert "(a,c)" in found


def test_empty_database(spark):
    db = literal(spark, {1: [{"a": 0.5}]}, {"a": 1.0}).part("seq_id > 5")
    assert mine_static(db, Params(0.1)).patterns == []


def test_trie_deletes_from_the_leaf_up():
    ids = {x: k for k, x in enumerate("abcd")}
    texts = ["(a)", "(a,b)", "(b)", "(a,b)(c)", "(b)(c)", "(c,d)"]
    trie = PatternTrie(Pattern.parse(t, ids) for t in texts)
    assert trie.delete(Pattern.parse("(a,b)(c)", ids)) and trie.find(Pattern.parse("(a,b)", ids)) is not None
    assert trie.delete(Pattern.parse("(b)", ids)) and trie.find(Pattern.parse("(b)(c)", ids)) is not None
    assert not trie.delete(Pattern.parse("(b)", ids))
    again = PatternTrie.from_edges(trie.to_edges())
    assert {p for _, p in again.walk()} == {p for _, p in trie.walk()}


def test_state_survives_a_restart(spark, tmp_path):
    dbs = [literal(spark, s, WORKED_WEIGHTS) for s in (WORKED, *WORKED_INCREMENTS)]
    one = PromisingIncrementalMiner(WORKED_PARAMS)
    one.start(dbs[0], 0)
    one.update(dbs[1], 1)
    StateStore(str(tmp_path)).commit(one)
    two = PromisingIncrementalMiner(WORKED_PARAMS)
    assert StateStore(str(tmp_path)).restore(two)
    assert {p: s.score for p, s in two.update(dbs[2], 2).items()} == {p: s.score for p, s in one.update(dbs[2], 2).items()}


def test_word_patterns_read_whole_texts(spark, tmp_path):
    from uncertainseq.sources.adapters import occurrences

    texts = [" ".join(["early"] * 40 + ["late"]), "one two"]
    spark.createDataFrame([(k, t, "en") for k, t in enumerate(texts)], "doc_id long, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {(r.seq_id, r.eid, r.item) for r in occurrences(spark, str(tmp_path), "words").collect()}
    assert got == {(k, i, w) for k, t in enumerate(texts) for i, w in enumerate(t.split(" "), 1)}


def test_node_visits_count_pairs_of_positions(spark):
    from uncertainseq.operators.scoring import node_visits

    rows = [(1, 1, 0, 0.5), (1, 1, 1, 0.5), (1, 2, 0, 0.5), (1, 3, 1, 0.5), (2, 1, 0, 0.5)]
    flat = spark.createDataFrame(rows, "seq_id long, eid int, item_id int, p double")
    found = {r["events"]: tuple(r)[1:] for r in node_visits(flat, 2).collect()}
    assert found == {3: (1, 18, 4 + 2 + 3), 1: (1, 6, 1)}  # second and third events follow two and three occurrences
    assert node_visits(flat.limit(0), 2).count() == 0


def test_worked_example_equals_its_literal_sql(spark):
    import duckdb

    from uncertainseq.plans.worked import simulation_sql
    from uncertainseq.plans.workloads import simulate_worked_example

    want = {(m, k, s, p): round(v, 2) for m, k, s, p, v in duckdb.sql(simulation_sql()).fetchall()}
    got = {(m, k, s, p): round(v, 2) for m, k, s, p, v in simulate_worked_example(spark)}
    assert got == want and len(got) == 47


@pytest.mark.parametrize("name", ["initial_size_sweep", "update_ratio_sweep"])
def test_sweeps_mine_more_than_single_items(spark, sf_dir, monkeypatch, name):
    taken = []
    monkeypatch.setattr(workloads, "incremental_run", lambda parts, params, *_, **__: taken.append(params) or [])
    assert QUERIES[name](spark, sf_dir).count() == 0
    assert {p.max_len for p in taken} == {None}
    found = mine_static(load(spark, sf_dir, "basket_drift"), taken[0]).patterns
    frequent = [s.pattern.n_items for s in found if s.status == "frequent"]
    assert sum(n > 1 for n in frequent) > sum(n == 1 for n in frequent)


def test_growth_to_the_end_of_every_sequence(spark):
    db = literal(spark, {1: [{"a": 1.0}, {"b": 1.0}], 2: [{"a": 1.0}, {"b": 1.0}]}, {"a": 1.0, "b": 1.0})
    assert sorted(s.pattern.text(db.names) for s in mine_static(db, Params(0.5)).patterns) == ["(a)", "(a)(b)", "(b)"]


def test_update_sweep_keeps_no_parts(spark, sf_dir, monkeypatch):
    held = []
    monkeypatch.setattr(workloads, "incremental_run", lambda parts, *_, **__: held.extend((p, p.blocks()) for p in parts) or [])
    workloads.update_ratio_sweep(load(spark, sf_dir, "basket_drift"), 0.0005, 0.2, [0.1], None, (1,))
    assert len(held) == 2 and all(p._blocks is None and not b.is_cached for p, b in held)
