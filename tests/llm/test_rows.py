"""Rows that share a doc_id or lack one, held against brute force."""

from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from uncertainseq.llm import fingerprint, license_scan, line_dedup, mixing
from uncertainseq.llm.jaccard import brute_jaccard


def docs_of(spark, rows):
    return spark.createDataFrame([(i, t, "en", s, len(t or ""), "k") for i, t, s in rows], "doc_id long, text string, lang string, source string, n_chars long, key string")


def test_license_scan_keeps_rows_apart(spark):
    texts = ["under the mit alpha beta", "gamma the mit license beta", "under the mit license beta", "under the mit license beta", None]
    for ident in (None, 7):
        rows = license_scan.scan(docs_of(spark, [(ident, t, "a") for t in texts])).collect()
        assert sorted((r.n_words, r.n_base, r.base_labels) for r in rows) == [(0, 0, ""), (5, 0, ""), (5, 0, ""), (5, 1, "mit"), (5, 1, "mit")]


@pytest.mark.parametrize(("ident", "text"), [(lambda k: None, lambda k: "one two"), (lambda k: k // 2, lambda k: " ".join(["w"] * (k % 9)))])
def test_mixing_draws_rows_one_by_one(spark, ident, text):
    rows = [(ident(k), text(k), "aaaaabbbbc"[k % 10]) for k in range(300)]
    docs = docs_of(spark, rows)
    plan = mixing.mix_plan(docs).collect()
    assert len(plan) == 300 and sorted(plan) == sorted(mixing.mix_plan(docs.repartition(5)).collect())
    taken, target = Counter(), {}
    for r in plan:
        assert r.taken <= 3 * r.size
        taken[r.source_size] += r.taken
        target[r.source_size] = r.target
    assert len(target) == 3 and all(abs(taken[s] - target[s]) <= 9 for s in target)
    mixed = mixing.mixture(docs, 8)
    assert sum(len((r.text or "").split()) for r in mixed.collect()) == sum(taken.values())
    assert mixed.count() == sum(len(r.shards) for r in plan)


def test_many_shards_get_units(spark):
    rows = [(k, "w " * (1 + k % 5), "abc"[k % 3]) for k in range(3000)]
    plan = mixing.mix_plan(docs_of(spark, rows), 256).collect()
    assert len({s for r in plan for s in r.shards}) == 256


def test_line_dedup_null_and_shared_ids(spark):
    same, own = "the very same line of several words here", "a line that nobody else has got at all"
    rows = [(None, same, "a"), (1, same, "a"), (2, f"{own}\n{same}", "a"), (3, f"{own} ever\nx\n{same}", "a"), (3, f"other words\n{same}", "a"), (3, f"other words\n{same}", "a")]
    got = sorted((str(r.doc_id), r.text, r.n_removed) for r in line_dedup.dedup_lines(docs_of(spark, rows)).collect())
    assert ("None", same, 0) in got and ("1", same, 0) in got and ("2", own, 1) in got
    assert ("3", "x", 2) in got and got.count(("3", "other words", 1)) == 2 and len(got) == 6


def test_line_recall_by_length(spark):
    """One word replaced in lines of 5 to 200 words: at least 0.9 of the pairs that brute force finds near are found, in every class of lengths."""
    from tests.llm.test_operators import edit_similarity

    rng = np.random.default_rng(11)
    words = ["".join(rng.choice(list("etaoinshrdlu"), rng.integers(3, 9))) for _ in range(4000)]
    rows, near = [], {}
    for low, high in ((5, 9), (10, 19), (20, 49), (50, 200)):
        for _ in range(60):
            n = int(rng.integers(low, high + 1))
            first = list(rng.choice(words, n))
            copy = list(first)
            copy[int(rng.integers(0, n))] = str(rng.choice(words))
            if copy != first and edit_similarity(" ".join(first), " ".join(copy)) >= 0.8:
                near[len(rows) + 1] = low
                rows += [(len(rows), " ".join(first), "a"), (len(rows) + 1, " ".join(copy), "a")]
    got = {r.doc_id: r.n_removed for r in line_dedup.dedup_lines(docs_of(spark, rows)).collect()}
    assert sum(got.values()) == sum(got[k] for k in near)
    for low in (5, 10, 20, 50):
        pairs = [k for k in near if near[k] == low]
        assert len(pairs) > 40 and sum(got[k] for k in pairs) >= 0.9 * len(pairs)


def test_lines_of_classes_meet(spark):
    """Chains of lines, each near the next, and lines that share a passage but are not near: the groups of brute force."""
    from tests.llm.test_operators import edit_similarity

    rng = np.random.default_rng(5)
    words = ["".join(rng.choice(list("etaoinshrdlu"), 6)) for _ in range(2000)]
    passage, lines = list(rng.choice(words, 40)), []
    for _ in range(6):
        line = list(rng.choice(words, 30))
        for _ in range(8):
            line = list(line)
            for k in rng.choice(30, 4, replace=False):
                line[k] = str(rng.choice(words))
            lines.append(" ".join(line))
    lines += [" ".join([*rng.choice(words, 25), *passage, *rng.choice(words, 25)]) for _ in range(12)]
    root = list(range(len(lines)))
    for i in range(len(lines)):
        for j in range(i):
            if edit_similarity(lines[i], lines[j]) >= 0.8:
                old, new = max(root[i], root[j]), min(root[i], root[j])
                root = [new if r == old else r for r in root]
    got = {r.doc_id: r.n_removed for r in line_dedup.dedup_lines(docs_of(spark, [(k, t, "a") for k, t in enumerate(lines)])).collect()}
    assert got == {k: int(root[k] != k) for k in range(len(lines))} and 12 < len(set(root)) < len(lines)


def test_fingerprints_against_brute_jaccard_with_classes(spark):
    rng = np.random.default_rng(2)
    words = [f"w{k}" for k in range(500)]
    base = list(rng.choice(words, 400))
    texts = []
    for n in (0, 4, 40, 120, 400):
        text = list(base)
        for k in rng.choice(400, n, replace=False):
            text[k] = f"x{k}"
        texts.append(" ".join(text))
    texts += ["few words", "few words", None]
    docs = docs_of(spark, [(k, t, "a") for k, t in enumerate(texts)] + [(None, texts[0], "a")])
    got = {r.doc_id: r for r in fingerprint.fingerprints_and_classes(docs).collect()}
    assert len(got) == 9 and [got[k].class_id for k in (*range(8), None)] == [0, 0, 2, 3, 4, 5, 5, 7, None]
    follows = [*texts[1:], texts[0]]
    for k, (one, two) in enumerate(zip(texts, follows, strict=True)):
        if one and two:
            assert got[k].near_next == pytest.approx(brute_jaccard(one, two, False), abs=0.15)
            assert got[k].near_edited == pytest.approx(brute_jaccard(one, fingerprint.edited(one, two), False), abs=0.15)


def balanced(rows, truth):
    """Mean of the shares of either label that are told right."""
    return np.mean([np.mean([r.predicted == y for r in rows if truth[r.doc_id] == y]) for y in (0, 1)])


def test_learned_scores_beat_constant_and_shuffled_labels(spark):
    """Held-out balanced accuracy at sf0.01; a constant answer has 0.5, and so has a model of shuffled labels, nearly."""
    from uncertainseq.llm import quality, toxicity
    from uncertainseq.llm.common import table

    sf = "/root/testdata/sf0.01"
    docs, marks = table(spark, sf, "documents"), table(spark, sf, "labels").cache()
    known = marks.collect()
    order = np.random.default_rng(0).permutation(len(known))
    mixed = spark.createDataFrame([(r.doc_id, known[k].quality, known[k].toxic) for r, k in zip(known, order, strict=True)], marks.schema)
    for build, label in ((quality.quality_table, "quality"), (toxicity.toxicity_table, "toxic")):
        truth = {r.doc_id: r[label] for r in known}
        held = lambda t: [r for r in t.collect() if r.held_out and r.doc_id in truth]  # noqa: B023, E731
        assert balanced(held(build(docs, marks)), truth) >= 0.8
        assert balanced(held(build(docs, mixed)), truth) <= 0.7


def test_fingerprints_are_joined_as_bytes(spark):
    """op7: no hex text passes through the join with the classes; the rows are those of the table by itself."""
    from uncertainseq.llm import fingerprint

    docs = spark.createDataFrame([(1, "one two three four five six"), (2, "one two three four five six"), (3, None), (4, "seven eight")], "doc_id long, text string")
    got = fingerprint.fingerprints_and_classes(docs)
    plan = got._jdf.queryExecution().optimizedPlan().toString().split("MapInArrow")
    assert plan[0].count("lower(hex(") == 3 and plan[0].index("lower(hex(") < plan[0].index("Join")
    assert sorted(got.drop("class_id").collect(), key=lambda r: r["doc_id"]) == sorted(fingerprint.fingerprint_table(docs).collect(), key=lambda r: r["doc_id"])
    assert {r["doc_id"]: r["class_id"] for r in got.collect()} == {1: 1, 2: 1, 3: 3, 4: 4}


def test_classes_meet_once(spark, monkeypatch):
    """Classes that share many buckets are paired by one row, whether they list their buckets or the buckets list them."""
    rng = np.random.default_rng(11)
    held = sorted({(int(b), int(r)) for b in range(30) for r in rng.choice(25, 8)} | {(b, 99) for b in range(30)})
    ranges = {r: (100 + 3 * r, 110 + 4 * r) for r in [*range(25), 99]}
    want = {
        (x, y) for b, x in held for c, y in held
        if b == c and x < y and max(ranges[x][0], ranges[y][0]) - min(ranges[x][1], ranges[y][1]) <= 0.2 * max(ranges[x][0], ranges[y][0])
    }
    numbers = [f"{letter}{k}" for letter in "st" for k in range(line_dedup.NUMBERS)]
    sized = spark.createDataFrame([(r, 2, *ranges[r]) for r in ranges], "root long, n long, short int, long int")
    sized = sized.selectExpr("*", *[f"cast(null as long) {c}" for c in numbers])
    met = spark.createDataFrame(held, "bucket long, root long")
    listed = met.join(met.groupBy("root").agg(F.collect_set("bucket").alias("at")), "root").join(sized, "root")
    assert sorted((r.root_a, r.root_b) for r in line_dedup.meetings(listed, 0.8).collect()) == sorted(want)
    for most in (256, 12, 0):
        monkeypatch.setattr(line_dedup, "LISTED", most)
        assert sorted((r.small, r.large) for r in line_dedup.class_pairs(met, sized, 0.8).collect()) == sorted(want)
