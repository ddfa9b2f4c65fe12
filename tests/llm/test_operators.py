import hashlib
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
import xxhash

from uncertainseq.llm import bagminhash, fingerprint, jpeg_media, license_scan, line_dedup, mixing, packing, quality, toxicity, warc
from uncertainseq.llm.jaccard import brute_jaccard

DOCS = "doc_id long, text string, lang string, source string, n_chars long, key string, gone string"
LONG = " ".join(f"word{i}" for i in range(3000))


def docs_of(spark, rows):
    return spark.createDataFrame([(i, t, "en", s, len(t or ""), "k", "g") for i, t, s in rows], DOCS)


@pytest.fixture(scope="module")
def odd(spark):
    """Null and empty texts, a null doc_id, a repeated row, a very long text, equal texts, clashing columns."""
    return docs_of(spark, [(1, None, "a"), (2, "", "a"), (3, LONG, None), (4, "one two three four five six\nseven", "b"), (4, "one two three four five six\nseven", "b"), (5, LONG, "b"), (None, "under the MIT License", "c"), (6, "!!! ???", "c"), (7, "é ü 漢字 😀", "a")])


@pytest.fixture(scope="module")
def none(spark):
    return docs_of(spark, [])


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(i, i % 2, i % 2) for i in range(1, 8)] + [(None, 1, None)], "doc_id long, quality int, toxic int")


def test_license_scan(spark, odd, none):
    assert license_scan.scan(none).count() == 0
    rows = license_scan.scan(odd).collect()
    assert {r.doc_id: (r.n_words, r.n_base, r.base_labels, r.score) for r in rows}[None] == (4, 1, "mit", 1.0)
    text = "x CC BY NC, cc-by-nc! under the mit license version 2; Apache License Version 2 under the mKit license"
    r = license_scan.scan(docs_of(spark, [(1, text, "a")])).first()
    words = re.findall(r"[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text))
    places = [i for p in license_scan.PHRASES.values() for i in range(len(words)) if words[i : i + len(p.split())] == p.split()]
    assert (r.n_words, r.n_base, r.first_word, r.last_word) == (len(words), len(places), min(places), max(places))
    notice = license_scan.NOTICES["notice:mit"].split()
    edited = " ".join(notice[:8] + ["really"] + notice[8:12] + notice[13:])
    assert "notice:mit" in license_scan.scan(docs_of(spark, [(1, edited, "a")])).first().labels


def test_quality_edges(odd, none, labels):
    rows = quality.quality_table(odd, labels).collect()
    assert len(rows) == 9 and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5) for r in rows)
    assert {r.doc_id: r.held_out for r in rows if r.doc_id} == {i: zlib.crc32(str(i).encode()) % 3 == 1 for i in range(1, 8)}
    assert quality.quality_table(none, labels).count() == 0
    assert all(r.score == 0.5 for r in quality.quality_table(odd, labels.limit(0)).collect())


def test_isotonic_is_monotone_and_pools():
    x, y = quality.isotonic(np.array([0.0, 1, 2, 3]), np.array([0.0, 1, 0.5, 1]), np.array([1.0, 1, 1, 1]))
    assert (np.diff(y) >= 0).all() and list(y) == [0.0, 0.75, 1.0] and list(x) == [0.0, 1.5, 3.0]


def test_held_out_quality_and_toxicity(spark, sf_dir):
    from uncertainseq.llm.common import table

    docs, marks = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    known = {r.doc_id: r for r in marks.collect()}
    rows = [r for r in quality.quality_table(docs, marks).collect() if r.held_out and r.doc_id in known]
    assert np.mean([r.predicted == known[r.doc_id].quality for r in rows]) >= 0.85
    rows = [r for r in toxicity.toxicity_table(docs, marks).collect() if r.held_out and r.doc_id in known]
    assert np.mean([r.predicted == known[r.doc_id].toxic for r in rows]) >= 0.85


def test_toxicity_edges(odd, none, labels):
    assert toxicity.toxicity_table(odd, labels).count() == 9
    assert toxicity.toxicity_table(none, labels).count() == 0


def test_packing_covers_every_id_once(odd, none):
    assert packing.pack(none).count() == 0
    encode = packing.Encoder(*packing.default_vocabulary())
    texts = Counter((r.doc_id, r.text or "") for r in odd.collect())
    pieces = packing.pack(odd).collect()
    for (doc, text), n in texts.items():
        ids = np.append(encode.exact.encode(text, add_special_tokens=False).ids, [0]).astype("<u4")
        own = sorted((p.start, p.length, p.ids_crc32) for p in pieces if p.doc_id == doc)
        assert sum(x[1] for x in own) == n * len(ids) and all(p.doc_tokens == len(ids) for p in pieces if p.doc_id == doc)
        assert all(zlib.crc32(ids[s : s + k].tobytes()) == c for s, k, c in own)
    held = {}
    for p in sorted(pieces, key=lambda p: (p.sequence_id, p.offset)):
        assert p.offset == held.get(p.sequence_id, 0)
        held[p.sequence_id] = p.offset + p.length
    assert all(n <= 1024 and n & (n - 1) == 0 for n in held.values())


def test_ids_of_rare_letters_and_special_strings():
    encode = packing.Encoder(*packing.default_vocabulary())
    for text in ("naïve ÅÇ ß́ <|endoftext|> x", "漢字 😀 ა", "  a\n\n b\t", "don't we'll 123abc", "  x"):
        assert list(encode(text)) == encode.exact.encode(text, add_special_tokens=False).ids


def test_warc(spark):
    big = "x" * 1500
    rows = [(1, "http://a\r\nb", big), (2, None, big), (3, "u", None), (4, "u", "small"), (5, "u", "small"), (6, "u", "é" * 600), (None, "u", big)]
    pages = spark.createDataFrame([(*r, "x") for r in rows], "page_id long, url string, html string, keep string")
    got = {r.page_id: r for r in warc.page_records(pages).collect()}
    assert len(got) == 7
    for page, _, html in rows:
        raw = (html or "").encode()
        assert (got[page].payload_bytes, got[page].payload_digest) == (len(raw), hashlib.sha1(raw).hexdigest())
    assert (got[1].record_type, got[1].refers_to, got[2].record_type, got[None].refers_to, got[4].record_type) == ("revisit", 2, "response", 2, "response")
    assert warc.page_records(pages.limit(0)).count() == 0
    r = warc.archive_pages(pages).first()
    assert sum(x["length"] for x in r["index"]) == len(r.content)
    assert warc.per_record(bytes(r.content))[0] == bytes(r.content)


def test_bagminhash_estimates_weighted_jaccard():
    a, b = " ".join(["a b c d e f g h"] * 4 + [f"x{i}" for i in range(40)]), " ".join(["a b c d e f g h"] * 2 + [f"x{i}" for i in range(30)])
    signed, _ = bagminhash.signatures(pa.array([a, b, a]), 4000)
    assert (signed[0] == signed[2]).all()
    assert (signed[0] == signed[1]).mean() == pytest.approx(brute_jaccard(a, b, True), abs=0.04)


def test_near_duplicates(spark, odd, none):
    words = [f"w{i}" for i in range(200)]
    near = words[:100] + ["other"] + words[101:]
    rows = [(10, " ".join(words), "a"), (11, " ".join(near), "a"), (12, " ".join(words[:120]), "a"), (13, " ".join(words), "b"), (14, "few words", "b"), (15, "few words", "b")]
    got = {r.doc_id: r.class_id for r in bagminhash.near_duplicates(docs_of(spark, rows)).collect()}
    assert got == {10: 10, 11: 10, 12: 12, 13: 10, 14: 14, 15: 14}
    assert fingerprint.near_pairs(docs_of(spark, rows)).filter("doc_id <> class_id").count() == 3
    kept = bagminhash.keep_one(docs_of(spark, rows))
    assert sorted(r.doc_id for r in kept.collect()) == [10, 12, 14] and kept.columns == odd.columns
    odd_classes = bagminhash.near_duplicates(odd).collect()
    assert len(odd_classes) == 9 and {r.doc_id: r.class_id for r in odd_classes} == {1: 1, 2: 1, 3: 3, 4: 4, 5: 3, None: None, 6: 6, 7: 7}
    assert bagminhash.near_duplicates(none).count() == 0


def test_fingerprints(odd, none):
    assert fingerprint.fingerprint_table(none).count() == 0
    rows = sorted(odd.collect(), key=lambda r: (r.doc_id is not None, r.doc_id or 0, r.text or ""))
    got = sorted(fingerprint.fingerprint_table(odd).collect(), key=lambda r: (r.doc_id is not None, r.doc_id or 0, r.n_chars))
    texts = [r.text or "" for r in rows]
    for k, r in enumerate(got):
        text, after = texts[k], texts[(k + 1) % len(texts)]
        assert (r.doc_id, r.n_chars) == (rows[k].doc_id, len(text))
        assert r.edited_sha256 == hashlib.sha256((text[: len(text) - len(text) // 2] + after[: len(text) // 2]).encode()).hexdigest()
        assert 0 <= r.near_edited <= 1 and 0 <= r.near_next <= 1
    by_text = {}
    for t, r in zip(texts, got, strict=True):
        assert by_text.setdefault(t, r.fingerprint) == r.fingerprint


def test_jpeg_round_trip_and_general_files(odd, none):
    assert jpeg_media.media_table(none).count() == 0
    for r, d in zip(sorted(jpeg_media.media_table(odd).collect(), key=lambda r: (str(r.doc_id), r.n_bytes)), sorted(odd.collect(), key=lambda r: (str(r.doc_id), len((r.text or "").encode()))), strict=True):
        payload = jpeg_media.pad((d.text or "").encode())
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len((d.text or "").encode()), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]))
    every = bytes(range(256)) * 3
    assert jpeg_media.payload_of(jpeg_media.decode([jpeg_media.encode_payload(jpeg_media.pad(every))])[0]) == jpeg_media.pad(every)
    # one grey block, Huffman codes 0 for a DC size of 3 and for the end of block: DC 5 is 0 101, end of block 0
    s = jpeg_media.segment
    grey = b"\xff\xd8" + s(0xDB, bytes([0]) + bytes([16] * 64)) + s(0xC0, bytes([8, 0, 8, 0, 8, 1, 1, 0x11, 0])) + s(0xC4, bytes([0, 1] + [0] * 15 + [3])) + s(0xC4, bytes([0x10, 1] + [0] * 15 + [0])) + s(0xDA, bytes([1, 1, 0, 0, 63, 0])) + bytes([0b01010111]) + b"\xff\xd9"
    p = jpeg_media.decode([grey])[0]
    assert (p.width, p.height, p.coefficients[0, 0], p.coefficients[0, 1:].any()) == (8, 8, 5, False) and jpeg_media.thumbnail(p)[0, 0] == 5 * 16 / 8 + 128


def test_line_dedup(spark, odd, none):
    line = " ".join(f"considerable{i}" for i in range(60))
    rows = [(1, f"Same line here\n\n{line}", "a"), (2, f"other\n  SAME line   here \n{line.replace('considerable59', 'considerable5')}", "a"), (3, "fresh words only", "a")]
    got = {r.doc_id: (r.text, r.n_lines, r.n_removed) for r in line_dedup.dedup_lines(docs_of(spark, rows)).collect()}
    assert got[1] == (rows[0][1], 3, 0) and got[3] == ("fresh words only", 1, 0)
    assert "SAME" not in got[2][0] and got[2][0].startswith("other")
    clean = line_dedup.dedup_lines(odd.withColumnRenamed("key", "n_lines")).collect()
    assert len(clean) == 9 and {r.doc_id: r.n_removed for r in clean}[5] == 1 and {r.doc_id: r.text for r in clean}[1] is None
    assert line_dedup.dedup_lines(none).count() == 0


def brute_simhash(line):
    words = line.split(" ")
    long = [w for w in words if len(w) >= 5]
    digests = [xxhash.xxh64_intdigest(w.encode(), seed=42) for w in (long if len(long) >= 3 else words)]
    bits = sum(1 << k for k in range(64) if 2 * sum(d >> k & 1 for d in digests) > len(digests))
    return bits - (1 << 64) if bits >> 63 else bits


def test_simhash_is_the_majority_of_bits(spark):
    lines = ["one", "two words", LONG.lower(), "grüße an alle geräte hier", " ".join(["again"] * 29_999)]
    rows = [(k, t, "a") for k, t in enumerate(lines)] + [(7, lines[4], "a")] * 5
    got = {(r.doc_id, r.sim) for r in line_dedup.simhashes(docs_of(spark, rows)).collect()}
    assert got == {(k, brute_simhash(t)) for k, t in enumerate(lines)} | {(7, brute_simhash(lines[4]))}
    over = line_dedup.simhashes(docs_of(spark, [(1, " ".join(["again"] * 30_001), "a"), (2, " \u00a0\t", "a")])).collect()
    assert [(r.doc_id, r.sim) for r in over] == [(1, None)]


def edit_similarity(a, b):
    codes, at = np.frombuffer(b.encode("utf-32-le"), dtype=np.uint32), np.arange(len(b) + 1)
    row = at
    for i, c in enumerate(a, 1):
        new = np.append([i], np.minimum(row[:-1] + (codes != ord(c)), row[1:] + 1))
        row = np.minimum.accumulate(new - at) + at
    return 1 - row[-1] / max(len(a), len(b))


def test_line_recall_against_edit_similarity(spark):
    """Lines of 5 to 400 words, each with a copy whose words were replaced as long as brute force finds edit similarity 0.8."""
    rng = np.random.default_rng(4)
    words = ["".join(rng.choice(list("etaoinshrdlu"), rng.integers(2, 10))) for _ in range(3000)]
    rows, near = [], 0
    for n in [5, 6, 8, 11, 12, 15, 20, 24, 25, 30, 40, 60] * 8 + [100, 200, 400]:
        first = list(rng.choice(words, n))
        copy, last = list(first), None
        for k in rng.permutation(n):
            copy[k] = str(rng.choice(words))
            if edit_similarity(" ".join(first), " ".join(copy)) < 0.8:
                break
            last = " ".join(copy) if copy != first else last
        if last:
            near += 1
            rows += [(2 * near, " ".join(first), "a"), (2 * near + 1, last, "a")]
    got = {r.doc_id: r.n_removed for r in line_dedup.dedup_lines(docs_of(spark, rows)).collect()}
    assert near > 85 and sum(got.values()) >= 0.95 * near
    assert not any(got[2 * k] for k in range(1, near + 1))


def test_lines_of_any_length_become_candidates(spark):
    words = list(np.random.default_rng(5).choice(list("etaoinshrdlucmfw"), (30_500, 3)))
    words = ["".join(w) for w in words]
    lines = spark.createDataFrame([(1, " ".join(words)), (2, " ".join([*words[:17_000], "other", *words[17_001:]])), (3, "apart")], "hash long, line string")
    assert {r.id for r in line_dedup.shared_buckets(line_dedup.minhashes(lines)).collect()} == {1, 2}


def brute_targets(sizes):
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: (5, 2, 1)[k % 3] for k, s in enumerate(order)}
    held, left = {}, set(order)
    while True:
        share = (sum(sizes.values()) - sum(held.values())) / max(1, sum(weight[s] for s in left))
        over = {s for s in left if share * weight[s] > 3 * sizes[s]}
        if not over:
            return held | {s: share * weight[s] for s in left}
        held |= {s: 3 * sizes[s] for s in over}
        left -= over


def test_mixing(spark, odd, none):
    assert mixing.mix_plan(none).count() == 0 and mixing.mix_plan(odd).count() == 9
    rows = [(i, " ".join(["w"] * (1 + i * 7 % 40)), [None, "a", "b", "c"][0 if i % 40 == 0 else 1 + i % 3]) for i in range(600)]
    docs = docs_of(spark, rows)
    got, again = mixing.mix_plan(docs).collect(), mixing.mix_plan(docs.repartition(3)).collect()
    assert sorted(got) == sorted(again)
    sizes, taken = Counter(), Counter()
    source = {i: s for i, _, s in rows}
    for r in got:
        sizes[source[r.doc_id]] += r.size
        taken[source[r.doc_id]] += r.taken
        assert r.taken <= 3 * r.size
    want = brute_targets(sizes)
    for r in got:
        assert r.target == pytest.approx(want[source[r.doc_id]])
    assert all(abs(taken[s] - want[s]) <= 10 for s in want)
    mixed = mixing.mixture(docs, 8)
    assert mixed.count() == sum(len(r.shards) for r in got) and mixed.columns == docs.columns


def test_mixing_goes_on_past_a_dominant_document(spark):
    placed = spark.createDataFrame([(1, 10, k, 2500.0) for k in range(400)] + [(1, 6000, -1, 2500.0)], "rank int, size long, place long, rest double")
    placed = placed.withColumn("place", placed.place + 5).selectExpr("*", "0L passes")
    rows = mixing.filled(placed, 3).collect()
    assert sum(r.size for r in rows if r.took) == 2500


def test_clashing_columns_stay(spark, odd, labels):
    docs = odd.select("*", *[odd.key.alias(c) for c in ("score", "predicted", "shards", "copy", "hash", "bucket", "class_id", "text_")])
    assert quality.keep_good(docs, labels).columns == docs.columns
    assert set(docs.columns) <= set(line_dedup.dedup_lines(docs).columns)
    assert mixing.mixture(docs, 8).columns == docs.columns
    assert bagminhash.keep_one(docs).count() == 7


def test_sizes_rule_out_no_link(spark):
    """A group of near copies of many distances: the same classes as brute force, with and without sizes."""
    from uncertainseq.llm import linking
    from uncertainseq.llm.jaccard import partner_sizes, verified_jaccard

    rng = np.random.default_rng(3)
    base = [f"w{i}" for i in range(120)]
    texts = []
    for n in range(70):
        words = list(base)
        for _ in range(int(rng.integers(0, 7))):
            words[int(rng.integers(0, 120))] = f"x{rng.integers(0, 40)}"
        texts.append(" ".join(words[int(rng.integers(0, 12)) :] + ["tail"] * (n % 3)))
    rows = [(i, t, "a") for i, t in enumerate(dict.fromkeys(texts))]
    docs = docs_of(spark, rows)
    root = list(range(len(rows)))
    for i, a, _ in rows:
        for j, b, _ in rows[:i]:
            if brute_jaccard(a, b, True) >= 0.8:
                old, new = max(root[i], root[j]), min(root[i], root[j])
                root = [new if r == old else r for r in root]
    signed = docs.selectExpr("doc_id", "sha1(text) as key", "array(1L, doc_id % 2) as bands")
    verify = lambda pairs, t: verified_jaccard(pairs, t, 0.8, weighted=True)
    for sizes in (None, lambda t: partner_sizes(t, 0.8, weighted=True)):
        assert {r.doc_id: r.class_id for r in linking.classes(signed, verify, docs, sizes).collect()} == dict(enumerate(root))
    assert 1 < len(set(root)) < len(rows)
