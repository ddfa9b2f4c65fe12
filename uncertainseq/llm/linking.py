"""From candidate buckets to classes: verified links between members of a bucket, joined to connected classes.

Exact copies share one member, so a large group of copies costs one row. Members of a bucket are first held against the
bucket's least member; what is linked becomes one class. Where a bucket still has several classes, their least members
are held against each other, and where that leaves classes of several members apart, the members of different classes
are. So no pair in a bucket goes untested unless its members already share a class or its sizes rule a link out, and a
large group of like members costs a row each, not a row a pair. Sizes rule out what is on the rim of a large group: a
member that has many runs of its own cannot be similar enough to any member as large as those around it. All steps are DataFrame operations on narrow rows; intermediate tables are written.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from uncertainseq.llm.common import discard, materialise, small_or_shuffled, text_of
from uncertainseq.llm.jaccard import PARTS

MEASURES = ["id", "root", "size", "most", "half", "parts"]
Verify = Callable[[DataFrame, DataFrame], DataFrame]


def components(edges: DataFrame, start: DataFrame | None = None) -> DataFrame:
    """(id, root) of every end of the edges (a, b); root is the least id of the connected component.

    Each round gives every node the least root around it and then follows roots to their own roots, until nothing changes.
    Roots only fall, and each round's table is written, so a lost executor costs no more than the round at hand.
    """
    both = edges.select(F.col("a").alias("id"), F.col("b").alias("near")).union(edges.select(F.col("b"), F.col("a")))
    both = materialise(both.groupBy("id", "near").count().drop("count"), "links")
    if start is None:
        roots = both.groupBy("id").agg(F.min("near").alias("near")).select("id", F.least("id", "near").alias("root"))
    else:
        ids = both.select("id").distinct()
        roots = ids.join(start, "id", "left").select("id", F.coalesce("root", "id").alias("root"))
    roots = materialise(roots, "roots")
    done = [roots]
    while True:
        around = both.join(roots.select(F.col("id").alias("near"), "root"), "near").groupBy("id").agg(F.min("root").alias("least"))
        stepped = roots.join(around, "id").select("id", F.col("root").alias("was"), F.least("root", "least").alias("root"))
        hooks = stepped.filter(F.col("root") < F.col("was")).groupBy("was").agg(F.min("root").alias("to"))  # an old root follows its members
        jumps = stepped.join(hooks.withColumnRenamed("was", "root"), "root", "left").select("id", "was", F.least("root", F.coalesce("to", "root")).alias("root"))
        new = materialise(jumps, "roots")
        discard(done.pop())
        roots = new.select("id", "root")
        roots.stored_at = new.stored_at
        if new.filter(F.col("root") < F.col("was")).isEmpty():
            discard(both)
            return roots
        done.append(new)


def buckets_of(members: DataFrame) -> DataFrame:
    """(bucket, id, head) of buckets that hold at least two ids, each with the bucket's least id, from (id, keys); stored.

    One aggregate finds the buckets that are shared, most being of one id; only their rows are looked at again.
    """
    flat = members.select("id", F.posexplode("keys").alias("at", "key")).select("id", F.xxhash64("at", "key").alias("bucket"))
    shared = materialise(flat.groupBy("bucket").agg(F.min("id").alias("head"), F.count("*").alias("n")).filter("n > 1").select("bucket", "head"), "shared")
    found = materialise(flat.join(small_or_shuffled(shared), "bucket").select("bucket", "id", "head"), "buckets")
    discard(shared)
    return found


def able(rows: DataFrame, root: str = "root") -> DataFrame:
    """``rows`` (bucket, id, size, most, root) without those that no row of another root in their bucket may link with, by size.

    A row needs a partner no larger than its ``most`` whose own ``most`` is no less than its size. The two least sizes and
    the two greatest ``most`` of different roots settle whether another root has one of each; that is all a bucket sends on.
    """
    by_root = rows.groupBy("bucket", root).agg(F.min("size").alias("low"), F.max("most").alias("high"))
    ends = by_root.groupBy("bucket").agg(
        F.min(F.struct("low", root)).alias("least"), F.max(F.struct("high", root)).alias("most_of"),
    )
    second = by_root.join(ends, "bucket").groupBy("bucket").agg(
        F.first("least").alias("least"), F.first("most_of").alias("most_of"),
        F.min(F.when(F.col(root) != F.col(f"least.{root}"), F.col("low"))).alias("low_two"), F.max(F.when(F.col(root) != F.col(f"most_of.{root}"), F.col("high"))).alias("high_two"),
    )
    low = F.when(F.col(root) == F.col(f"least.{root}"), F.col("low_two")).otherwise(F.col("least.low"))
    high = F.when(F.col(root) == F.col(f"most_of.{root}"), F.col("high_two")).otherwise(F.col("most_of.high"))
    return rows.join(second, "bucket").filter((low <= F.col("most")) & (high >= F.col("size"))).select(rows.columns)


def across(rows: DataFrame, parts: int) -> DataFrame:
    """Pairs (a, b) of different roots in a bucket that sizes and parts do not rule out, from (bucket, id, root, size, most, half, parts)."""
    left = rows.select("bucket", *[F.col(c).alias(f"{c}_a") for c in MEASURES])
    right = rows.select("bucket", *[F.col(c).alias(f"{c}_b") for c in MEASURES])
    on = (left.bucket == right.bucket) & F.expr("id_a < id_b and root_a <> root_b and size_a <= most_b and size_b <= most_a")
    if parts:
        on &= F.expr(" + ".join(f"least(parts_a[{k}], parts_b[{k}])" for k in range(parts)) + " >= half_a + half_b")
    return left.join(right, on).select(F.col("id_a").alias("a"), F.col("id_b").alias("b")).distinct()


def link(buckets: DataFrame, verify: Callable[[DataFrame], DataFrame], sizes: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """Links (a, b) that join all ids whose pairs in a common bucket pass ``verify``; ``buckets`` is a stored table of ``buckets_of``.

    ``sizes``, if given, tells for ids (id) their size, that of their largest possible partner, and what both must share, by parts
    (id, size, most, half, parts); see ``jaccard.partner_sizes``.
    """
    first = buckets.filter("head < id").select(F.col("head").alias("a"), F.col("id").alias("b")).distinct()
    edges = materialise(verify(first), "edges")
    roots = components(edges)
    placed = buckets.join(roots, "id", "left").select("bucket", "id", F.coalesce("root", "id").alias("root"))
    several = placed.groupBy("bucket").agg(F.min("root").alias("low"), F.max("root").alias("high")).filter("low < high").select("bucket")
    placed = materialise(placed.join(several, "bucket", "left_semi"), "placed")
    if sizes:
        known = materialise(sizes(placed.select("id").distinct()), "sizes")
        several_roots, placed = placed, materialise(able(placed.join(known, "id")), "able")
        discard(several_roots, known)
    else:
        placed = placed.withColumns({c: F.lit(0.0) for c in MEASURES[2:]})
    parts = placed.groupBy("bucket", "root").agg(F.min(F.struct("id", *MEASURES[2:])).alias("one"), F.count("*").alias("n")).select("bucket", "root", "one.*", "n")
    spread = parts.groupBy("bucket").agg(F.count("*").alias("parts"), F.max("n").alias("largest")).filter("parts > 1").select("bucket", "largest")
    parts = materialise(parts.join(spread, "bucket"), "parts")
    n_parts = PARTS if sizes else 0
    second = across(parts, n_parts).join(first, ["a", "b"], "left_anti")
    more = materialise(verify(second), "edges")
    if parts.filter("largest > 1").isEmpty():
        return edges.unionByName(more)
    edges = edges.unionByName(more)
    roots = components(edges, roots)
    wide = parts.filter("largest > 1").select("bucket").distinct()
    rest = placed.drop("root").join(wide, "bucket", "left_semi").join(roots, "id", "left").withColumn("root", F.coalesce("root", "id"))
    still = rest.groupBy("bucket").agg(F.min("root").alias("low"), F.max("root").alias("high")).filter("low < high").select("bucket")
    rest = materialise(rest.join(still, "bucket", "left_semi"), "rest")
    third = across(able(rest) if sizes else rest, n_parts)
    third = third.join(first, ["a", "b"], "left_anti").join(second, ["a", "b"], "left_anti")
    return edges.unionByName(materialise(verify(third), "edges"))


def classes(signed: DataFrame, verify: Verify, docs: DataFrame, sizes: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """(doc_id, class_id) of every row of ``signed`` (doc_id, key of equal texts, bands or null).

    ``verify`` takes pairs and texts (doc_id, text), ``sizes`` texts: see ``link``.

    class_id is the least doc_id of the class; null where doc_id is null. Rows of one doc_id are one document.
    """
    known = signed.filter("doc_id is not null")
    firsts = known.groupBy("key").agg(F.min("doc_id").alias("first"))
    named = materialise(known.join(firsts, "key").select("doc_id", "first").distinct(), "copies")
    own = named.groupBy("doc_id").agg(F.min("first").alias("first"))
    members = known.join(named.filter("doc_id = first").select("doc_id").distinct(), "doc_id", "left_semi").filter("bands is not null").select(F.col("doc_id").alias("id"), F.col("bands").alias("keys"))
    members = materialise(members, "members")
    buckets = buckets_of(members)
    some = small_or_shuffled(materialise(buckets.select(F.col("id").alias("doc_id")).distinct(), "wanted"))
    texts = materialise(docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of().alias("text")).join(some, "doc_id", "left_semi"), "texts")
    edges = link(buckets, lambda pairs: verify(pairs, texts), sizes and (lambda ids: sizes(texts.join(ids.withColumnRenamed("id", "doc_id"), "doc_id", "left_semi"))))
    roots = components(edges)
    discard(members, buckets, texts)
    joined = own.join(roots.select(F.col("id").alias("first"), "root"), "first", "left").select("doc_id", F.coalesce("root", "first").alias("class_id"))
    return signed.select("doc_id").join(joined, "doc_id", "left")
