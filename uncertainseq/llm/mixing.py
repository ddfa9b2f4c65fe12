"""Mixing of sources to target weights with DataFrame functions only: exact quotas, a splitting tree, disjoint permuted blocks.

A document is a row, known by its doc_id, source, a hash of its text, and its number among rows that agree in all three. Its place in its
source's order is a 60-bit hash of these, so rows without a doc_id, or with the same one, are drawn one by one. Whole passes over a source come first; the rest
of its target is a prefix of the order, found by sums over 256 ranges of the hash, then over 256 parts of the range at
the cut, then over the documents of that part, so no task holds a source. Documents beyond the cut
that fit close the gap, until none fits.
Ranges of the hash are the blocks, more of them the more shards there are; each copy of a block is a unit. A tree halves the units among shards: at every level a node's
units are drawn without replacement, which gives its halves multivariate-hypergeometric numbers of each source's units.
A shard then takes that many units from the source's permuted order, disjoint from all other shards', and is shuffled
by itself. Only sums by source and block are ever gathered.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from uncertainseq.llm.common import discard, fresh, materialise

WEIGHTS, CAP, SEED, SHARDS = (5, 2, 1), 3, 10, 8
#: Documents, each of the size nearest to what is missing, that are tried before the next prefix of fitting documents.
CLOSING = 4
#: Columns that name a document, with its number ``nth`` among equal rows.
NAMES = ["doc_id", "source", "text_hash"]
#: Equal rows are numbered in runs of so many.
AT_ONCE = 4096


def portable_hash(*parts: Column) -> Column:
    """60 bits of an MD5 of the parts; null counts as empty."""
    text = F.concat_ws("/", *[F.coalesce(p.cast("string"), F.lit("")) for p in parts])
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 15), 16, 10).cast("long")


def sizes(docs: DataFrame, seed: int = SEED) -> DataFrame:
    """(doc_id, source, text_hash, nth, size, place) of all documents: size in words, place in the source's order.

    Equal rows are counted, then numbered from the count, so no task sorts them.
    """
    size = F.coalesce(F.regexp_count("text", F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")
    rows = docs.select("doc_id", "source", F.xxhash64("text").alias("text_hash"), size.alias("size"))
    counted = rows.groupBy(*NAMES, "size").agg(F.count("*").alias("n"))
    runs = counted.select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("n") - 1) / AT_ONCE))).alias("run"))
    last = F.least(F.col("n"), (F.col("run") + 1) * AT_ONCE)
    each = runs.select(*NAMES, "size", F.explode(F.sequence(F.col("run") * AT_ONCE + 1, last)).alias("nth"))
    return each.select(*NAMES, "nth", "size", portable_hash(F.lit(seed), *[F.col(c) for c in NAMES], F.col("nth")).alias("place"))


def targets(base: DataFrame, weights: tuple[int, ...] = WEIGHTS, cap: float = CAP) -> DataFrame:
    """(source, rank, source_size, target): shares by weight, held at ``cap`` times a source's size, the excess shared again."""
    totals = base.groupBy("source").agg(F.sum("size").alias("source_size"))
    order = Window.orderBy(F.col("source").isNull(), "source")
    ranked = totals.withColumn("rank", F.row_number().over(order)).withColumn("weight", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), F.pmod(F.col("rank") - 1, F.lit(len(weights))) + 1))
    rising = Window.orderBy(F.col("source_size") / F.col("weight"), "rank")
    all_rows = Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    levels = ranked.select(
        "*", F.sum("source_size").over(all_rows).alias("total"), (F.lit(cap) * F.col("source_size") / F.col("weight")).alias("full_at"),
        F.coalesce(F.sum(F.col("source_size") * cap).over(rising.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("held"),
        F.sum("weight").over(rising.rowsBetween(Window.currentRow, Window.unboundedFollowing)).alias("open"),
    ).withColumn("level", (F.col("total") - F.col("held")) / F.col("open"))
    first_open = F.min(F.when(F.col("full_at") > F.col("level"), F.struct("full_at", "rank", "level"))).over(all_rows)
    level = F.coalesce(first_open.getField("level"), F.lit(float("inf")))
    return levels.withColumn("water", level).select("source", "rank", "source_size", F.when(F.col("full_at") <= F.col("water"), F.col("source_size") * F.lit(float(cap))).otherwise(F.col("water") * F.col("weight")).alias("target"))


def cuts(placed: DataFrame) -> DataFrame:
    """(rank, cut, gap): documents of place below ``cut`` get one more copy; ``gap`` words are then still missing.

    ``placed``: rank, size, place, rest (words of the source's target beyond its whole passes).
    """

    def narrowed(rows: DataFrame, shift: int, low: DataFrame | None) -> DataFrame:
        """The last range of 2**shift places that begins within the rest, and the words before it."""
        part = F.shiftright("place", shift)
        if low is not None:
            rows = rows.join(low.select("rank", F.col("part").alias("outer"), "before"), "rank").filter(F.shiftright("place", shift + 8) == F.col("outer"))
        keys = ["rank", "rest"] + (["before"] if low is not None else [])
        sums = rows.groupBy(*keys, part.alias("part")).agg(F.sum("size").alias("words"))
        start = F.coalesce(F.sum("words").over(Window.partitionBy("rank").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        sums = sums.withColumn("start", start + (F.col("before") if low is not None else 0))
        return sums.filter("start <= rest").groupBy("rank").agg(F.max(F.struct("part", "start")).alias("at")).select("rank", F.col("at.part").alias("part"), F.col("at.start").alias("before"))

    some = placed.filter("rest > 0 and size > 0")
    outer = narrowed(some, 52, None)
    inner = narrowed(some, 44, outer)
    last = some.join(inner, "rank").filter(F.shiftright("place", 44) == F.col("part"))
    end = F.sum("size").over(Window.partitionBy("rank").orderBy("place").rangeBetween(Window.unboundedPreceding, Window.currentRow)) + F.col("before")
    ends = last.select("rank", "place", "rest", "before", end.alias("end"))
    fits = ends.filter("end <= rest").groupBy("rank").agg(F.max("end").alias("filled"))
    first_out = ends.filter("end > rest").groupBy("rank").agg(F.min("place").alias("cut"))
    found = inner.join(fits, "rank", "left").join(first_out, "rank", "left").join(some.select("rank", "rest").groupBy("rank").agg(F.max("rest").alias("rest")), "rank")
    beyond = F.shiftleft(F.col("part") + 1, 44)
    return found.select("rank", F.coalesce("cut", beyond).alias("cut"), (F.col("rest") - F.coalesce("filled", "before")).alias("gap"))


def filled(placed: DataFrame, cap: float) -> DataFrame:
    """``placed`` (rank, size, place, rest, passes, ...) and ``took``: whether the document gets one more copy.

    After the prefix up to the first document that does not fit, up to ``CLOSING`` documents of the size nearest below the
    gap are taken; then the prefix of what is outside and fits the gap, by the same range sums; and so on until nothing
    outside fits. Last comes the one document that lowers the miss most by going beyond the target.
    """
    cut = materialise(cuts(placed), "cuts")
    state = placed.join(cut, "rank", "left").withColumn("took", F.coalesce(F.col("place") < F.col("cut"), F.lit(False)) & (F.col("size") > 0)).drop("cut", "gap")
    gaps = cut.select("rank", "gap")

    def nearest(closing: DataFrame, fits: str) -> DataFrame:
        outside = state.join(closing, "rank").filter(f"not took and passes < {cap} and size > 0 and {fits} and not array_contains(closing, place)")
        best = outside.groupBy("rank").agg(F.min(F.struct(F.abs(F.col("size") - F.col("gap")).alias("off"), "place", "size")).alias("best"))
        chosen = closing.join(best, "rank", "left")
        return materialise(chosen.select("rank", (F.col("gap") - F.coalesce("best.size", F.lit(0))).alias("gap"), F.when(F.col("best").isNull(), F.col("closing")).otherwise(F.array_append("closing", F.col("best.place"))).alias("closing")), "closing")

    def with_closing(closing: DataFrame) -> DataFrame:
        one = state.join(closing.select("rank", "closing"), "rank", "left")
        return one.withColumn("took", F.col("took") | (F.coalesce(F.array_contains("closing", F.col("place")), F.lit(False)) & (F.col("size") > 0))).drop("closing")

    none, stored = F.array().cast("array<bigint>"), None
    while True:
        closing = gaps.select("rank", "gap", none.alias("closing"))
        for _ in range(CLOSING):
            closing = nearest(closing, "size <= gap")
            if closing.filter("gap >= 1").isEmpty():
                break
        state, gaps = with_closing(closing), closing.select("rank", "gap")
        rest = state.drop("rest").join(gaps.withColumnRenamed("gap", "rest"), "rank").filter(f"not took and passes < {cap} and size > 0 and size <= rest")
        if rest.isEmpty():
            break
        further = materialise(cuts(rest), "cuts")
        held = state.join(gaps.withColumnRenamed("gap", "was"), "rank", "left").join(further.select("rank", "cut"), "rank", "left")
        before, state = stored, materialise(held.withColumn("took", F.col("took") | F.coalesce((F.col("size") > 0) & (F.col("size") <= F.col("was")) & (F.col("place") < F.col("cut")), F.lit(False))).drop("was", "cut"), "filled")
        stored = state
        if before is not None:
            discard(before)
        gaps = materialise(gaps.join(further.select("rank", F.col("gap").alias("now")), "rank", "left").select("rank", F.coalesce("now", "gap").alias("gap")), "gaps")
    return with_closing(nearest(gaps.select("rank", "gap", none.alias("closing")), "abs(size - gap) < gap"))


def copies(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, cap: float = CAP, seed: int = SEED) -> DataFrame:
    """(doc_id, source, text_hash, nth, rank, size, source_size, target, place, copies) of all documents; written, so that every use agrees."""
    base = materialise(sizes(docs, seed), "sizes")
    goal = materialise(targets(base, weights, cap).withColumn("passes", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size") + 1e-12)).otherwise(0).cast("long")), "targets")
    goal = goal.withColumn("rest", F.col("target") - F.col("passes") * F.col("source_size"))
    placed = base.withColumnRenamed("source", "own").join(goal, F.col("own").eqNullSafe(F.col("source"))).drop("own")
    marked = filled(placed, cap)
    more = F.col("took")
    return materialise(marked.select(*NAMES, "nth", "rank", "size", "source_size", "target", "place", (F.col("passes") + more.cast("long")).alias("copies")), "copies")


def block_of(n: int) -> Column:
    """The range of places, of 256 or, for many shards, 32 a shard, that a document lies in."""
    return F.shiftright("place", 60 - max(8, n.bit_length() - 1 + 5))


def shards(planned: DataFrame, n: int = SHARDS, seed: int = SEED) -> DataFrame:
    """(rank, block, copy, shard) of every unit: quotas by a splitting tree, then units of each source in permuted order.

    ``n`` is a power of two. A unit is one copy of the documents of a source whose place lies in one range; see ``block_of``. All units together
    are (sources x ranges x copies), whatever the number of documents.
    """
    if n & (n - 1):
        raise ValueError("the number of shards must be a power of two")
    block = block_of(n).alias("block")
    most = planned.filter("copies > 0").groupBy("rank", block).agg(F.max("copies").alias("most"))
    units = materialise(most.select("rank", "block", F.explode(F.sequence(F.lit(1).cast("long"), F.col("most"))).alias("copy")), "units")
    tree = units.withColumn("shard", F.lit(0).cast("long"))
    level = 1
    while level < n:
        drawn = Window.partitionBy("shard").orderBy(portable_hash(F.lit(seed), F.lit(level), F.col("rank"), F.col("block"), F.col("copy")), "rank", "block", "copy")
        half = F.count("*").over(Window.partitionBy("shard"))
        tree = tree.withColumn("nth", F.row_number().over(drawn)).withColumn("of", half)
        tree = tree.select("rank", "block", "copy", (F.col("shard") * 2 + (F.col("nth") * 2 > F.col("of")).cast("long")).alias("shard"))
        level *= 2
    quotas = tree.groupBy("rank", "shard").agg(F.count("*").alias("quota"))
    by_source = Window.partitionBy("rank").orderBy("shard")
    quotas = quotas.withColumn("end", F.sum("quota").over(by_source.rowsBetween(Window.unboundedPreceding, Window.currentRow))).withColumn("begin", F.col("end") - F.col("quota"))
    permuted = Window.partitionBy("rank").orderBy("copy", portable_hash(F.lit(seed), F.lit("draw"), F.col("rank"), F.col("block"), F.col("copy")), "block")
    numbered = units.withColumn("nth", F.row_number().over(permuted))
    drawn = numbered.join(quotas, "rank").filter("nth > begin and nth <= end")
    return drawn.select("rank", "block", "copy", "shard")


def plan_rows(docs: DataFrame, n: int, weights: tuple[int, ...], cap: float, seed: int) -> DataFrame:
    """The rows of ``copies`` and the shards of each document's copies."""
    planned = copies(docs, weights, cap, seed)
    units = materialise(shards(planned, n, seed), "shards").groupBy("rank", "block").agg(F.sort_array(F.collect_list(F.struct("copy", "shard"))).alias("units"))
    joined = planned.withColumn("block", block_of(n)).join(units, ["rank", "block"], "left")
    where = F.when(F.col("copies") > 0, F.transform(F.slice("units", 1, F.greatest(F.col("copies"), F.lit(1)).cast("int")), lambda u: u["shard"])).otherwise(F.array().cast("array<bigint>"))
    return joined.select(*planned.columns, where.alias("shards"))


def mix_plan(docs: DataFrame, n: int = SHARDS, weights: tuple[int, ...] = WEIGHTS, cap: float = CAP, seed: int = SEED) -> DataFrame:
    """A row per document: doc_id, size, source_size, target, taken, and the shards of its copies.

    Null text has size 0; documents of size 0 are taken in whole passes, which add no words. Null source is a source, the
    last. Every row is a document: rows that share a doc_id, lack one, or are equal in all are drawn one by one. No rows give no rows.
    """
    rows = plan_rows(docs, n, weights, cap, seed)
    return rows.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"), "shards")


def mixture(docs: DataFrame, n: int | None = None, weights: tuple[int, ...] = WEIGHTS, cap: float = CAP, seed: int = SEED) -> DataFrame:
    """The mix itself: a row, with all columns of ``docs``, for every copy taken, grouped by shard and shuffled within it.

    Rows alike in doc_id, source and text are numbered as ``sizes`` does; which of them has which number is left open.
    """
    n = n or 1 << max(3, (int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")) - 1).bit_length())
    text_hash, nth, shards_, copy, shard = (fresh(docs, x) for x in ("text_hash", "nth", "shards", "copy", "shard"))
    taken = plan_rows(docs, n, weights, cap, seed).filter("size(shards) > 0").select(*[F.col(c).alias(f"mixed_{c}") for c in NAMES], F.col("nth").alias("mixed_nth"), F.col("shards").alias("mixed_shards"))
    by_name = taken.groupBy(*[f"mixed_{c}" for c in NAMES]).agg(F.map_from_entries(F.collect_list(F.struct("mixed_nth", "mixed_shards"))).alias("mixed"))
    named = docs.withColumn(text_hash, F.xxhash64("text"))
    keys = [F.col("doc_id"), F.col("source"), F.col(text_hash)]
    numbered = named.withColumn(nth, F.row_number().over(Window.partitionBy(*keys).orderBy(F.lit(1))).cast("long"))
    same = [k.eqNullSafe(F.col(f"mixed_{c}")) for k, c in zip(keys, NAMES, strict=True)]
    rows = numbered.join(by_name, same[0] & same[1] & same[2]).withColumn(shards_, F.try_element_at("mixed", F.col(nth)))
    flat = rows.select(*docs.columns, F.posexplode(shards_).alias(copy, shard))
    order = portable_hash(F.lit(seed), F.lit("order"), F.col("doc_id"), F.xxhash64("text"), F.col(copy))
    return flat.repartition(shard).sortWithinPartitions(shard, order).select(docs.columns)
