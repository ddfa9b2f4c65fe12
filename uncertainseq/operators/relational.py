"""Relational operators around the miners: profiles, pairs, as-of and interval joins, trends, samples, tops, set operations."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def profile(flat: DataFrame, item: str = "item") -> DataFrame:
    """One row: sequences, occurrences, longest sequence, distinct items."""
    lengths = flat.groupBy("seq_id").agg(F.count("*").alias("len")).agg(F.count("*").alias("sequences"), F.sum("len").alias("occurrences"), F.max("len").alias("longest"))
    return lengths.join(F.broadcast(flat.agg(F.countDistinct(item).alias("items"))), how="left")


def distribution_profile(df: DataFrame, column: str, width: int) -> DataFrame:
    return df.groupBy(F.floor(F.col(column) / width).alias("bin")).agg(F.count("*").alias("n"), F.avg(column).alias("mean"))


def pairs(flat: DataFrame, kind: str, item: str = "item") -> DataFrame:
    """Ordered (``s``) or same-event (``i``) pairs of occurrences inside a sequence."""
    other = flat.select("seq_id", F.col("eid").alias("eid2"), F.col(item).alias("item2"), F.col("p").alias("p2"))
    return flat.join(other, "seq_id").filter("eid2 > eid" if kind == "s" else f"eid2 = eid and item2 > {item}")


def as_of(left: DataFrame, right: DataFrame, by: str, on: str, values: list[str]) -> DataFrame:
    """Each left row with the right row's values at or before it: a union and one window, no range join. Ties take the right row."""
    a = left.select("*", F.lit(1).alias("side__"), *[F.lit(None).cast(right.schema[v].dataType).alias(f"{v}__") for v in values])
    b = right.select(*[F.col(c) if c in (by, on) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns], F.lit(0).alias("side__"), *[F.col(v).alias(f"{v}__") for v in values])
    so_far = Window.partitionBy(by).orderBy(on, "side__").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    both = a.unionByName(b)
    filled = both.select(*left.columns, "side__", *[F.last(f"{v}__", ignorenulls=True).over(so_far).alias(v) for v in values])
    return filled.filter("side__ = 1").drop("side__")


def within(left: DataFrame, right: DataFrame, by: str, on: str, delta: float) -> DataFrame:
    """Pairs of rows of one ``by`` whose ``on`` lie at most ``delta`` apart: an equi-join on cells of that width, then the exact test."""
    cell = lambda c: F.floor(F.col(c).cast("double") / delta)
    a = left.withColumn("cell__", F.explode(F.array(cell(on) - 1, cell(on), cell(on) + 1)))
    b = right.select([F.col(c).alias(c if c == by else f"{c}_right") for c in right.columns]).withColumn("cell__", cell(f"{on}_right"))
    return a.join(b, [by, "cell__"]).filter(F.abs(F.col(on).cast("double") - F.col(f"{on}_right").cast("double")) <= delta).drop("cell__")


def add_eid(df: DataFrame, order: list[str]) -> DataFrame:
    return df.withColumn("eid", F.dense_rank().over(Window.partitionBy("seq_id").orderBy(*order)))


def previous_item(flat: DataFrame, item: str = "item") -> DataFrame:
    return flat.withColumn("previous", F.lag(item).over(Window.partitionBy("seq_id").orderBy("eid", item)))


def next_items(flat: DataFrame, k: int) -> DataFrame:
    """(item, item2, support, rank): the k items with the largest expected support of following an item, in whole percents of percents; ties go by name."""
    other = flat.select("seq_id", F.col("eid").alias("eid2"), F.col("item").alias("item2"), F.col("p_pct").cast("long").alias("p2"))
    later = flat.join(other, "seq_id").filter("eid2 > eid").groupBy("seq_id", "item", "item2").agg(F.max(F.col("p_pct") * F.col("p2")).alias("p"))
    support = later.groupBy("item", "item2").agg(F.sum("p").alias("support"))
    return support.withColumn("rank", F.row_number().over(Window.partitionBy("item").orderBy(F.desc("support"), "item2"))).filter(F.col("rank") <= k)


def deviation(flat: DataFrame, expected: DataFrame) -> DataFrame:
    """(seq_id, steps, unexpected): steps from an item to the next one, and those that ``expected`` (item, item2) does not hold."""
    steps = previous_item(flat).filter("previous is not null").select("seq_id", "previous", "item")
    known = expected.select(F.col("item").alias("previous"), F.col("item2").alias("item"), F.lit(1).alias("usual"))
    return steps.join(known, ["previous", "item"], "left").groupBy("seq_id").agg(F.count("*").alias("steps"), F.count(F.when(F.col("usual").isNull(), 1)).alias("unexpected"))


def hash_sample(df: DataFrame, fraction: float, seed: int = 0) -> DataFrame:
    """Whole sequences by a hash of seq_id; for probing thresholds, never for exact results."""
    return df.filter(F.pmod(F.xxhash64(F.lit(seed), F.col("seq_id")), F.lit(1_000_000)) < int(fraction * 1_000_000))


def prune_items(flat: DataFrame, weights: DataFrame, floor: float) -> DataFrame:
    """Rows of items that can be in a frequent pattern: no pattern's expected support exceeds that of any of its items."""
    top = weights.agg(F.max("w")).first()[0] or 0.0
    kept = flat.groupBy("seq_id", "item_id").agg(F.max("p").alias("p")).groupBy("item_id").agg(F.sum("p").alias("s")).filter(F.col("s") * top >= floor - 1e-9).select("item_id")
    return flat.join(kept, "item_id", "left_semi")


def top_patterns(result: DataFrame, k: int, per: str | None = None) -> DataFrame:
    if per is None:
        return result.orderBy(F.desc("weighted_support"), "pattern").limit(k)
    ranked = result.withColumn("rank", F.row_number().over(Window.partitionBy(per).orderBy(F.desc("weighted_support"), "pattern")))
    return ranked.filter(F.col("rank") <= k)


def lost_patterns(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.join(b, "pattern", "left_anti")


def gained_patterns(a: DataFrame, b: DataFrame) -> DataFrame:
    return b.join(a, "pattern", "left_anti")


def pattern_trend(states: DataFrame, batches: list) -> DataFrame:
    """Weighted support of each pattern (pattern, batch, weighted_support), a column a batch."""
    return states.groupBy("pattern").pivot("batch", batches).agg(F.max("weighted_support"))


def state_report(state: DataFrame, mode: str = "rollup") -> DataFrame:
    grouped = {"rollup": state.rollup, "cube": state.cube}[mode]("status", "n_items")
    return grouped.agg(F.count("*").alias("n"), F.max("weighted_support").alias("best"))


def trie_paths(edges: DataFrame) -> DataFrame:
    """(node, depth, path) of every node, by a recursive query over (node, parent, item_id, kind)."""
    edges.createOrReplaceTempView("trie_edges__")
    return edges.sparkSession.sql("""
        with recursive paths(node, depth, path) as (
            select node, 1, concat('(', item_id) from trie_edges__ where parent = 0
            union all
            select e.node, p.depth + 1, concat(p.path, if(e.kind = 's', ')(', ','), e.item_id) from paths p join trie_edges__ e on e.parent = p.node)
        select node, depth, concat(path, ')') path from paths""")


def tokenize(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit("[a-z]+"), F.lit(0))


def write_sequence(rows: DataFrame) -> DataFrame:
    """(seq_id, text): each sequence as text that ``parse_sequence`` reads, from (seq_id, eid, item, p)."""
    inner = F.transform(F.sort_array(F.collect_list(F.struct("item", "p"))), lambda x: F.concat(x["item"], F.lit(":"), x["p"].cast("string")))
    events = rows.groupBy("seq_id", "eid").agg(F.concat(F.lit("("), F.array_join(inner, ", "), F.lit(")")).alias("event"))
    whole = F.transform(F.sort_array(F.collect_list(F.struct("eid", "event"))), lambda x: x["event"])
    return events.groupBy("seq_id").agg(F.array_join(whole, "").alias("text"))


def parse_sequence(text: Column) -> Column:
    """Events of items and probabilities from text such as ``(a:0.9, c:0.6)(b:0.3)``."""
    events = F.regexp_extract_all(text, F.lit(r"\(([^()]*)\)"), F.lit(1))
    return F.transform(events, lambda e: F.transform(F.split(e, r"\s*,\s*"), lambda x: F.struct(F.trim(F.element_at(F.split(x, ":"), 1)).alias("item"), F.element_at(F.split(x, ":"), 2).cast("double").alias("p"))))


def vector_items(embeddings: DataFrame, d: int) -> DataFrame:
    """(vec_id, label, p): cosine to the label's centroid, held within (0, 1]."""
    entry = lambda c, i: F.get(c, F.lit(i)).cast("double")
    centroid = embeddings.groupBy("label").agg(*[F.avg(entry("embedding", i)).alias(f"c{i}") for i in range(d)])
    joined = embeddings.join(centroid, "label")
    dot = sum(entry("embedding", i) * F.col(f"c{i}") for i in range(d))
    norm = F.sqrt(sum(entry("embedding", i) ** 2 for i in range(d))) * F.sqrt(sum(F.col(f"c{i}") ** 2 for i in range(d)))
    return joined.select("vec_id", "label", F.greatest(F.lit(0.01), F.least(F.lit(1.0), F.coalesce(dot / norm, F.lit(0.01)))).alias("p"))
