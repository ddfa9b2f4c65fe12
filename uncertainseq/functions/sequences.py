"""Nested and flat forms of a database, and column functions over them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from uncertainseq.model import Pattern


def clean(flat: DataFrame) -> DataFrame:
    """Rows of positive probability, an item once an event with its largest probability."""
    return flat.filter("p > 0").groupBy("seq_id", "batch_id", "eid", "item_id").agg(F.max("p").alias("p"))


def to_sequences(flat: DataFrame) -> DataFrame:
    """A row a sequence: events in order, items of an event in order."""
    events = clean(flat).groupBy("seq_id", "batch_id", "eid").agg(F.sort_array(F.collect_list(F.struct("item_id", "p"))).alias("items"))
    rows = events.groupBy("seq_id", "batch_id").agg(F.sort_array(F.collect_list(F.struct("eid", "items"))).alias("events"))
    return rows.select("seq_id", "batch_id", F.transform("events", lambda e: e["items"]).alias("events"))


def to_flat(db: DataFrame) -> DataFrame:
    """A row an item; eid counts events from 1."""
    events = db.select("seq_id", "batch_id", F.posexplode("events").alias("at", "items"))
    return events.select("seq_id", "batch_id", (F.col("at") + 1).alias("eid"), F.inline("items"))


def suffix_max(flat: DataFrame) -> DataFrame:
    """Add ``later``: the largest probability of the item from its event on in its sequence."""
    after = Window.partitionBy("seq_id", "item_id").orderBy("eid").rowsBetween(Window.currentRow, Window.unboundedFollowing)
    return flat.withColumn("later", F.max("p").over(after))


def as_maps(events: Column) -> Column:
    """Each event as a map from item to probability."""
    return F.transform(events, lambda e: F.map_from_entries(e))


def event_product(event: Column, items: list[int]) -> Column:
    """Product of the items' probabilities in an event; 0 if one is not there."""
    out = F.lit(1.0)
    for x in items:
        out = out * F.coalesce(F.get(F.filter(event, lambda s: s["item_id"] == F.lit(x)), F.lit(0))["p"], F.lit(0.0))
    return out


def best_match(pattern: Pattern, events: Column | str = "events") -> Column:
    """Largest product of probabilities over all occurrences of ``pattern``: one pass over the events, the last pattern event updated first."""
    wanted = pattern.events
    column = F.col(events) if isinstance(events, str) else events

    def step(best: Column, event: Column) -> Column:
        return F.array(F.lit(1.0), *[F.greatest(best[j + 1], best[j] * event_product(event, items)) for j, items in enumerate(wanted)])

    return F.element_at(F.aggregate(column, F.array(F.lit(1.0), *[F.lit(0.0) for _ in wanted]), step), len(wanted) + 1)


def register_functions(spark) -> None:
    """SQL functions: best_match(events, pattern) and pattern_contains(a, b); patterns as text over item ids, such as (3)(4,7)."""
    import pandas as pd

    def parsed(text: str) -> Pattern:
        ids = {x: int(x) for x in text.replace("(", " ").replace(")", " ").replace(",", " ").split()}
        return Pattern.parse(text, ids)

    @F.pandas_udf("double")
    def match(events: pd.Series, pattern: pd.Series) -> pd.Series:
        return pd.Series([match_in(e, parsed(t)) for e, t in zip(events, pattern, strict=True)])

    @F.pandas_udf("boolean")
    def holds(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([parsed(x).contains(parsed(y)) for x, y in zip(a, b, strict=True)])

    spark.udf.register("best_match", match)
    spark.udf.register("pattern_contains", holds)


def match_in(events, pattern: Pattern) -> float:
    """best_match of one sequence in plain Python: events are collections of (item_id, p) rows or dictionaries."""
    wanted = pattern.events
    best = [1.0] + [0.0] * len(wanted)
    for e in events:
        have = {x["item_id"]: x["p"] for x in e}
        for j in range(len(wanted), 0, -1):
            product = best[j - 1]
            for x in wanted[j - 1]:
                product *= have.get(x, 0.0)
            best[j] = max(best[j], product)
    return best[-1]
