"""Probabilities and weights drawn by integer arithmetic that every SQL engine repeats bit by bit."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

PRIME = 2147483647
MULTIPLIERS = [pow(48271, j + 3, PRIME) for j in range(12)]


def noise_sql(key: str) -> str:
    """About a standard normal draw for an integer key: the sum of twelve uniform ones less six."""
    return "((" + " + ".join(f"((({key}) % {PRIME} + 1) * {m}) % {PRIME}" for m in MULTIPLIERS) + f") / {PRIME}.0 - 6)"


def percent_sql(key: str, mean: float, sd: float) -> str:
    """A whole percent from 1 to 100."""
    return f"cast(least(100, greatest(1, floor({mean} + {sd} * cast({noise_sql(key)} as double) + 0.5))) as int)"


def noise(key: Column) -> Column:
    total = sum((((key % PRIME + 1) * F.lit(m).cast("long")) % PRIME for m in MULTIPLIERS[1:]), ((key % PRIME + 1) * F.lit(MULTIPLIERS[0]).cast("long")) % PRIME)
    return total / F.lit(float(PRIME)) - 6


def assign_probability(df: DataFrame, key: Column, mean: float = 50.0, sd: float = 25.0, policy: str = "clamp") -> DataFrame:
    """Add ``p_pct`` and ``p``; draws outside 1 to 100 percent are held at the ends, or (``resample``) taken from up to three further keys first."""
    draw = lambda k: F.floor(F.lit(float(mean)) + F.lit(float(sd)) * noise(k) + 0.5)
    key = key.cast("long")
    value = draw(key)
    if policy == "resample":
        for n in range(1, 4):
            value = F.when(value.between(1, 100), value).otherwise(draw(key + 1_000_003 * n))
    elif policy != "clamp":
        raise ValueError("policy is clamp or resample")
    return df.withColumn("p_pct", F.least(F.lit(100), F.greatest(F.lit(1), value)).cast("int")).withColumn("p", F.col("p_pct") / 100.0)


def build_dictionary(items: DataFrame, column: str = "item") -> DataFrame:
    """(item_id, item): ids follow the order of labels. One row an item of the alphabet is sorted in one task."""
    return items.select(column).distinct().select((F.row_number().over(Window.orderBy(column)) - 1).cast("int").alias("item_id"), F.col(column).alias("item"))


def assign_weight(dictionary: DataFrame, mean: float = 50.0, sd: float = 12.5) -> DataFrame:
    """(item_id, item, w_pct, w)."""
    drawn = F.floor(F.lit(float(mean)) + F.lit(float(sd)) * noise(F.col("item_id").cast("long") * 7919 + 13) + 0.5)
    return dictionary.withColumn("w_pct", F.least(F.lit(100), F.greatest(F.lit(1), drawn)).cast("int")).withColumn("w", F.col("w_pct") / 100.0)
