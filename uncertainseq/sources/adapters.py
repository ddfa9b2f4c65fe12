"""Databases from the given tables, with the same integer arithmetic in Spark and in SQL."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from uncertainseq.functions.assign import assign_probability, assign_weight, build_dictionary, percent_sql
from uncertainseq.functions.sequences import clean
from uncertainseq.operators.mining import Database
from uncertainseq.operators.passes import in_order

BAND = "cast(least(9, floor(value / 20)) as int)"
LINES = "lineitem join part on l_partkey = p_partkey"
HISTORY = "orders join lineitem on o_orderkey = l_orderkey join part on l_partkey = p_partkey"


@dataclass(frozen=True)
class Adapter:
    """How rows of a table become occurrences; all expressions are valid in both SQL dialects."""

    source: str
    seq: str
    order: str
    item: str
    key: str
    where: str = "true"

    def sql(self, mean: float = 50.0, sd: float = 25.0) -> str:
        """DuckDB: ``flat`` (seq_id, eid, item, p_pct) and ``w`` (item, item_id, w_pct) as common table expressions."""
        return f"""raw as (select cast({self.seq} as bigint) seq_id, {self.order} ord, {self.item} item, cast({self.key} as bigint) k from {self.source} where {self.where}),
flat as (select seq_id, cast(eid as int) eid, item, max(p_pct) p_pct from (select seq_id, dense_rank() over (partition by seq_id order by ord) eid, item, {percent_sql('k', mean, sd)} p_pct from raw) group by 1, 2, 3),
w as (select item, item_id, {percent_sql('item_id * 7919 + 13', 50.0, 12.5)} w_pct from (select item, cast(row_number() over (order by item) - 1 as bigint) item_id from (select distinct item from raw)))"""


ADAPTERS = {
    "click_type": Adapter("events", "user_id * 100 + day(ts)", "ts", "event_type", "event_id"),
    "click_day": Adapter("events", "user_id * 100 + day(ts)", "ts", f"concat(event_type, '_', {BAND})", "event_id"),
    "click_user": Adapter("events", "user_id", "cast(ts as date)", f"concat(event_type, '_', {BAND})", "event_id"),
    "basket_brand": Adapter(LINES, "l_orderkey", "l_linenumber * 100000 + l_partkey", "p_brand", "l_orderkey * 8 + l_linenumber + l_partkey * 131"),
    "basket_part": Adapter(LINES, "l_orderkey", "l_linenumber * 100000 + l_partkey", "cast(l_partkey as string)", "l_orderkey * 8 + l_linenumber + l_partkey * 131"),
    "cust_hist": Adapter(HISTORY, "o_custkey", "o_orderdate", "p_brand", "l_orderkey * 8 + l_linenumber + l_partkey * 131"),
    "cust_type": Adapter(HISTORY, "o_custkey", "o_orderdate", "p_type", "l_orderkey * 8 + l_linenumber + l_partkey * 131"),
    "basket_drift": Adapter(f"(select *, dense_rank() over (order by o_orderdate, o_orderkey) nth, concat(p_brand, '@', cast(floor((year(o_orderdate) - 1995) / 2) as int)) drifting from {HISTORY})", "nth", "l_linenumber * 100000 + l_partkey", "drifting", "l_orderkey * 8 + l_linenumber + l_partkey * 131"),
    "words": Adapter("en_words", "doc_id", "pos", "word", "doc_id * 1000 + pos"),
    "turns": Adapter("turn_words", "conv_id", "turn", "word", "conv_id * 1000 + turn"),
}
#: Sources that Spark reads in a form of its own, with the same rows: orders are ranked within their day, after all orders of earlier days.
SPARK_SOURCES = {
    "basket_drift": f"""(select l_linenumber, l_partkey, l_orderkey, concat(p_brand, '@', cast(floor((year(o_orderdate) - 1995) / 2) as int)) drifting,
  earlier + dense_rank() over (partition by o_orderdate order by o_orderkey) nth
  from {HISTORY} join (select day, sum(n) over (order by day) - n earlier from (select o_orderdate day, count(distinct o_orderkey) n from {HISTORY} group by 1)) on o_orderdate <=> day)""",
}
TABLES = ("events", "lineitem", "part", "orders", "documents", "conversations")
EN_WORDS = "en_words as (select doc_id, unnest(ws) word, generate_subscripts(ws, 1) pos from (select doc_id, regexp_extract_all(lower(text), '[a-z]+') ws from documents where lang = 'en'))"

TURN_WORDS = "turn_words as (select conv_id, turn, unnest(list_distinct(list_concat([role], regexp_extract_all(lower(coalesce(text, '')), '[a-z]+')))) word from conversations)"


def views(spark: SparkSession, sf_dir: str, adapter: Adapter) -> None:
    """Temporary views of the tables that an adapter names."""
    for t in TABLES:
        if t in adapter.source:
            spark.read.parquet(f"{sf_dir}/{t}.parquet").createOrReplaceTempView(t)
    if "en_words" in adapter.source:
        docs = spark.read.parquet(f"{sf_dir}/documents.parquet").filter("lang = 'en'")
        words = docs.select("doc_id", F.posexplode(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))).alias("at", "word"))
        words.select("doc_id", (F.col("at") + 1).alias("pos"), "word").createOrReplaceTempView("en_words")
    if "turn_words" in adapter.source:
        talk = spark.read.parquet(f"{sf_dir}/conversations.parquet")
        words = F.array_distinct(F.concat(F.array("role"), F.regexp_extract_all(F.lower(F.coalesce("text", F.lit(""))), F.lit("[a-z]+"), F.lit(0))))
        talk.select("conv_id", "turn", F.explode(words).alias("word")).createOrReplaceTempView("turn_words")


def occurrences(spark: SparkSession, sf_dir: str, name: str, mean: float = 50.0, sd: float = 25.0) -> DataFrame:
    """(seq_id, batch_id, eid, item, p_pct, p), an item once an event."""
    return drawn(raw_rows(spark, sf_dir, name), mean, sd)


def raw_rows(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(seq_id, ord, item, k) before events are numbered."""
    a = ADAPTERS[name]
    views(spark, sf_dir, a)
    return spark.sql(f"select cast({a.seq} as bigint) seq_id, {a.order} ord, {a.item} item, cast({a.key} as bigint) k from {SPARK_SOURCES.get(name, a.source)} where {a.where}")


def drawn(raw: DataFrame, mean: float, sd: float) -> DataFrame:
    ranked = raw.withColumn("eid", F.dense_rank().over(Window.partitionBy("seq_id").orderBy("ord")))
    best = assign_probability(ranked, F.col("k"), mean, sd).groupBy("seq_id", "eid", "item").agg(F.max("p_pct").alias("p_pct"))
    return best.select("seq_id", F.lit(0).alias("batch_id"), "eid", "item", "p_pct", (F.col("p_pct") / 100.0).alias("p"))


def load(spark: SparkSession, sf_dir: str, name: str, mean: float = 50.0, sd: float = 25.0) -> Database:
    """A database of the given tables; item weights and names are the driver's, a row an item of the alphabet."""
    raw = raw_rows(spark, sf_dir, name)
    weighed = assign_weight(build_dictionary(raw))
    known = weighed.collect()
    flat = in_order(drawn(raw, mean, sd).join(F.broadcast(weighed.select("item", "item_id")), "item")).cache()
    return Database(flat, {r["item_id"]: r["w"] for r in known}, {r["item_id"]: r["item"] for r in known}, _packed=flat)


def literal(spark: SparkSession, sequences: dict[int, list[dict[str, float]]], weights: dict[str, float]) -> Database:
    """A database of literal sequences: id to events, an event from item to probability."""
    ids = {x: k for k, x in enumerate(sorted(weights))}
    rows = [(s, 0, e + 1, ids[x], float(p)) for s, events in sequences.items() for e, event in enumerate(events) for x, p in event.items()]
    flat = spark.createDataFrame(rows, "seq_id long, batch_id int, eid int, item_id int, p double")
    return Database(clean(flat), {ids[x]: w for x, w in weights.items()}, {k: x for x, k in ids.items()})
