"""Queries around the miners: caps against each other, reports on states, next items, sessions, joins in time; and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from uncertainseq.model import Params
from uncertainseq.operators import relational
from uncertainseq.operators.incremental import BufferedIncrementalMiner
from uncertainseq.operators.local import mine_groups
from uncertainseq.operators.mining import mine_static
from uncertainseq.operators.scoring import node_visits
from uncertainseq.plans.catalogue import PATTERNS, SPLIT, Query, caps_query, caps_sql, cte, enumerated, floor_sql, incremental_query, incremental_sql, mined, mined_sql, rows_of, score, segments_sql
from uncertainseq.plans.worked import simulation_sql
from uncertainseq.runtime import ship
from uncertainseq.sources.adapters import load, occurrences

#: Occurrences of a projection that one task of the hybrid miner grows to its end.
LOCAL_ROWS = 20_000
ITEMS_OF = ",|\\)\\("
HALF_SUPPORT = 0.44


def visits(spark: SparkSession, sf_dir: str) -> DataFrame:
    db = load(ship(spark), sf_dir, "cust_type")
    return node_visits(db.flat, len(db.names))


VISITS_SQL = cte("cust_type") + """,
n as (select count(*) k from w),
l as (select seq_id, count(distinct eid) events, count(*) held from flat group by 1),
p as (select a.seq_id, count(*) pairs from flat a join flat b on b.seq_id = a.seq_id and b.eid > a.eid group by 1)
select events, count(*) sequences, cast(events * count(*) * (select k + k * k from n) as bigint) linear, cast(sum(held + coalesce(pairs, 0)) as bigint) pairwise
from l left join p using (seq_id) group by 1"""


def cap_tightness(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Both caps of every candidate that survives the tight one."""
    tight, loose = (caps_query(c)(spark, sf_dir).select("pattern", F.col("support_cap").alias(c)) for c in ("tight", "loose"))
    return tight.join(loose, "pattern").withColumn("tighter", F.col("tight") < F.col("loose"))


CAP_TIGHTNESS = f"select pattern, a.support_cap tight, b.support_cap loose, a.support_cap < b.support_cap tighter from ({caps_sql('tight')}) a join ({caps_sql('loose')}) b using (pattern)"


def top_by_length(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The three patterns of each length with the largest weighted support, in whole numbers."""
    found = mined("cust_type", 0.3, 2)(spark, sf_dir).withColumn("weighted_support", F.col("support") * F.col("weight"))
    return relational.top_patterns(found, 3, "n_items").select("pattern", "n_items", "weighted_support", "rank")


TOP_BY_LENGTH = f"""select * from (select pattern, n_items, support * weight weighted_support, row_number() over (partition by n_items order by support * weight desc, pattern) "rank"
from ({mined_sql('cust_type', 0.3, 2)})) where "rank" <= 3"""


def state_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Patterns tracked after an increment, by status and length, with subtotals."""
    state = incremental_query(BufferedIncrementalMiner)(spark, sf_dir)
    sized = state.select("status", F.size(F.split("pattern", ITEMS_OF)).alias("n_items"), F.col("support").alias("weighted_support"))
    return relational.state_report(sized).withColumns({"status": F.coalesce("status", F.lit("all")), "n_items": F.coalesce("n_items", F.lit(0))})


STATE_ROLLUP = f"""select coalesce(status, 'all') status, cast(coalesce(n_items, 0) as int) n_items, count(*) n, max(support) best
from (select status, support, cast(len(regexp_split_to_array(pattern, '{ITEMS_OF}')) as int) n_items from ({incremental_sql('buffered')})) group by rollup (status, n_items)"""


def changed(which: str) -> Query:
    """Patterns frequent in one half of the sequences alone."""

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        db = load(ship(spark), sf_dir, "cust_type")
        halves = [mine_static(db.part(f"{SPLIT} = {k}"), Params(HALF_SUPPORT, max_len=2)).patterns for k in (0, 1)]
        was, now = (spark.createDataFrame(rows_of(h, db.names), PATTERNS) for h in halves)
        return (relational.lost_patterns if which == "lost" else relational.gained_patterns)(was, now).select("pattern", "support")

    return query


def changed_sql(which: str) -> str:
    one, other = ("old", "new") if which == "lost" else ("new", "old")
    parts = cte("cust_type") + f",\nold as (select * from flat where {SPLIT} = 0),\nnew as (select * from flat where {SPLIT} = 1)" + enumerated(2, "old", "in_old") + enumerated(2, "new", "in_new")
    frequent = lambda name: f"select pattern, sup from in_{name} where {score()} >= {floor_sql(name, HALF_SUPPORT)} - 1e-9"
    return parts + f"\nselect pattern, sup support from ({frequent(one)}) where pattern not in (select pattern from ({frequent(other)}))"


def item_trend(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Expected support of every item in each of three parts of the sequences, a column a part."""
    rows = occurrences(spark, sf_dir, "cust_type").groupBy("seq_id", "item").agg(F.max("p_pct").alias("p"))
    states = rows.groupBy(F.col("item").alias("pattern"), F.pmod("seq_id", F.lit(3)).alias("batch")).agg(F.sum("p").alias("weighted_support"))
    return relational.pattern_trend(states, [0, 1, 2]).toDF("pattern", "part0", "part1", "part2")


ITEM_TREND = cte("cust_type") + """,
m as (select seq_id, item, max(p_pct) p from flat group by 1, 2)
select item pattern, """ + ", ".join(f"cast(sum(case when seq_id % 3 = {k} then p end) as bigint) part{k}" for k in range(3)) + " from m group by 1"  # fmt: skip


def next_item(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The two items that most likely follow an item, by expected support of the ordered pair."""
    return relational.next_items(occurrences(spark, sf_dir, "click_type"), 2)


FOLLOWS = """,
b as (select x.seq_id, x.item, y.item item2, max(cast(x.p_pct as bigint) * y.p_pct) p from flat x join flat y on x.seq_id = y.seq_id and y.eid > x.eid group by all),
n as (select item, item2, cast(sum(p) as bigint) support, row_number() over (partition by item order by sum(p) desc, item2) "rank" from b group by 1, 2),
nexts as (select * from n where "rank" <= 2)"""
NEXT_ITEM = cte("click_type", FOLLOWS) + "\nselect * from nexts"


def sequence_deviation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Steps of every sequence, and those to an item that is not among the two most likely after the one before."""
    rows = occurrences(spark, sf_dir, "click_type")
    return relational.deviation(rows, relational.next_items(rows, 2))


DEVIATION = cte("click_type", FOLLOWS) + """,
s as (select seq_id, lag(item) over (partition by seq_id order by eid, item) previous, item from flat)
select seq_id, count(*) steps, count(*) filter (where n.item is null) unexpected from s left join nexts n on n.item = s.previous and n.item2 = s.item where previous is not null group by 1"""


def user_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events of a user with less than six hours between neighbours make a session."""
    events = spark.read.parquet(f"{sf_dir}/events.parquet").select("user_id", "ts", "event_id")
    grouped = events.groupBy("user_id", F.session_window("ts", "6 hours")).agg(F.min("event_id").alias("first_event"), F.max("event_id").alias("last_event"), F.count("*").alias("n"))
    return grouped.drop("session_window")


SESSIONS = """with e as (select user_id, event_id, ts, case when ts - lag(ts) over w < interval 6 hours then 0 else 1 end fresh from events window w as (partition by user_id order by ts)),
s as (select *, sum(fresh) over (partition by user_id order by ts rows unbounded preceding) nth from e)
select user_id, min(event_id) first_event, max(event_id) last_event, count(*) n from s group by user_id, nth"""


def timed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/events.parquet").select("user_id", "event_id", "event_type", "value", F.unix_micros(F.col("ts").cast("timestamp")).alias("at"))


def last_value_before(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For every event of the first type, the value of the user's last event of the last type until then."""
    events = timed(spark, sf_dir)
    ends = events.agg(F.min("event_type").alias("first"), F.max("event_type").alias("last"))
    marked = events.join(F.broadcast(ends))
    left = marked.filter("event_type = first").select("user_id", "event_id", "at")
    right = marked.filter("event_type = last").select("user_id", "at", F.col("value").alias("last_value"))
    return relational.as_of(left, right, "user_id", "at", ["last_value"]).select("user_id", "event_id", "last_value")


LAST_VALUE = """with t as (select min(event_type) f, max(event_type) l from events),
a as (select events.* from events, t where event_type = f), b as (select events.* from events, t where event_type = l)
select a.user_id, a.event_id, (select max_by(value, ts) from b where b.user_id = a.user_id and b.ts <= a.ts) last_value from a"""


def events_within(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of a user's events at most an hour apart, counted by their types."""
    events = timed(spark, sf_dir).drop("value")
    near = relational.within(events, events, "user_id", "at", 3_600_000_000.0).filter("event_id < event_id_right")
    return near.groupBy("event_type", F.col("event_type_right").alias("other")).agg(F.count("*").alias("n"))


WITHIN = """select a.event_type, b.event_type other, count(*) n from events a join events b on a.user_id = b.user_id and a.event_id < b.event_id and abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 3600000000 group by 1, 2"""


def event_properties(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events by a property in their JSON text."""
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    return events.groupBy(F.from_json("props", "k bigint").getField("k").alias("k")).agg(F.count("*").alias("n"))


PROPERTIES = "select cast(json_extract_string(props, '$.k') as bigint) k, count(*) n from events group by 1"


def turn_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return relational.profile(occurrences(spark, sf_dir, "turns"))


TURN_PROFILE = cte("turns") + """,
n as (select seq_id, count(*) len from flat group by 1)
select count(*) sequences, cast(sum(len) as bigint) occurrences, cast(max(len) as bigint) longest, (select count(distinct item) from flat) items from n"""


def mine_hybrid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The static miner, with small projections grown to their end in one task each."""
    db = load(ship(spark), sf_dir, "cust_type")
    return spark.createDataFrame(rows_of(mine_static(db, Params(0.3, max_len=2), local_rows=LOCAL_ROWS).patterns, db.names), PATTERNS)


def mine_segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The static miner on the customers of each market segment."""
    db = load(ship(spark), sf_dir, "cust_type")
    key = spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_custkey").cast("long").alias("seq_id"), F.col("c_mktsegment").alias("segment"))
    rows = [(name, r[0], r[3]) for name, found in mine_groups(db, key, Params(0.4, max_len=2)).items() for r in rows_of(found.patterns, db.names)]
    return spark.createDataFrame(rows, "segment string, pattern string, support long")


def parsed_sequences(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The sequences of users' days, written as text and read back from it."""
    written = relational.write_sequence(occurrences(spark, sf_dir, "click_type"))
    events = written.select("seq_id", F.posexplode(relational.parse_sequence(F.col("text"))).alias("eid", "items"))
    return events.select("seq_id", (F.col("eid") + 1).alias("eid"), F.inline("items"))


PARSED = cte("click_type") + "\nselect seq_id, eid, item, p_pct / 100.0::double p from flat"

QUERIES: dict[str, Query] = {
    "node_visits": visits, "cap_tightness": cap_tightness, "topk_by_length": top_by_length, "state_rollup": state_rollup, "lost_patterns": changed("lost"), "gained_patterns": changed("gained"),
    "pattern_trend_pivot": item_trend, "next_item": next_item, "sequence_deviation": sequence_deviation, "session_sequences": user_sessions, "last_value_as_of": last_value_before,
    "events_within_an_hour": events_within, "event_properties": event_properties, "turn_profile": turn_profile, "parsed_sequences": parsed_sequences,
    "mine_hybrid": mine_hybrid, "mine_segments_static": mine_segments,
}
ORACLES: dict[str, str] = {
    "node_visits": VISITS_SQL,
    "paper_simulation": simulation_sql(),
    "cap_tightness": CAP_TIGHTNESS, "topk_by_length": TOP_BY_LENGTH, "state_rollup": STATE_ROLLUP, "lost_patterns": changed_sql("lost"), "gained_patterns": changed_sql("gained"),
    "pattern_trend_pivot": ITEM_TREND, "next_item": NEXT_ITEM, "sequence_deviation": DEVIATION, "session_sequences": SESSIONS, "last_value_as_of": LAST_VALUE,
    "events_within_an_hour": WITHIN, "event_properties": PROPERTIES, "turn_profile": TURN_PROFILE, "parsed_sequences": PARSED,
    "mine_hybrid": mined_sql("cust_type", 0.3, 2), "mine_segments_static": segments_sql(),
}
