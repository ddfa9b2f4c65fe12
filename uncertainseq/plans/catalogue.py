"""Registered queries over the given tables, and DuckDB SQL that enumerates instead of growing by caps."""

from __future__ import annotations

from collections.abc import Callable
from itertools import product

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from uncertainseq.functions.assign import assign_weight, build_dictionary
from uncertainseq.functions.sequences import best_match, suffix_max, to_flat, to_sequences
from uncertainseq.model import Params, Pattern, floors
from uncertainseq.operators import relational
from uncertainseq.operators.compact import closed, maximal
from uncertainseq.operators.growth import grow
from uncertainseq.operators.incremental import BufferedIncrementalMiner, PromisingIncrementalMiner, RemineBaseline, transitions
from uncertainseq.operators.mining import Database, mine_by_group, mine_loose, mine_static
from uncertainseq.operators.scoring import expected_supports
from uncertainseq.plans import workloads
from uncertainseq.runtime import ship
from uncertainseq.sources.adapters import ADAPTERS, EN_WORDS, TURN_WORDS, load, occurrences

Query = Callable[[SparkSession, str], DataFrame]
PATTERNS = "pattern string, n_items int, n_events int, support bigint, weight bigint"


def rows_of(scored, names) -> list[tuple]:
    """Patterns with whole-number measures: support times 100 to the length, weight as a sum of percents."""
    return [(s.pattern.text(names), s.pattern.n_items, s.pattern.n_events, round(s.support * 100**s.pattern.n_items), round(s.weight * 100 * s.pattern.n_items)) for s in scored]


def cte(name: str, extra: str = "", sd: float = 25.0) -> str:
    a = ADAPTERS[name]
    words = {"en_words": EN_WORDS + ",\n", "turn_words": TURN_WORDS + ",\n"}.get(a.source, "")
    return "with " + words + a.sql(sd=sd) + extra


def enumerated(max_len: int, rows: str = "flat", name: str = "pats", shapes: list[tuple[str, ...]] | None = None) -> str:
    """A table of all patterns up to a length, by self-joins: pattern, n_items, n_events, sup, wsum."""
    parts = []
    for n in range(1, max_len + 1):
        for kinds in shapes or product("si", repeat=n - 1):
            if len(kinds) != n - 1:
                continue
            tables = [f"{name}_f f{k}" for k in range(n)]
            on = [f"f{k}.seq_id = f0.seq_id and " + (f"f{k}.eid > f{k - 1}.eid" if kind == "s" else f"f{k}.eid = f{k - 1}.eid and f{k}.item_id > f{k - 1}.item_id") for k, kind in enumerate(kinds, 1)]
            text = "'(' || f0.item" + "".join((" || ')(' || " if kind == "s" else " || ',' || ") + f"f{k}.item" for k, kind in enumerate(kinds, 1)) + " || ')'"
            value, weight = " * ".join(f"cast(f{k}.p_pct as bigint)" for k in range(n)), " + ".join(f"f{k}.w_pct" for k in range(n))
            parts.append(f"select pattern, {n} n_items, {1 + sum(k == 's' for k in kinds)} n_events, cast(sum(best) as bigint) sup, cast(any_value(ws) as bigint) wsum from (select f0.seq_id, {text} pattern, max({value}) best, any_value({weight}) ws from {' join '.join([tables[0]] + [f'{t} on {o}' for t, o in zip(tables[1:], on, strict=True)])} group by 1, 2) group by 1")
    return f",\n{name}_f as (select seq_id, eid, item, p_pct, w_pct, item_id from {rows} join w using (item)),\n{name} as ({' union all '.join(parts)})"


def floor_sql(rows: str = "flat", min_sup: float = 0.0, factor: float = 1.0, unit: bool = False) -> str:
    mean = "1.0" if unit else f"(select sum(w_pct) / (100.0 * count(*)) from {rows} join w using (item))"
    return f"({min_sup} * {factor} * (select count(distinct seq_id) from {rows}) * {mean})"


def score(n: str = "n_items", unit: bool = False) -> str:
    weight = "1.0" if unit else f"(wsum / (100.0 * {n}))"
    return f"(sup / pow(100.0, {n}) * {weight})"


def mined_sql(name: str, min_sup: float, max_len: int, factor: float = 1.0, unit: bool = False) -> str:
    weight = "n_items * 100" if unit else "wsum"
    return cte(name, enumerated(max_len)) + f"\nselect pattern, cast(n_items as int) n_items, cast(n_events as int) n_events, sup support, cast({weight} as bigint) weight from pats where {score(unit=unit)} >= {floor_sql(min_sup=min_sup, factor=factor, unit=unit)} - 1e-9"


def mined(name: str, min_sup: float, max_len: int, unit: bool = False, loose: bool = False, factor: float = 1.0, keep: Callable[[list], list] = list) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        db = load(ship(spark), sf_dir, name)
        base = db.unit() if unit else db
        found = mine_loose(base, Params(min_sup, factor, max_len=max_len)) if loose else mine_static(base, Params(min_sup, factor, max_len=max_len))
        return spark.createDataFrame(rows_of(keep(found.patterns), db.names), PATTERNS)

    return query


def compact_sql(name: str, min_sup: float, also: str = "") -> str:
    """Of patterns of one or two items, those that no longer one contains (and, for closed ones, at the same support)."""
    return f"""with m as ({mined_sql(name, min_sup, 2)})
select * from m where n_items = 2 or not exists (
  select 1 from m o where o.n_items = 2 and list_contains(regexp_split_to_array(o.pattern, '[(),]+'), regexp_replace(m.pattern, '[()]', '', 'g')) {also})"""


def flat_query(name: str, then: Callable[[DataFrame], DataFrame]) -> Query:
    return lambda spark, sf_dir: then(occurrences(spark, sf_dir, name))


def all_of_shape(name: str, kinds: tuple[str, ...], scorer: str) -> Query:
    """Expected supports of every pattern of one shape that occurs."""

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        db = load(ship(spark), sf_dir, name)
        items = sorted(db.names)
        patterns = []
        for chosen in product(items, repeat=len(kinds) + 1):
            if all(k == "s" or b > a for a, b, k in zip(chosen, chosen[1:], kinds, strict=False)):
                patterns.append(Pattern(((chosen[0], "s"), *zip(chosen[1:], kinds, strict=True))))
        supports = expected_supports(db.sequences(), patterns, scorer, db.flat)
        return spark.createDataFrame([(p.text(db.names), round(v * 100**p.n_items)) for p, v in supports.items() if v > 0], "pattern string, support bigint")

    return query


def shape_sql(name: str, kinds: tuple[str, ...]) -> str:
    return cte(name, enumerated(len(kinds) + 1, shapes=[kinds])) + "\nselect pattern, sup support from pats"


def weights_query(name: str) -> Query:
    return lambda spark, sf_dir: assign_weight(build_dictionary(occurrences(spark, sf_dir, name))).select("item", F.col("item_id").cast("long").alias("item_id"), "w_pct")


def flattened(spark: SparkSession, sf_dir: str) -> DataFrame:
    db = load(spark, sf_dir, "cust_type")
    return to_flat(to_sequences(db.flat)).select("seq_id", F.col("eid").cast("int").alias("eid"), F.col("item_id").cast("long").alias("item_id"), F.round(F.col("p") * 100).cast("int").alias("p_pct"))


def profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = [relational.profile(occurrences(spark, sf_dir, n)).select(F.lit(n).alias("name"), "*") for n in ("click_type", "click_day", "click_user", "basket_brand", "cust_hist")]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def profile_sql() -> str:
    one = "(select seq_id, count(*) len from ({f}) group by 1)"
    return "\nunion all\n".join(f"select '{n}' as name, count(*) sequences, cast(sum(len) as bigint) occurrences, cast(max(len) as bigint) longest, (select count(distinct item) from ({cte(n)} select * from flat)) items from {one.format(f=cte(n) + ' select * from flat')}" for n in ("click_type", "click_day", "click_user", "basket_brand", "cust_hist"))


def totals_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = occurrences(spark, sf_dir, "basket_brand")
    w = assign_weight(build_dictionary(rows)).select("item", "w_pct")
    return rows.join(F.broadcast(w), "item").agg(F.countDistinct("seq_id").alias("sequences"), F.count("*").alias("occurrences"), F.sum("w_pct").alias("weight_pct"))


def floors_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    db = load(spark, sf_dir, "click_day")
    f = floors(db.totals(), Params(0.02, 0.75, 0.7), db.totals())
    return spark.createDataFrame([(round(f.frequent, 6), round(f.buffer, 6), round(f.local, 6))], "frequent double, buffer double, local double")


def best_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    db = load(spark, sf_dir, "click_type")
    first, second = sorted(db.names)[:2]
    return db.sequences().select("seq_id", F.round(best_match(Pattern(((first, "s"), (second, "s")))) * 10_000).cast("bigint").alias("best")).filter("best > 0")


def caps_query(cap: str) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        db = load(ship(spark), sf_dir, "cust_type")
        floor = floors(db.totals(), Params(0.3)).frequent
        found = grow(db.flat, db.weights, floor, cap, max_len=2)
        return spark.createDataFrame([(c.pattern.text(db.names), round(c.peak, 6), round(c.support_cap, 4), round(c.weight_cap, 6), round(c.joint_cap, 4)) for c in found], "pattern string, peak double, support_cap double, weight_cap double, joint_cap double")

    return query


def caps_cte(name: str, cap: str, min_sup: float, levels: int, unit: bool = False, bound: str = "projected", sd: float = 25.0) -> str:
    """Growth by caps, unrolled: c1, c2, ... hold the candidates of each length, ``found`` all of them."""
    part = "t.total" if cap == "tight" else "t.best * t.n"
    weight = "1.0::double" if unit else "w_pct / 100.0"
    floor = floor_sql(min_sup=min_sup, unit=unit)
    heaviest = "max(t.wt) over (partition by t.prefix)" if bound == "projected" else "(select max(wt) from s)"
    out = cte(name, sd=sd) + f""",
s as (select seq_id, eid, item, item_id, {weight} wt,
  max(p_pct) over (partition by seq_id, item order by eid rows between current row and unbounded following) / 100.0 p
  from flat join w using (item)),
c0 as (select '' pattern, 1.0::double peak, 0.0::double heavy),
x1 as (select seq_id, '' as prefix, 's' kind, item, item_id, wt, eid, p from s)"""
    for k in range(1, levels + 1):
        out += f""",
t{k} as (select prefix, kind, item, item_id, any_value(wt) wt, sum(m) total, max(m) best, count(*) n from
  (select prefix, kind, item, item_id, seq_id, any_value(wt) wt, max(p) m from x{k} group by prefix, kind, item, item_id, seq_id)
  group by prefix, kind, item, item_id),
c{k} as (select * from (
  select case t.kind when 's' then t.prefix || '(' || t.item || ')' else left(t.prefix, length(t.prefix) - 1) || ',' || t.item || ')' end pattern,
    t.prefix, t.kind, t.item, t.item_id, c.peak * t.best peak, c.peak * {part} support_cap,
    greatest({heaviest}, c.heavy, t.wt) weight_cap, greatest(c.heavy, t.wt) heavy
  from t{k} t join c{k - 1} c on c.pattern = t.prefix) where support_cap * weight_cap >= {floor} - 1e-9)"""
        if k < levels:
            out += f""",
e{k} as (select distinct x.seq_id, c.pattern, c.item_id, x.eid from x{k} x join c{k} c on c.prefix = x.prefix and c.kind = x.kind and c.item = x.item),
f{k} as (select seq_id, pattern, min(eid) low from e{k} group by seq_id, pattern),
x{k + 1} as (select f.seq_id, f.pattern prefix, 's' kind, s.item, s.item_id, s.wt, s.eid, s.p from f{k} f join s on s.seq_id = f.seq_id and s.eid > f.low
  union all select e.seq_id, e.pattern, 'i', s.item, s.item_id, s.wt, s.eid, s.p from e{k} e join s on s.seq_id = e.seq_id and s.eid = e.eid and s.item_id > e.item_id)"""
    every = " union all ".join(f"select pattern, peak, support_cap, weight_cap from c{k}" for k in range(1, levels + 1))
    return out + f",\nfound as ({every})"


def caps_sql(cap: str) -> str:
    return caps_cte("cust_type", cap, 0.3, 2) + """
select pattern, round(peak, 6) peak, round(support_cap, 4) support_cap, round(weight_cap, 6) weight_cap, round(support_cap * weight_cap, 4) joint_cap from found"""


def counts_sql(name: str, cap: str, min_sup: float, max_len: int, unit: bool = False, bound: str = "projected", sd: float = 25.0) -> str:
    """One row: how many candidates growth gives, and how many patterns enumeration finds frequent."""
    frequent = f"{score(unit=unit)} >= {floor_sql(min_sup=min_sup, unit=unit)} - 1e-9"
    return caps_cte(name, cap, min_sup, max_len, unit, bound, sd) + enumerated(max_len) + f"""
select cast((select count(*) from found) as int) candidates, cast((select count(*) from pats where {frequent}) as int) frequent"""


def miners_sql(name: str, supports: list[float], max_len: int, spreads: tuple[float, ...] = ()) -> str:
    """Counts of the static and the loose-cap miner at unit weights, over supports, or over spreads at one support."""
    cases = [("sd", sd, supports[0], 100 * sd) for sd in spreads] or [("min_sup", x, x, 25.0) for x in supports]
    return "\nunion all\n".join(
        f"select {x}::double {label}, '{miner}' miner, candidates, frequent, case when candidates > 0 then 100::double * (candidates - frequent) / candidates else 0 end false_positives "
        f"from ({counts_sql(name, miner, sup, max_len, True, 'projected' if miner == 'tight' else 'global', sd)})"
        for label, x, sup, sd in cases
        for miner in ("tight", "loose")
    )


def bounds_sql(name: str, min_sup: float, max_len: int) -> str:
    return "\nunion all\n".join(f"select '{b}' as mode, candidates from ({counts_sql(name, 'tight', min_sup, max_len, bound=b)})" for b in ("projected", "global"))


def units_sql(name: str, min_sup: float, max_len: int) -> str:
    frequent = [f"{score(unit=unit)} >= {floor_sql(min_sup=min_sup, unit=unit)} - 1e-9" for unit in (False, True)]
    both = f"(select cast(count(*) as int) from ({cte(name, enumerated(max_len))} select * from pats where {' and '.join(frequent)}))"
    return "\nunion all\n".join(f"select '{m}' as mode, candidates, frequent, {both} as both from ({counts_sql(name, 'tight', min_sup, max_len, unit)})" for m, unit in (("weighted", False), ("unit", True)))


def transitions_sql(name: str, min_sup: float, ratio: float) -> str:
    """Classes before and after the second half of the sequences (ids from 1 without gaps), with the promising patterns of that half."""
    half = "(select count(distinct seq_id) // 2 from flat)"
    own = f"{2 * min_sup * ratio} * (select count(distinct seq_id) from new) * (select sum(w_pct) / (100.0 * count(*)) from new join w using (item))"
    return cte(name) + f""",
old as (select * from flat where seq_id <= {half}),
new as (select * from flat where seq_id > {half})""" + enumerated(2, "old", "was") + enumerated(2, "new", "got") + f""",
before as (select pattern, n_items, wsum, sup, case when {score()} >= {floor_sql('old', min_sup)} - 1e-9 then 'frequent' else 'semi' end status
  from was where {score()} >= {ratio} * {floor_sql('old', min_sup)} - 1e-9),
merged as (select b.pattern, b.n_items, b.wsum, b.sup + coalesce(g.sup, 0) sup, b.status from before b left join got g using (pattern)
  union all select pattern, n_items, wsum, sup, 'dropped' from got where {score()} >= {own} - 1e-9 and pattern not in (select pattern from before)),
moved as (select status, {score()} s from merged)
select status as was, case when s >= {floor_sql(min_sup=min_sup)} - 1e-9 then 'frequent' when s >= {ratio} * {floor_sql(min_sup=min_sup)} - 1e-9 then 'semi'
  when s >= {own} - 1e-9 then 'promising' else 'dropped' end became, count(*) patterns from moved group by 1, 2"""


def sweep_factor(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.createDataFrame(workloads.weight_factor_sweep(load(ship(spark), sf_dir, "cust_type"), 0.3, [0.5, 0.75, 1.0, 1.25, 1.5], 2), "factor double, frequent long")


SPLIT = "seq_id % 2"


def incremental_query(miner: type) -> Query:
    """State after half of the sequences (even ids) and an increment of the other half."""

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        db = load(ship(spark), sf_dir, "cust_type")
        m = miner(Params(0.3, buffer_ratio=0.7, max_len=2))
        m.start(db.part(f"{SPLIT} = 0"), 0)
        state = m.update(db.part(f"{SPLIT} = 1"), 1)
        kept = [(p.text(db.names), s.status, round(s.support * 100**p.n_items)) for p, s in state.items()]
        return spark.createDataFrame(kept, "pattern string, status string, support bigint")

    return query


def incremental_sql(kind: str) -> str:
    base = cte("cust_type") + f",\nold as (select * from flat where {SPLIT} = 0),\nnew as (select * from flat where {SPLIT} = 1)" + enumerated(2, "old", "was") + enumerated(2, "new", "got")
    if kind == "remine":
        return cte("cust_type", enumerated(2)) + f"\nselect pattern, 'frequent' status, sup support from pats where {score()} >= {floor_sql(min_sup=0.3)} - 1e-9"
    local = f"{2 * 0.3 * 0.7} * (select count(distinct seq_id) from new) * (select sum(w_pct) / (100.0 * count(*)) from new join w using (item))"
    fresh = f" union all select g.pattern, g.n_items, g.wsum, g.sup from got g where {score()} >= {local} - 1e-9 and g.pattern not in (select pattern from tracked)" if kind == "promising" else ""
    drop = f"when s >= {local} - 1e-9 then 'promising'" if kind == "promising" else ""
    return base + f""",
tracked as (select * from was where {score()} >= 0.7 * {floor_sql('old', 0.3)} - 1e-9),
merged as (select t.pattern, t.n_items, t.wsum, t.sup + coalesce(g.sup, 0) sup from tracked t left join got g using (pattern){fresh}),
named as (select pattern, sup, {score()} s from merged),
out as (select pattern, case when s >= {floor_sql(min_sup=0.3)} - 1e-9 then 'frequent' when s >= 0.7 * {floor_sql(min_sup=0.3)} - 1e-9 then 'semi' {drop} end status, cast(sup as bigint) support from named)
select * from out where status is not null"""


def transitions_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    db = load(ship(spark), sf_dir, "basket_drift")
    m = PromisingIncrementalMiner(Params(0.005, buffer_ratio=0.7, max_len=2))
    total = db.totals().sequences
    parts = workloads.slice_batches(db, [total // 2, total])
    before = dict(m.start(parts[0], 0))
    return spark.createDataFrame([(a, b, n) for (a, b), n in transitions(before, m.update(parts[1], 1)).items()], "was string, became string, patterns long")


def increments_of(db: Database, initial: float, n: int) -> list[Database]:
    return workloads.slice_batches(db, workloads.cuts([1.0] * n, db.totals().sequences, initial))


CURVE = "miner string, batch int, seconds double, completeness double, precision double, frequent int"


def completeness_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.createDataFrame(workloads.incremental_run(increments_of(load(ship(spark), sf_dir, "basket_drift"), 0.2, 4), Params(0.005, buffer_ratio=0.7, max_len=2)), CURVE)


def ratio_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = increments_of(load(ship(spark), sf_dir, "basket_drift"), 0.2, 2)
    return spark.createDataFrame(workloads.buffer_ratio_sweep(parts, 0.005, [0.5, 0.6, 0.7, 0.85, 1.0], 2), f"ratio double, {CURVE}")


def update_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Patterns of any length at 0.05 %, as in ``initial_query``."""
    return spark.createDataFrame(workloads.update_ratio_sweep(load(ship(spark), sf_dir, "basket_drift"), 0.0005, 0.2, [0.1, 0.3], None, (1, 5)), f"ratio double, increments int, {CURVE}")


def growth_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.createDataFrame(workloads.growth_sweep(load(ship(spark), sf_dir, "basket_brand"), 0.01, 0.3, 2), f"sequences int, {CURVE}")


def initial_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Patterns of any length at 0.05 %; at 0.5 % nearly all that is frequent in this set is a single item."""
    return spark.createDataFrame(workloads.initial_size_sweep(load(ship(spark), sf_dir, "basket_drift"), 0.0005, [0.2, 0.4, 0.6], None), f"initial double, {CURVE}")


def runtime_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds of both miners, over supports and sets, with the same bound on length."""
    rows = []
    for name, supports in (("click_type", [0.01, 0.05]), ("cust_type", [0.3, 0.4])):
        db = load(ship(spark), sf_dir, name)
        rows += [(name, m, s, c, f, fp, sec) for m, s, c, f, fp, sec in workloads.candidate_sweep(db, supports, 2)]
    return spark.createDataFrame(rows, "name string, miner string, min_sup double, candidates int, frequent int, false_positives double, seconds double")


def speed_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds of the incremental miners over half of the sequences and five increments, against mining anew."""
    db = load(ship(spark), sf_dir, "cust_type")
    rows = workloads.incremental_sweep(db, [0.3], increments_of(db, 0.5, 5), 2)
    return spark.createDataFrame(workloads.speed_ups(rows), "min_sup double, miner string, seconds double, saved double, times double")


def compare_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = workloads.candidate_sweep(load(ship(spark), sf_dir, "click_type"), [0.01, 0.05], 3)
    return spark.createDataFrame([(m, s, c, f, fp) for m, s, c, f, fp, _ in rows], "miner string, min_sup double, candidates int, frequent int, false_positives double")


SPREADS = (0.05, 0.1, 0.15, 0.2, 0.25, 0.3)


def sigma_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.createDataFrame(workloads.sigma_sweep(ship(spark), sf_dir, "click_type", 0.01, list(SPREADS), 3), "sd double, miner string, candidates int, frequent int, false_positives double")


def ablation_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.createDataFrame(workloads.weight_bound_ablation(load(ship(spark), sf_dir, "basket_drift"), 0.0006, 2), "mode string, candidates int")


def unit_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.createDataFrame(workloads.unit_vs_weighted(load(ship(spark), sf_dir, "cust_type"), 0.3, 2), "mode string, candidates int, frequent int, both int")


def segments_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    db = load(spark, sf_dir, "cust_type")
    key = spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_custkey").cast("long").alias("seq_id"), F.col("c_mktsegment").alias("segment"))
    found = mine_by_group(db, key, Params(0.4))
    items = F.size(F.split("pattern", ",|\\)\\("))
    return found.select("segment", "pattern", F.round(F.col("support") * F.pow(F.lit(100.0), items)).cast("bigint").alias("support"))


def segments_sql() -> str:
    return cte("cust_type") + """,
seg as (select cast(c_custkey as bigint) seq_id, c_mktsegment segment from customer),
g as (select segment, seq_id, eid, item, p_pct, w_pct, item_id from flat join w using (item) join seg using (seq_id)),
lim as (select segment, 0.4 * count(distinct seq_id) * (sum(w_pct) / (100.0 * count(*))) fl from g group by 1),
a as (select segment, '(' || item || ')' pattern, 1 n, sum(m) sup, any_value(w_pct) ws from (select segment, seq_id, item, w_pct, max(p_pct) m from g group by all) group by 1, 2),
b as (select segment, pattern, 2 n, sum(m) sup, any_value(ws) ws from (select x.segment, x.seq_id, case when y.eid > x.eid then '(' || x.item || ')(' || y.item || ')' else '(' || x.item || ',' || y.item || ')' end pattern, x.w_pct + y.w_pct ws, max(x.p_pct * y.p_pct) m
  from g x join g y on x.seq_id = y.seq_id and (y.eid > x.eid or (y.eid = x.eid and y.item_id > x.item_id)) group by all) group by 1, 2)
select segment, pattern, cast(sup as bigint) support from (select * from a union all select * from b) join lim using (segment) where sup / pow(100.0, n) * ws / (100.0 * n) >= fl - 1e-9"""


def simulation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.createDataFrame(workloads.simulate_worked_example(ship(spark)), "miner string, batch int, status string, pattern string, weighted_support double").select("miner", "batch", "status", "pattern", F.round("weighted_support", 2).alias("weighted_support"))


QUERIES: dict[str, Query] = {
    "prob_assign": flat_query("click_type", lambda d: d.select("seq_id", "eid", "item", "p_pct")),
    "weight_assign": weights_query("click_day"),
    "seq_flatten": flattened,
    "seq_profile": profile,
    "dist_profile": flat_query("basket_brand", lambda d: relational.distribution_profile(d, "p_pct", 10)),
    "item_support": flat_query("basket_brand", lambda d: d.groupBy("seq_id", "item").agg(F.max("p_pct").alias("m")).groupBy("item").agg(F.count("*").alias("n"), F.sum("m").alias("support"))),
    "plain_support_pairs": flat_query("click_type", lambda d: relational.pairs(d, "s").groupBy("item", "item2").agg(F.countDistinct("seq_id").alias("n"))),
    "suffix_max": flat_query("click_user", lambda d: suffix_max(d.withColumnRenamed("item", "item_id")).select("seq_id", "eid", F.col("item_id").alias("item"), F.round(F.col("later") * 100).cast("int").alias("later_pct"))),
    "mean_weight": totals_query,
    "floors": floors_query,
    "best_match_pairs": best_pairs,
    "expected_support_1": all_of_shape("basket_brand", (), "trie"),
    "expected_support_s2": all_of_shape("cust_type", ("s",), "fold"),
    "expected_support_i2": all_of_shape("cust_type", ("i",), "levels"),
    "expected_support_len3": all_of_shape("cust_type", ("s", "i"), "trie"),
    "expected_support_pairwise": all_of_shape("click_type", ("s", "s"), "pairwise"),
    "support_cap_level2": caps_query("tight"),
    "loose_cap_level2": caps_query("loose"),
    "mine_static_click": mined("click_type", 0.01, 3),
    "mine_static_basket": mined("basket_brand", 0.004, 2),
    "mine_static_hist": mined("cust_type", 0.3, 3),
    "mine_static_factor": mined("click_type", 0.02, 2, factor=0.75),
    "mine_unit_weight": mined("cust_type", 0.3, 2, unit=True),
    "mine_static_hist_pairs": mined("cust_type", 0.3, 2),
    "mine_loose_hist": mined("cust_type", 0.3, 2, loose=True),
    "mine_maximal": mined("click_type", 0.01, 2, keep=maximal),
    "mine_closed": mined("click_type", 0.01, 2, keep=closed),
    "word_patterns": mined("words", 0.05, 2),
    "weight_factor_sweep": sweep_factor,
    "buffered_update": incremental_query(BufferedIncrementalMiner),
    "promising_update": incremental_query(PromisingIncrementalMiner),
    "remine_update": incremental_query(RemineBaseline),
    "mine_by_segment": segments_query,
    "candidates_compare": compare_query,
    "runtime_compare": runtime_query,
    "incremental_speed": speed_query,
    "sigma_sweep": sigma_query,
    "status_transitions": transitions_query,
    "completeness_curve": completeness_curve,
    "buffer_ratio_sweep": ratio_sweep,
    "update_ratio_sweep": update_sweep,
    "db_growth_sweep": growth_query,
    "initial_size_sweep": initial_query,
    "weight_bound_ablation": ablation_query,
    "unit_vs_weighted": unit_query,
    "paper_simulation": simulation,
}
ORACLES: dict[str, str] = {
    "prob_assign": cte("click_type") + "\nselect seq_id, eid, item, p_pct from flat",
    "weight_assign": cte("click_day") + "\nselect item, item_id, w_pct from w",
    "seq_flatten": cte("cust_type") + "\nselect seq_id, eid, item_id, p_pct from flat join w using (item)",
    "seq_profile": profile_sql(),
    "dist_profile": cte("basket_brand") + "\nselect cast(floor(p_pct / 10) as bigint) bin, count(*) n, avg(p_pct) mean from flat group by 1",
    "item_support": cte("basket_brand") + "\nselect item, count(*) n, cast(sum(m) as bigint) support from (select seq_id, item, max(p_pct) m from flat group by 1, 2) group by 1",
    "plain_support_pairs": cte("click_type") + "\nselect a.item, b.item item2, count(distinct a.seq_id) n from flat a join flat b on a.seq_id = b.seq_id and b.eid > a.eid group by 1, 2",
    "suffix_max": cte("click_user") + "\nselect seq_id, eid, item, max(p_pct) over (partition by seq_id, item order by eid rows between current row and unbounded following) later_pct from flat",
    "mean_weight": cte("basket_brand") + "\nselect count(distinct seq_id) sequences, count(*) occurrences, cast(sum(w_pct) as bigint) weight_pct from flat join w using (item)",
    "floors": cte("click_day") + f"\nselect round({floor_sql(min_sup=0.02, factor=0.75)}, 6) frequent, round(0.7 * {floor_sql(min_sup=0.02, factor=0.75)}, 6) buffer, round(1.4 * {floor_sql(min_sup=0.02, factor=0.75)}, 6) as local",
    "best_match_pairs": cte("click_type") + "\nselect a.seq_id, max(cast(a.p_pct as bigint) * b.p_pct) best from flat a join flat b on a.seq_id = b.seq_id and b.eid > a.eid join w x on x.item = a.item and x.item_id = 0 join w y on y.item = b.item and y.item_id = 1 group by 1",
    "expected_support_1": shape_sql("basket_brand", ()),
    "expected_support_s2": shape_sql("cust_type", ("s",)),
    "expected_support_i2": shape_sql("cust_type", ("i",)),
    "expected_support_len3": shape_sql("cust_type", ("s", "i")),
    "expected_support_pairwise": shape_sql("click_type", ("s", "s")),
    "support_cap_level2": caps_sql("tight"),
    "loose_cap_level2": caps_sql("loose"),
    "mine_static_click": mined_sql("click_type", 0.01, 3),
    "mine_static_basket": mined_sql("basket_brand", 0.004, 2),
    "mine_static_hist": mined_sql("cust_type", 0.3, 3),
    "mine_static_factor": mined_sql("click_type", 0.02, 2, factor=0.75),
    "mine_unit_weight": mined_sql("cust_type", 0.3, 2, unit=True),
    "mine_static_hist_pairs": mined_sql("cust_type", 0.3, 2),
    "mine_loose_hist": mined_sql("cust_type", 0.3, 2),
    "mine_maximal": compact_sql("click_type", 0.01),
    "mine_closed": compact_sql("click_type", 0.01, "and o.support >= 100 * m.support"),
    "word_patterns": mined_sql("words", 0.05, 2),
    "weight_factor_sweep": cte("cust_type", enumerated(2)) + f"\nselect f factor, (select count(*) from pats where {score()} >= f * {floor_sql(min_sup=0.3)} - 1e-9) frequent from (values (0.5::double), (0.75::double), (1.0::double), (1.25::double), (1.5::double)) t(f)",
    "buffered_update": incremental_sql("buffered"),
    "promising_update": incremental_sql("promising"),
    "remine_update": incremental_sql("remine"),
    "mine_by_segment": segments_sql(),
    "candidates_compare": miners_sql("click_type", [0.01, 0.05], 3),
    "sigma_sweep": miners_sql("click_type", [0.01], 3, SPREADS),
    "weight_bound_ablation": bounds_sql("basket_drift", 0.0006, 2),
    "unit_vs_weighted": units_sql("cust_type", 0.3, 2),
    "status_transitions": transitions_sql("basket_drift", 0.005, 0.7),
}
