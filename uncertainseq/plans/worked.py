"""The worked example as literal SQL: both incremental miners over three batches, by enumeration."""

from __future__ import annotations

from uncertainseq.plans.catalogue import enumerated, floor_sql, score
from uncertainseq.plans.workloads import WORKED, WORKED_INCREMENTS, WORKED_PARAMS, WORKED_WEIGHTS

LONGEST = 5


def literal_rows() -> str:
    """d0, d1, d2: the batches' occurrences; u0, u1, u2: all of them up to a batch; w: items and weights."""
    items = ", ".join(f"('{x}', {k}, {round(100 * v)})" for k, (x, v) in enumerate(sorted(WORKED_WEIGHTS.items())))
    out = f"with w as (select * from (values {items}) v(item, item_id, w_pct))"
    for k, batch in enumerate((WORKED, *WORKED_INCREMENTS)):
        rows = ", ".join(f"({s}, {e}, '{x}', {round(100 * p)})" for s, events in batch.items() for e, event in enumerate(events, 1) for x, p in event.items())
        out += f",\nd{k} as (select * from (values {rows}) v(seq_id, eid, item, p_pct))"
        out += f",\nu{k} as (select * from d{k}" + (f" union all select * from u{k - 1})" if k else ")")
    return out + "".join(enumerated(LONGEST, f"d{k}", f"p{k}") for k in range(3))


def states(kind: str) -> str:
    """State of one miner after each batch, as tables ``kind``_0, ``kind``_1, ``kind``_2."""
    low, ratio = WORKED_PARAMS.min_sup, WORKED_PARAMS.buffer_ratio
    out = ""
    for k in range(3):
        frequent, own = floor_sql(f"u{k}", low), f"{2 * ratio} * {floor_sql(f'd{k}', low)}"
        if k == 0:
            merged, local = "select pattern, n_items, wsum, sup from p0", ""
        else:
            merged = f"select t.pattern, t.n_items, t.wsum, t.sup + coalesce(g.sup, 0) sup from {kind}_{k - 1} t left join p{k} g using (pattern)"
            local = f"when s >= {own} - 1e-9 then 'promising'" if kind == "promising" else ""
            if kind == "promising":
                merged += f" union all select pattern, n_items, wsum, sup from p{k} where {score()} >= {own} - 1e-9 and pattern not in (select pattern from {kind}_{k - 1})"
        named = f"case when s >= {frequent} - 1e-9 then 'frequent' when s >= {ratio} * {frequent} - 1e-9 then 'semi' {local} end"
        out += f",\n{kind}_{k} as (select * from (select pattern, n_items, wsum, sup, s, {named} status from (select *, {score()} s from ({merged}))) where status is not null)"
    return out


def simulation_sql() -> str:
    rows = " union all ".join(f"select '{m}' miner, {k}::int batch, status, pattern, round(round(s, 6), 2) weighted_support from {m}_{k}" for m in ("buffered", "promising") for k in range(3))
    return literal_rows() + states("buffered") + states("promising") + "\n" + rows
