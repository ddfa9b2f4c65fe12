"""License phrases and notices by diagonal voting.

The hash of every run of three words of every text is joined with the hashes of the templates' runs. A hit votes for the diagonal (position
in the text less position in the template). Neighbouring diagonals of a template, a few words apart, are one span when
they meet in the text, so inserted or dropped words do not break it. A span is verified by the share of the template's
runs that it holds, each counted once; a short phrase must be whole, on one diagonal, word for word.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from uncertainseq.llm.common import text_of

# The phrases of the base labels.
PHRASES = {
    "mit": "under the mit license",
    "apache-2": "apache license version 2",
    "cc-by-nc": "cc by nc",
}
# Well-known notices, as their licenses word them.
NOTICES = {
    "notice:mit": "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction",
    "notice:apache-2": "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license",
    "notice:bsd": "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met",
    "notice:gpl": "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation",
    "notice:mpl-2": "this source code form is subject to the terms of the mozilla public license v 2 0",
    "notice:isc": "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted",
    "notice:cc": "this work is licensed under a creative commons attribution noncommercial 4 0 international license",
    "notice:all-rights-reserved": "all rights reserved no part of this publication may be reproduced distributed or transmitted in any form or by any means",
}
K, DRIFT, SHARE = 3, 5, 0.6
WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def template_runs(spark: SparkSession, templates: dict[str, str], exact: bool) -> DataFrame:
    """(label, tpos, runs, exact, gram): as many rows as the templates have runs; gram is the hash of the run's words."""
    rows = []
    for label, text in templates.items():
        words = text.split()
        rows += [(label, i, len(words) - K + 1, exact, words[i : i + K]) for i in range(len(words) - K + 1)]
    made = spark.createDataFrame(rows, "label string, tpos int, runs int, exact boolean, run array<string>")
    return made.select("label", "tpos", "runs", "exact", F.xxhash64(*[F.get("run", F.lit(j)) for j in range(K)]).alias("gram"))


def scan(docs: DataFrame, phrases: dict[str, str] | None = None, notices: dict[str, str] | None = None, share: float = SHARE, drift: int = DRIFT) -> DataFrame:
    """A row per document: n_words, places and labels of whole phrases, labels of verified notices, score.

    score is 1 for a whole phrase, else the largest verified share of a notice, else 0. Null text is empty; a text of fewer
    than three words has no runs. Every row is a document of its own, whatever doc_id it shares or lacks. No rows
    give no rows; other columns are ignored. Templates are lower-case words, three at least, and few: they are broadcast.
    """
    spark = docs.sparkSession
    templates = template_runs(spark, phrases or PHRASES, True).union(template_runs(spark, notices or NOTICES, False))
    low = F.lower(F.replace(text_of(), F.lit("K"), F.lit("ĸ")))  # the one letter whose lower case would be ASCII
    words = docs.select(F.monotonically_increasing_id().alias("row"), "doc_id", F.regexp_extract_all(low, F.lit(WORD), F.lit(0)).alias("words"))
    run = F.transform(F.sequence(F.lit(1), F.size("words") - K + 1), lambda i: F.xxhash64(*[F.element_at("words", i + j) for j in range(K)]))
    grams = words.select("row", "doc_id", F.size("words").cast("long").alias("n_words"), F.posexplode_outer(F.when(F.size("words") >= K, run)).alias("pos", "gram"))
    hits = grams.join(F.broadcast(templates), "gram", "left")
    votes = hits.groupBy("row", "doc_id", "n_words", "label", "runs", "exact", (F.col("pos") - F.col("tpos")).alias("diagonal")).agg(
        F.min(F.when(F.col("label").isNotNull(), F.col("pos"))).alias("low"), F.max(F.when(F.col("label").isNotNull(), F.col("pos"))).alias("high"), F.collect_set("tpos").alias("held")
    )
    near = Window.partitionBy("row", "doc_id", "n_words", "label").orderBy("diagonal", "low")
    apart = F.coalesce((F.col("diagonal") - F.lag("diagonal").over(near) > F.when(F.col("exact"), 0).otherwise(drift)) | ((F.col("low") > F.lag("high").over(near) + F.col("runs")) | (F.col("high") < F.lag("low").over(near) - F.col("runs"))), F.lit(True))
    spans = votes.withColumn("span", F.sum(apart.cast("int")).over(near)).groupBy("row", "doc_id", "n_words", "label", "runs", "exact", "span").agg(
        F.min("low").alias("low"), F.size(F.array_distinct(F.flatten(F.collect_list("held")))).alias("held")
    ).withColumn("part", F.col("held") / F.col("runs"))
    whole, verified = F.col("exact") & (F.col("held") == F.col("runs")), ~F.col("exact") & (F.col("part") >= share)
    joined = lambda c: F.array_join(F.sort_array(F.collect_set(F.when(c, F.col("label")))), ",")
    return spans.groupBy("row", "doc_id", "n_words").agg(
        F.count(F.when(whole, 1)).alias("n_base"), F.min(F.when(whole, F.col("low"))).cast("long").alias("first_word"), F.max(F.when(whole, F.col("low"))).cast("long").alias("last_word"),
        joined(whole).alias("base_labels"), joined(whole | verified).alias("labels"), F.round(F.coalesce(F.max(F.when(whole, 1.0).when(verified, F.col("part"))), F.lit(0.0)), 6).alias("score"),
    ).drop("row")


def oracle() -> str:
    """The same rows by DuckDB."""
    rows = []
    for exact, templates in ((True, PHRASES), (False, NOTICES)):
        for label, text in templates.items():
            w = text.split()
            rows += [f"('{label}',{i},{len(w) - K + 1},'{w[i]}','{w[i + 1]}','{w[i + 2]}',{exact})" for i in range(len(w) - K + 1)]
    return f"""
with t(label,tpos,runs,w0,w1,w2,exact) as (values {",".join(rows)}),
w as (select doc_id, regexp_extract_all(translate(coalesce(text,''),'ABCDEFGHIJKLMNOPQRSTUVWXYZ','abcdefghijklmnopqrstuvwxyz'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') ws from documents),
f as (select doc_id, unnest(ws) word, generate_subscripts(ws,1)-1 pos from w),
g as (select doc_id, pos, word w0, lead(word,1) over (partition by doc_id order by pos) w1, lead(word,2) over (partition by doc_id order by pos) w2 from f),
h as (select doc_id, label, runs, exact, pos-tpos diagonal, pos, tpos from g join t using (w0,w1,w2)),
v as (select doc_id, label, runs, exact, diagonal, min(pos) low, max(pos) high from h group by all),
a as (select *, case when diagonal - lag(diagonal) over n > (case when exact then 0 else {DRIFT} end) or low > lag(high) over n + runs or high < lag(low) over n - runs then 1 when lag(low) over n is null then 1 else 0 end apart
  from v window n as (partition by doc_id, label order by diagonal, low)),
s as (select *, sum(apart) over (partition by doc_id, label order by diagonal, low rows unbounded preceding) span from a),
p as (select s.doc_id, s.label, s.runs, s.exact, s.span, min(s.low) low, count(distinct h.tpos) held from s join h on s.doc_id=h.doc_id and s.label=h.label and s.diagonal=h.diagonal group by all),
q as (select *, exact and held=runs whole, not exact and held/runs >= {SHARE} verified from p)
select w.doc_id, cast(len(any_value(ws)) as bigint) n_words, count(case when whole then 1 end) n_base,
  cast(min(case when whole then low end) as bigint) first_word, cast(max(case when whole then low end) as bigint) last_word,
  coalesce(string_agg(distinct case when whole then label end, ',' order by case when whole then label end),'') base_labels,
  coalesce(string_agg(distinct case when whole or verified then label end, ',' order by case when whole or verified then label end),'') labels,
  round(coalesce(max(case when whole then 1.0 when verified then held/runs end),0.0),6) score
from w left join q on w.doc_id=q.doc_id group by w.doc_id"""
