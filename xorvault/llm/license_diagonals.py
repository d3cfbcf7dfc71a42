"""License scans by diagonal voting, in DataFrame functions only.

Every rolling word k-gram of a text is hashed, and the hashes are joined to a table of template positions. A hit votes
for the diagonal (place in the text minus place in the template); votes are counted by diagonal, neighbouring diagonals
(a word put in or left out) are merged, and a merged group is verified: its span in the text must be about as long as
the template, and the template's words that its hits cover must make up a given share. Hits compare the words
themselves beside the hash, so that a hash collision cannot vote.

The templates are a fixed table in this module, so its broadcast has a proven bound. Hashes that are in no template
are dropped before the join by an IN-set of the same table, inside the row; only hits are ever exploded. A row that
has no hit stays as one row. Votes group by document, template and diagonal, never by text, so that copies and common
passages make no hot group. Null and empty texts have no words; repeated rows give repeated results.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

K = 3
#: Diagonals up to this far apart are merged.
NEAR = 3
LEAST_SCORE = 0.8

# What counts as a word, and the base phrases with their labels.
WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
PHRASES = (("gnu general public license", "gpl"), ("apache license", "apache"), ("cc by", "cc-by"), ("mit license", "mit"))

# Short public licence notices, lower-case words.
TEMPLATES = (
    ("apache-2.0", "licensed under the apache license version 2 0"),
    ("apache-2.0", "you may not use this file except in compliance with the license you may obtain a copy of the license at http www apache org licenses license 2 0"),
    ("mit", "released under the mit license"),
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files"),
    ("gpl-3.0", "licensed under the gnu general public license version 3"),
    ("gpl", "you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation"),
    ("cc-by-4.0", "licensed under cc by 4 0"),
    ("cc-by-sa-4.0", "licensed under cc by sa 4 0"),
    ("cc-by-nc-4.0", "licensed under cc by nc 4 0"),
    ("cc-by-4.0", "licensed under a creative commons attribution 4 0 international license"),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"),
    ("mpl-2.0", "this source code form is subject to the terms of the mozilla public license v 2 0"),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted"),
    ("unlicense", "this is free and unencumbered software released into the public domain"),
)


def template_rows() -> list[tuple[int, str, int, int, str]]:
    """(template, label, its words, position, k-gram) of every template position."""
    rows = []
    for t, (label, text) in enumerate(TEMPLATES):
        words = text.split()
        rows += [(t, label, len(words), p, " ".join(words[p : p + K])) for p in range(len(words) - K + 1)]
    return rows


def _all(parts: list[Column]) -> Column:
    return reduce(lambda a, b: a & b, parts)


def _gram(words: Column, i: Column) -> Column:
    return F.concat_ws(" ", *[F.get(words, i + k) for k in range(K)])


def scan_licenses(docs: DataFrame, *, least_score: float = LEAST_SCORE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, n_words, n_base, first_word, last_word, base_labels, labels, score, n_votes."""
    spark = docs.sparkSession
    low = F.translate(F.coalesce(F.col(text_col), F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    split = docs.select(F.col(id_col).alias("_id"), F.regexp_extract_all(low, F.lit(WORD), F.lit(0)).alias("_w"))
    words, n = F.col("_w"), F.size("_w")
    joined = split.select("_id", "_w", F.concat(F.lit(" "), F.array_join("_w", " "), F.lit(" ")).alias("_all"))

    none = F.array().cast("array<int>")

    def places(phrase: str) -> Column:
        parts = phrase.split()
        found = F.filter(F.sequence(F.lit(0), n - len(parts)), lambda i: _all([F.get(words, i + k) == p for k, p in enumerate(parts)]))
        return F.when(F.col("_all").contains(f" {phrase} "), found).otherwise(none)

    grams = spark.createDataFrame(template_rows(), "_t int, _label string, _len int, _p int, _gram string").select("*", F.xxhash64("_gram").alias("_h"))
    known = sorted({r._h for r in grams.select("_h").collect()})
    hashed = F.filter(F.sequence(F.lit(0), n - K), lambda i: F.xxhash64(_gram(words, i)).isin(known))
    hits = F.when(n >= K, F.transform(hashed, lambda i: F.struct(i.alias("at"), F.xxhash64(_gram(words, i)).alias("h"), _gram(words, i).alias("gram"))))
    rows = joined.select("_id", F.monotonically_increasing_id().alias("_row"), n.cast("long").alias("n_words"), *[places(p).alias(f"_b{k}") for k, (p, _) in enumerate(PHRASES)], hits.alias("_hits"))
    every = F.concat(*[F.col(f"_b{k}") for k in range(len(PHRASES))])
    named = F.array_compact(F.array(*[F.when(F.size(f"_b{k}") > 0, F.lit(label)) for k, (_, label) in enumerate(PHRASES)]))
    base = rows.select("_id", "_row", "n_words", F.size(every).cast("long").alias("n_base"), F.array_min(every).cast("long").alias("first_word"), F.array_max(every).cast("long").alias("last_word"), F.array_sort(named).alias("_base"), "_hits")
    keys = [c for c in base.columns if c != "_hits"]

    # Votes: one row per hit and template position that has the same words.
    hit = base.select(*keys, F.explode_outer("_hits").alias("_x")).select(*keys, F.col("_x.at").alias("_at"), F.col("_x.h").alias("_h"), F.col("_x.gram").alias("_gram"))
    votes = hit.join(F.broadcast(grams), ["_h", "_gram"], "left").withColumn("_diag", F.col("_at") - F.col("_p"))
    own = ["_row", "_t", "_label", "_len"]
    rest = [F.first(c).alias(c) for c in keys if c != "_row"]
    diagonals = votes.groupBy(*own, "_diag").agg(*rest, F.collect_set("_p").alias("_ps"), F.min("_at").alias("_from"), F.max("_at").alias("_to"), F.count("_p").alias("_n"))

    # Neighbouring diagonals of one text and template become one group.
    in_order = "OVER (PARTITION BY _row, _t ORDER BY _diag"
    gap = diagonals.withColumn("_new", F.expr(f"CASE WHEN _diag - lag(_diag) {in_order}) <= {NEAR} THEN 0 ELSE 1 END"))
    grouped = gap.withColumn("_group", F.expr(f"sum(_new) {in_order} ROWS UNBOUNDED PRECEDING)"))
    merged = grouped.groupBy(*own, "_group").agg(*rest, F.array_distinct(F.flatten(F.collect_list("_ps"))).alias("_ps"), F.min("_from").alias("_from"), F.max("_to").alias("_to"), F.sum("_n").alias("_n"))
    covered = F.size(F.array_distinct(F.flatten(F.transform("_ps", lambda p: F.transform(F.array(*[F.lit(k) for k in range(K)]), lambda k: p + k)))))
    span = F.col("_to") - F.col("_from") + K
    share = F.when(F.col("_t").isNotNull() & (span <= F.col("_len") + NEAR + F.floor(F.col("_len") / 4)), covered / F.col("_len")).otherwise(0.0)
    scored = merged.withColumn("_score", share)
    ok = F.col("_score") >= least_score
    out = scored.groupBy("_row").agg(*rest, F.collect_set(F.when(ok, F.col("_label"))).alias("_more"), F.max("_score").alias("_best"), F.sum("_n").alias("n_votes"))
    score = F.greatest(F.when(F.col("n_base") > 0, F.lit(1.0)).otherwise(0.0), F.col("_best"))
    return out.select(F.col("_id").alias(id_col), "n_words", "n_base", "first_word", "last_word", F.array_join("_base", ",").alias("base_labels"), F.array_join(F.array_sort(F.array_union("_base", "_more")), ",").alias("labels"), score.alias("score"), "n_votes")


def oracle_sql() -> str:
    """The same result in DuckDB SQL, from words rather than hashes."""
    grams = ", ".join(f"({t}, '{label}', {n}, {p}, '{g}')" for t, label, n, p, g in template_rows())
    phrases = ", ".join(f"('{p}', '{label}')" for p, label in PHRASES)
    return f"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS w FROM documents),
t(t, label, len, p, gram) AS (VALUES {grams}),
ph(phrase, label) AS (VALUES {phrases}),
i AS (SELECT r, w, unnest(range(len(w))) AS i FROM d),
b AS (SELECT i.r, i.i, ph.label FROM i, ph WHERE array_to_string(w[i + 1 : i + len(string_split(phrase, ' '))], ' ') = phrase),
bs AS (SELECT r, count(*) AS n, min(i) AS lo, max(i) AS hi, list(DISTINCT label) AS ls FROM b GROUP BY r),
v AS (SELECT i.r, i.i, t.* FROM i JOIN t ON array_to_string(w[i + 1 : i + {K}], ' ') = t.gram WHERE i.i + {K} <= len(w)),
dg AS (SELECT r, t, label, len, i - p AS diag, list(DISTINCT p) AS ps, min(i) AS lo, max(i) AS hi, count(*) AS n FROM v GROUP BY ALL),
g1 AS (SELECT *, CASE WHEN diag - lag(diag) OVER (PARTITION BY r, t ORDER BY diag) <= {NEAR} THEN 0 ELSE 1 END AS new FROM dg),
g2 AS (SELECT *, sum(new) OVER (PARTITION BY r, t ORDER BY diag ROWS UNBOUNDED PRECEDING) AS grp FROM g1),
m AS (SELECT r, t, label, len, grp, list_distinct(flatten(list(ps))) AS ps, min(lo) AS lo, max(hi) AS hi, sum(n) AS n FROM g2 GROUP BY r, t, label, len, grp),
s AS (SELECT r, label, n, CASE WHEN hi - lo + {K} <= len + {NEAR} + len // 4 THEN len(list_distinct(flatten(list_transform(ps, lambda p: [p + k FOR k IN range({K})])))) / len ELSE 0 END AS score FROM m),
ss AS (SELECT r, max(score) AS best, sum(n) AS n, coalesce(list(DISTINCT label) FILTER (WHERE score >= {LEAST_SCORE}), []) AS ls FROM s GROUP BY r)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(bs.n, 0) AS BIGINT) AS n_base, CAST(bs.lo AS BIGINT) AS first_word, CAST(bs.hi AS BIGINT) AS last_word,
 coalesce(array_to_string(list_sort(bs.ls), ','), '') AS base_labels, array_to_string(list_sort(list_distinct(list_concat(coalesce(bs.ls, []), coalesce(ss.ls, [])))), ',') AS labels,
 CAST(greatest(CASE WHEN bs.n > 0 THEN 1.0 ELSE 0.0 END, coalesce(best, 0)) AS DOUBLE) AS score, CAST(coalesce(ss.n, 0) AS BIGINT) AS n_votes
FROM d LEFT JOIN bs USING (r) LEFT JOIN ss USING (r)"""
