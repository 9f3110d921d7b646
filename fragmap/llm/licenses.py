"""License scans by an exact set-similarity join. DataFrame functions only.

Text blocks (overlapping runs of words) are joined with license templates where the
block holds at least ``CONTAINMENT`` of the template's distinct words. Words are
ranked by their document frequency over the whole table, rarest first; a template is
indexed under its first ``size - needed + 1`` words only, so a block that shares none
of them cannot qualify. Length and positional filters cut candidates before their
overlap is counted. Blocks are twice the longest template long and start every such
length, so any run of words no longer than a template lies whole in one block.

Base places are exact runs of consecutive words of fixed phrases; their labels always stay.

Defined cases: a null or empty text has no word, no label and score 0; repeated rows
each get their row; equal words of a block count once; an empty table gives an empty
result; other columns of the input are not read.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fragmap.llm import common

#: The phrases and labels of the contract.
PHRASES = {
    "under the mit license": "mit",
    "apache license version 2": "apache-2",
    "cc by nc": "cc-by-nc",
}
#: Common sentences of public licenses and their labels.
TEMPLATES = [
    ("mit", "released under the mit license"),
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software"),
    ("apache-2", "licensed under the apache license version 2 0"),
    ("cc-by-nc", "licensed under cc by nc 4 0"),
    ("gpl-3", "this work is licensed under the gnu general public license version 3"),
    ("gpl", "free software you can redistribute it and or modify it under the terms of the gnu general public license"),
    ("lgpl", "under the terms of the gnu lesser general public license"),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted"),
    ("mpl-2", "subject to the terms of the mozilla public license v 2 0"),
    ("cc-by", "licensed under a creative commons attribution 4 0 international license"),
    ("cc0", "to the extent possible under law the author has waived all copyright and related rights"),
    ("all-rights-reserved", "all rights reserved no part of this publication may be reproduced"),
]
CONTAINMENT = 0.9
_WORD = r"([^\x00-\x2F\x3A-\x60\x7B-\x7F]+)"


def words_of(text: Column) -> Column:
    """Words of the contract, but with other alphabets folded too: their letters are word characters before and after.

    The Kelvin sign alone would become an ASCII letter, so another letter stands for it. Words are
    counted and compared with ASCII words, never returned.
    """
    kept = F.replace(F.coalesce(text, F.lit("")), F.lit("\u212a"), F.lit("\u00e9"))
    return F.regexp_extract_all(F.lower(kept), F.lit(_WORD), 1)


def _strings(values: list[str]) -> Column:
    return F.array(*[F.lit(v) for v in values])


def phrase_places(words: Column, phrases: dict[str, str] | None = None) -> Column:
    """array<struct<label, at>> of every place where a phrase stands."""
    phrases = PHRASES if phrases is None else phrases
    return F.concat(*[_places(words, phrase.split(), label) for phrase, label in phrases.items()])


def _places(words: Column, parts: list[str], label: str) -> Column:
    rare = max(parts, key=len) if len(parts) > 3 else parts[-1]

    def here(i: Column) -> Column:
        test = F.get(words, i) == parts[0]
        for j, part in enumerate(parts[1:], 1):
            test = test & (F.get(words, i + j) == part)
        return test

    at = F.filter(F.sequence(F.lit(0), F.size(words) - 1), here)
    rows = F.transform(at, lambda i: F.struct(F.lit(label).alias("label"), i.alias("at")))
    return F.when(F.array_contains(words, rare), rows).otherwise(F.array().cast("array<struct<label:string,at:int>>"))


def word_frequencies(docs: DataFrame, words: list[str], text_col: str = "text") -> dict[str, int]:
    """In how many documents each of ``words`` (a set bounded by the templates) occurs."""
    held = F.array_intersect(words_of(F.col(text_col)), _strings(words))
    rows = docs.select(F.explode(held).alias("word")).groupBy("word").count().collect()
    return {r["word"]: r["count"] for r in rows}


def template_matches(
    docs: DataFrame, keys: list[str], text_col: str = "text", templates: list[tuple[str, str]] | None = None,
    containment: float = CONTAINMENT,
) -> DataFrame:
    """(keys, block, template, label, share) of every block that holds enough of a template."""
    spark = docs.sparkSession
    templates = TEMPLATES if templates is None else templates
    sets = [sorted(set(t.split())) for _, t in templates]
    vocabulary = sorted(set().union(*map(set, sets))) if sets else []
    seen = word_frequencies(docs, vocabulary, text_col) if vocabulary else {}
    rank = {w: i for i, w in enumerate(sorted(vocabulary, key=lambda w: (seen.get(w, 0), w)))}
    postings, shape = [], []
    for t, ((label, _), words) in enumerate(zip(templates, sets)):
        ranks = sorted(rank[w] for w in words)
        need = math.ceil(containment * len(ranks) - 1e-9)
        shape.append((t, label, ranks, need))
        postings += [(r, t, i, len(ranks), need) for i, r in enumerate(ranks[: len(ranks) - need + 1])]
    index = spark.createDataFrame(postings or [(0, -1, 0, 0, 1)], "word int, template int, at_t int, size_t int, need int")
    shapes = spark.createDataFrame(shape or [(-1, "", [0], 1)], "template int, label string, ranks array<int>, need int")
    longest = max([len(t.split()) for _, t in templates], default=1)
    ordered = sorted(vocabulary, key=rank.get)
    keyed_words = [w for w in ordered if any(r == rank[w] for r, *_ in postings)]
    width = 2 * longest

    # documents without an indexed word leave before any block is built
    held = docs.select(*keys, words_of(F.col(text_col)).alias("words"))
    held = held.where(F.arrays_overlap("words", _strings(keyed_words or [""])))
    starts = F.sequence(F.lit(0), F.greatest(F.size("words") - longest, F.lit(0)), F.lit(longest))
    blocks = held.select(*keys, "words", F.explode(starts).alias("start")).select(
        *keys, (F.col("start") / longest).cast("int").alias("block"), F.slice("words", F.col("start") + 1, width).alias("words")
    )
    as_ranks = F.array_sort(F.transform(
        F.array_intersect("words", _strings(ordered or [""])), lambda w: (F.array_position(_strings(ordered or [""]), w) - 1).cast("int")
    ))
    blocks = blocks.where(F.arrays_overlap("words", _strings(keyed_words or [""]))).withColumn("ranks_b", as_ranks)
    tokens = blocks.select(*keys, "block", "ranks_b", F.posexplode("ranks_b").alias("at_b", "word"))
    rest = F.least(F.col("size_t") - F.col("at_t"), F.size("ranks_b") - F.col("at_b"))
    candidates = (
        tokens.join(F.broadcast(index), "word")
        .where(F.size("ranks_b") >= F.col("need"))
        .where(F.col("at_t") + rest >= F.col("need"))
        .select(*keys, "block", "ranks_b", "template").distinct()  # several words of one prefix may hit
    )
    share = F.size(F.array_intersect("ranks_b", "ranks")) / F.size("ranks")
    return (
        candidates.join(F.broadcast(shapes), "template").withColumn("share", share)
        .where(F.size(F.array_intersect("ranks_b", "ranks")) >= F.col("need"))
        .select(*keys, "block", "template", "label", "share")
    )


def license_scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of ``docs``: words, base places, base labels, all labels and the best share."""
    keyed = docs.select(F.col(id_col).alias("doc_id"), F.xxhash64(text_col).alias("text_id"), F.col(text_col).alias("text"))
    matches = (
        template_matches(keyed, ["doc_id", "text_id"]).groupBy("doc_id", "text_id")
        .agg(F.collect_set("label").alias("own_labels"), F.max("share").alias("own_share"))
        .select(F.col("doc_id").alias("m_doc"), F.col("text_id").alias("m_text"), "own_labels", "own_share")
    )
    base = keyed.select("doc_id", "text_id", words_of(F.col("text")).alias("words")).select(
        "doc_id", "text_id",
        common.let(F.col("words"), lambda ws: F.struct(F.size(ws).cast("bigint").alias("n"), phrase_places(ws).alias("places"))).alias("b"),
    ).select("doc_id", "text_id", F.col("b.n").alias("n_words"), F.col("b.places").alias("places"))
    joined = base.join(
        matches.hint("shuffle_hash"), base["doc_id"].eqNullSafe(matches["m_doc"]) & (base["text_id"] == matches["m_text"]), "left"
    )
    at, labels = F.col("places.at"), F.array_sort(F.array_distinct(F.col("places.label")))
    own = F.coalesce("own_labels", F.array().cast("array<string>"))
    return joined.select(
        "doc_id", "n_words", F.size("places").cast("bigint").alias("n_base"),
        F.array_min(at).cast("bigint").alias("first_word"), F.array_max(at).cast("bigint").alias("last_word"),
        F.array_join(labels, ",").alias("base_labels"),
        F.array_join(F.array_sort(F.array_union(labels, own)), ",").alias("labels"),
        F.when(F.size("places") > 0, F.lit(1.0)).otherwise(F.coalesce("own_share", F.lit(0.0))).alias("score"),
    )


def op10_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan(common.table(spark, sf_dir, "documents"))
