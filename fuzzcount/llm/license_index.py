"""Licence scans with a positional index of rare licence words.

Base labels come from fixed phrases whose words stand consecutively.  The method adds labels of its own from
templates.  Words weigh by inverse document frequency, as shares of their template; a template's rarest
places, those that weigh more than an alignment may miss, are its postings.  Every text's words are looked up
in the postings, and those that meet at one relative position name an alignment: one without any of them
cannot score enough, so none is left out, whatever the length of a text or the number of its licences.
Alignments are scored in full, the share of the template's weight whose words agree, and a template's label
counts only if its mandatory key phrase stands in the text.  A base label scores 1.

Only DataFrame operations are used.  Texts are read twice: for base places and word frequencies, and those that
have a posting once more.

Edge cases: a null text counts as empty; a text without words has no place and no label and scores 0; rows that share
an id are scanned each for itself; overlapping places all count; an empty table gives no rows.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fuzzcount.llm.text import trimmed_words
from fuzzcount.sources.tables import cut, drop

#: Fixed values of the contract: phrase and label.
BASE = {"under the mit license": "mit", "apache license version 2": "apache-2", "cc by nc": "cc-by-nc"}


@dataclass(frozen=True)
class Template:
    label: str
    words: str
    mandatory: str


#: Opening words of public licences and of the notices that name them.
TEMPLATES = [
    Template("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", "permission is hereby granted free of charge"),
    Template("mit", "released under the mit license", "mit license"),
    Template("apache-2", "licensed under the apache license version 2 0", "apache license version 2"),
    Template("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", "redistribution and use in source and binary forms"),
    Template("gpl-3", "this work is licensed under the gnu general public license version 3", "gnu general public license version 3"),
    Template("gpl-2", "this program is free software you can redistribute it under the terms of the gnu general public license version 2", "gnu general public license version 2"),
    Template("lgpl", "this library is free software under the terms of the gnu lesser general public license", "gnu lesser general public license"),
    Template("agpl-3", "licensed under the gnu affero general public license version 3", "gnu affero general public license"),
    Template("mpl-2", "subject to the terms of the mozilla public license v 2 0", "mozilla public license"),
    Template("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", "permission to use copy modify and or distribute this software"),
    Template("cc-by-nc", "licensed under cc by nc 4 0", "cc by nc"),
    Template("cc-by-nc", "creative commons attribution noncommercial 4 0 international license", "creative commons attribution noncommercial"),
    Template("cc-by-sa", "licensed under cc by sa 4 0", "cc by sa"),
    Template("cc0", "cc0 1 0 universal public domain dedication", "cc0 1 0 universal"),
]

ACCEPT = 0.6
#: Sums in any order may differ in their last digits; the score is then taken once more in the order of the words.
SLACK = 1e-6


def starts_of(words: Column, phrase: str) -> Column:
    """All places of a phrase in an array of words."""
    parts = phrase.split(" ")
    last = F.size(words) - len(parts)
    places = F.when(last >= 0, F.sequence(F.lit(0), last)).otherwise(F.array().cast("array<int>"))

    def stands(i: Column) -> Column:
        found = F.get(words, i) == parts[0]
        for n, word in enumerate(parts[1:], 1):
            found = found & (F.get(words, i + n) == word)
        return found

    return F.filter(places, stands)


def worded(docs: DataFrame) -> DataFrame:
    """`docs` (doc_id, text, text_key) as (doc_id, text_key, normal, words)."""
    # One element exploded: the plan then computes it once, not in each expression, or each step of a lambda, that uses it.
    rows = docs.select("doc_id", "text_key", F.explode(F.array(trimmed_words(F.col("text")))).alias("normal"))
    return rows.select("doc_id", "text_key", "normal", F.explode(F.array(F.split(F.trim("normal"), " "))).alias("words"))


def scanned(docs: DataFrame, templates: list[Template]) -> DataFrame:
    """Per row: n_words, the places of base phrases, and its licence words."""
    vocabulary = sorted({w for t in templates for w in t.words.split(" ")})
    words, none = F.col("words"), F.array().cast("array<int>")
    return worded(docs).select(
        "doc_id", "text_key",
        F.when(F.col("normal") == " ", 0).otherwise(F.length("normal") - F.length(F.replace("normal", F.lit(" "), F.lit(""))) - 1).cast("bigint").alias("n_words"),
        *(F.when(F.contains("normal", F.lit(f" {p} ")), starts_of(words, p)).otherwise(none).alias(f"base_{i}") for i, p in enumerate(BASE)),
        F.array_intersect(words, F.array(*map(F.lit, vocabulary))).alias("licence_words"),
    )


def rarities(rows: DataFrame, templates: list[Template], total: int) -> dict[str, float]:
    """Inverse document frequency of each word of the templates, those that no text has included."""
    seen = rows.select(F.explode("licence_words").alias("word")).groupBy("word").agg(F.count("*").alias("n")).collect()  # the words of the templates at most
    n = {r["word"]: r["n"] for r in seen}
    return {w: math.log((total + 1) / (n.get(w, 0) + 0.5)) for t in templates for w in t.words.split(" ")}


def rarest_places(weights: list[float]) -> list[int]:
    """Places that weigh more than what an accepted alignment may miss, the heaviest first."""
    order, held = sorted(range(len(weights)), key=lambda i: (-weights[i], i)), 0.0
    for n, i in enumerate(order, 1):
        held += weights[i]
        if held > 1 - ACCEPT + SLACK:
            return order[:n]
    return order


def postings_of(templates: list[Template], idf: dict[str, float]) -> list[tuple[str, int, int]]:
    """The postings of all templates: (word, template, at)."""
    return [(t.words.split(" ")[i], number, i) for number, t in enumerate(templates) for i in rarest_places(weights_of(t, idf))]


def weights_of(template: Template, idf: dict[str, float]) -> list[float]:
    """The weight of each word of a template, as a share of 1."""
    weights = [max(idf.get(w, 0.0), 0.05) for w in template.words.split(" ")]
    return [w / sum(weights) for w in weights]


def template_table(spark: SparkSession, templates: list[Template], idf: dict[str, float]) -> DataFrame:
    """Per template: its words, their weights (a share of 1) and its label."""
    rows = [(number, t.words.split(" "), weights_of(t, idf), t.label) for number, t in enumerate(templates)]
    return spark.createDataFrame(rows, "template int, expected array<string>, weights array<double>, label string")


def key_of() -> Column:
    return F.struct(F.coalesce("doc_id", F.lit(-(1 << 63))).alias("id"), "text_key")


def licences(docs: DataFrame, templates: list[Template] = TEMPLATES) -> DataFrame:
    """One row per row of `docs` (doc_id, text); see the module's text and the columns below."""
    spark = docs.sparkSession
    docs = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).withColumn("text_key", F.xxhash64("text"))
    rows = cut(scanned(docs, templates))
    idf = rarities(rows, templates, rows.count())
    postings = postings_of(templates, idf)
    index = F.broadcast(spark.createDataFrame(postings, "word string, template int, at int"))  # the words of the templates at most

    rare = F.array(*map(F.lit, sorted({word for word, _, _ in postings})))
    met = cut(rows.where(F.arrays_overlap("licence_words", rare)).select(key_of().alias("key")).distinct())
    with_posting = worded(docs.join(met, key_of() == F.col("key"), "left_semi"))
    named = F.array_compact(F.array(*(F.when(F.contains("normal", F.lit(f" {t.mandatory} ")), number) for number, t in enumerate(templates))))
    held = cut(with_posting.select(F.monotonically_increasing_id().alias("row"), key_of().alias("key"), "words", named.alias("named")))
    tokens = held.select("row", F.posexplode("words").alias("place", "word"))
    aligned = cut(tokens.join(index, "word").select("row", "template", (F.col("place") - F.col("at")).alias("diagonal")).distinct())
    pairs = held.join(aligned, "row").join(F.broadcast(template_table(spark, templates, idf)), "template")
    place = lambda i: F.when(F.col("diagonal") + i >= 0, F.get("words", F.col("diagonal") + i))
    agree = lambda i: F.when(place(i) == F.get("expected", i), F.get("weights", i)).otherwise(0.0)
    score = F.aggregate(F.sequence(F.lit(0), F.size("expected") - 1), F.lit(0.0), lambda total, i: total + agree(i))
    scored = pairs.select("key", "named", "template", "label", score.alias("score")).where(F.col("score") >= ACCEPT)
    verified = scored.where(F.array_contains("named", F.col("template")))
    found = cut(verified.groupBy("key").agg(F.collect_set("label").alias("own_labels"), F.max("score").alias("own_score")))
    drop(met, held, aligned)

    places = F.concat(*(F.col(f"base_{i}") for i in range(len(BASE))))
    base = F.filter(F.array(*(F.when(F.size(f"base_{i}") > 0, label) for i, label in enumerate(BASE.values()))), lambda x: x.isNotNull())
    out = rows.withColumn("key", key_of()).join(found, "key", "left").withColumn("base", F.array_sort(F.array_distinct(base))).withColumn("places", places)
    return out.select(
        "doc_id", "n_words", F.size("places").cast("bigint").alias("n_base"),
        F.array_min("places").cast("bigint").alias("first_word"), F.array_max("places").cast("bigint").alias("last_word"),
        F.array_join("base", ",").alias("base_labels"),
        F.array_join(F.array_sort(F.array_distinct(F.concat("base", F.coalesce("own_labels", F.array().cast("array<string>"))))), ",").alias("labels"),
        F.when(F.size("base") > 0, 1.0).otherwise(F.least(F.lit(1.0), F.coalesce("own_score", F.lit(0.0)))).alias("score"),
    )
