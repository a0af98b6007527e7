"""Licence texts in documents by diagonal voting, with DataFrame functions only.

Every rolling pair of words of every document is hashed; pairs that some template has are joined, word
by word, to the places of the pair in the templates. A match at word i of a document and word j of a
template votes for the diagonal i - j; votes are added up per document, template and diagonal.
Neighbouring diagonals, which insertions and deletions cause, are merged into one span when they lie
within `drift` words of each other. A span is verified by its coverage: the share of the template's pairs that the span's diagonals hold, without
counting a template place twice. Short phrases must be held whole on one diagonal, which is exact
consecutive occurrence; longer notices need a share of `min_cover`.

Texts are read and cut into words once. What is kept of a row, its number of words and its template
pairs, is a table of the shared folder with a number per row. The template pairs are few literals, so
the join needs no shuffle of documents; only votes, which are rare, are shuffled, already added up per task.

Defined cases: null counts as empty; texts without words have n_words 0 and no labels; repeated rows
are rows of their own; an empty table gives an empty result; other
columns are ignored; first_word and last_word are the smallest and largest start of a base phrase.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from poolcurator.llm.store import pick, write_table

#: Runs of a-z, 0-9 and characters beyond ASCII. Java looks single characters up in a table, but asks ranges one after another.
WORD = "[^" + "".join(f"\\x{c:02X}" for c in range(128) if not chr(c).isdigit() and not chr(c).islower()) + "]+"

# Base phrases and their labels.
BASE = (
    ("gnu general public license", "gpl"),
    ("apache license", "apache"),
    ("cc by", "cc-by"),
    ("mit license", "mit"),
)
# Further phrases and notices of well-known licences, and their labels.
NOTICES = (
    ("permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", "mit"),
    ("redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", "bsd"),
    ("licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license", "apache"),
    ("this program is free software you can redistribute it and or modify it under the terms of the gnu general public license", "gpl"),
    ("this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license", "lgpl"),
    ("this source code form is subject to the terms of the mozilla public license v 2 0", "mpl"),
    ("permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", "isc"),
    ("this is free and unencumbered software released into the public domain", "unlicense"),
    ("this work is licensed under a creative commons attribution", "cc-by"),
    ("gnu lesser general public license", "lgpl"),
    ("gnu affero general public license", "agpl"),
    ("mozilla public license", "mpl"),
    ("eclipse public license", "epl"),
    ("boost software license", "bsl"),
    ("bsd license", "bsd"),
    ("cc by nc", "cc-by-nc"),
    ("cc by sa", "cc-by-sa"),
    ("cc by nd", "cc-by-nd"),
    ("all rights reserved", "proprietary"),
)


@dataclass(frozen=True)
class Template:
    number: int
    words: tuple[str, ...]
    label: str
    base: bool
    whole: bool  # must be held whole, on one diagonal


#: Templates up to this many words are phrases and must be held whole.
PHRASE_WORDS = 5


def templates(base=BASE, notices=NOTICES) -> list[Template]:
    listed = [(t, label, True) for t, label in base] + [(t, label, False) for t, label in notices]
    return [Template(i, tuple(t.split()), label, is_base, len(t.split()) <= PHRASE_WORDS) for i, (t, label, is_base) in enumerate(listed)]


def template_pairs(listed: list[Template]) -> list[tuple[str, str, int, int]]:
    """(first word, second word, template, place): as many as the templates have words."""
    return [(t.words[j], t.words[j + 1], t.number, j) for t in listed for j in range(len(t.words) - 1)]


def ascii_lower(text) -> F.Column:
    """Lower case; the one sign beyond ASCII whose lower case is a letter of ASCII, the Kelvin sign, stays beyond it."""
    return F.lower(F.replace(text, F.lit("\u212a"), F.lit("\u0138")))


def word_facts(text, pairs: list[tuple[str, str, int, int]]) -> F.Column:
    """(n_words, hits) of a text; hits are the word pairs, with the first one's number, that a template may have."""
    wanted = [F.xxhash64(F.lit(a), F.lit(b)) for a, b in sorted({p[:2] for p in pairs})]  # folded to constants, so looked up in a set
    words = F.regexp_extract_all(ascii_lower(text), F.lit(WORD), F.lit(0))

    def facts(w) -> F.Column:
        at = F.filter(F.sequence(F.lit(0), F.size(w) - 2), lambda i: F.xxhash64(F.get(w, i), F.get(w, i + 1)).isin(wanted))
        hits = F.transform(at, lambda i: F.struct(i.alias("i"), F.get(w, i).alias("a"), F.get(w, i + 1).alias("b")))
        return F.struct(F.size(w).cast("long").alias("n_words"), F.when(F.size(w) > 1, hits).alias("hits"))

    # The one-element array binds the words to a name, so that they are extracted once.
    return F.get(F.transform(F.array(words), facts), F.lit(0))


def scan_licenses(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", listed: list[Template] | None = None, min_cover: float = 0.6, drift: int = 3) -> tuple[DataFrame, DataFrame]:
    """(rows, spans): rows of docs as (key, id, n_words), and verified spans (key, label, base, start, n_places, cover)."""
    spark = docs.sparkSession
    listed = listed or templates()
    places = template_pairs(listed)
    # Both are bounded by the templates' words, which are literals of the caller.
    pairs = F.broadcast(spark.createDataFrame(places, "a string, b string, template int, place int"))
    facts = F.broadcast(spark.createDataFrame([(t.number, t.label, t.base, t.whole, len(t.words) - 1) for t in listed], "template int, label string, base boolean, whole boolean, n_pairs int"))
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = pick(docs, id_col, text_col).select(F.monotonically_increasing_id().alias("key"), F.col(id_col).alias("id"), word_facts(text, places).alias("f"))
    rows, _ = write_table(rows, "license-words")
    hits = rows.select("key", F.explode("f.hits").alias("h")).select("key", "h.*").join(pairs, ["a", "b"])
    votes = hits.groupBy("key", "template", (F.col("i") - F.col("place")).alias("diagonal")).agg(F.collect_set("place").alias("places")).join(facts, "template")
    phrases = votes.where("whole AND size(places) = n_pairs").select("key", "label", "base", F.col("diagonal").alias("start"), F.col("n_pairs").alias("n_places"), F.lit(1.0).alias("cover"))
    # Diagonals within `drift` of the one before belong to one span, which holds the union of their places.
    along = Window.partitionBy("key", "template").orderBy("diagonal")
    apart = F.coalesce(F.col("diagonal") - F.lag("diagonal").over(along) > drift, F.lit(True))
    lines = votes.where("NOT whole AND size(places) * 10 >= n_pairs").withColumn("apart", apart.cast("int")).withColumn("run", F.sum("apart").over(along))
    merged = lines.select("key", "template", "label", "base", "n_pairs", "run", "diagonal", F.explode("places").alias("place")).groupBy("key", "template", "label", "base", "n_pairs", "run")
    merged = merged.agg(F.min(F.struct("diagonal", "place")).alias("first"), F.size(F.collect_set("place")).alias("n_places"))
    notices = merged.select("key", "label", "base", (F.col("first.diagonal") + F.col("first.place")).alias("start"), "n_places", (F.col("n_places") / F.col("n_pairs")).alias("cover")).where(F.col("cover") >= min_cover)
    return rows.select("key", "id", "f.n_words"), phrases.unionByName(notices)


def license_digest(rows: DataFrame, spans: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """One row per row: id, n_words, n_base, first_word, last_word, base_labels, labels, score."""
    found = spans.groupBy("key").agg(
        F.count_if("base").alias("n_base"),
        F.min(F.when(F.col("base"), F.col("start"))).cast("long").alias("first_word"),
        F.max(F.when(F.col("base"), F.col("start"))).cast("long").alias("last_word"),
        F.array_join(F.sort_array(F.collect_set(F.when(F.col("base"), F.col("label")))), ",").alias("base_labels"),
        F.array_join(F.sort_array(F.collect_set("label")), ",").alias("labels"),
        F.max("cover").alias("score"),
    )
    return rows.join(found, "key", "left").select(
        F.col("id").alias(id_col),
        "n_words",
        F.coalesce("n_base", F.lit(0).cast("long")).alias("n_base"),
        "first_word",
        "last_word",
        F.coalesce("base_labels", F.lit("")).alias("base_labels"),
        F.coalesce("labels", F.lit("")).alias("labels"),
        F.coalesce("score", F.lit(0.0)).alias("score"),
    )
