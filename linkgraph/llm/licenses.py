"""License notices in whole texts, on DataFrame and SQL functions alone.

Base labels are places of fixed phrases.  Beyond them an exact set-similarity
join finds every text block that contains enough of a template's words, where a
block is any stretch of neighbouring words, little longer than the template,
whatever lines it is wrapped over.  Words are ordered by their frequency over
all documents, rarest first.  A block can match only if it holds a word of the
template's prefix (prefix filter), so blocks are taken round such words alone;
it must hold enough of the template's words (length filter), and still have
enough words left after the first shared ones (positional filter); the
survivors are compared in full, at every start.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from linkgraph.llm.common import materialise

# Phrases and their labels.
PHRASES = (("cc by", "cc-by"), ("general public license", "gpl"), ("all rights reserved", "reserved"))

#: Short notices, by label.  Several may share one.
TEMPLATES = (
    ("apache-2.0", "Licensed under the Apache License, Version 2.0"),
    ("mit", "Released under the MIT License"),
    ("mit", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files"),
    ("gpl-3.0", "This work is licensed under the GNU General Public License, version 3"),
    ("gpl-2.0", "This program is free software; you can redistribute it under the terms of the GNU General Public License version 2"),
    ("lgpl", "GNU Lesser General Public License"),
    ("agpl", "GNU Affero General Public License"),
    ("cc-by-nc-4.0", "Licensed under CC BY-NC 4.0"),
    ("cc-by-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License"),
    ("cc-by-sa-4.0", "This work is licensed under a Creative Commons Attribution ShareAlike 4.0 International License"),
    ("bsd", "Redistribution and use in source and binary forms, with or without modification, are permitted"),
    ("mpl-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0"),
    ("isc", "Permission to use, copy, modify, and or distribute this software for any purpose with or without fee is hereby granted"),
    ("unlicense", "This is free and unencumbered software released into the public domain"),
)

_SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


@dataclass(frozen=True)
class LicenseParams:
    templates: tuple[tuple[str, str], ...] = TEMPLATES
    #: Share of a template's distinct words that a block must contain.
    containment: float = 0.85
    #: Words of a block by those of the template, and added to them.
    stretch: float = 1.25
    slack: int = 2


def lowered(text: Column | str) -> Column:
    return F.translate(F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit("")), _UPPER, _LOWER)


def words_of(lower: Column) -> Column:
    return F.filter(F.split(lower, _SEPARATORS), lambda w: w != "")


def _split(text: str) -> list[str]:
    return [w for w in re.split(r"[\x00-\x2f\x3a-\x60\x7b-\x7f]+", text.translate(str.maketrans(_UPPER, _LOWER))) if w]


def _template_words(text: str) -> list[str]:
    return list(dict.fromkeys(_split(text)))


def _span(words: int, params: LicenseParams) -> int:
    """Words of the blocks that a template of so many words is compared with."""
    return max(words + params.slack, -int(-words * params.stretch // 1))


def _needed(size: int, containment: float) -> int:
    return -int(-size * containment // 1)


def _places(phrase: str) -> str:
    """SQL for the starts of a phrase in ``ws``, for texts that may hold it at all."""
    parts = phrase.split(" ")
    gate = " and ".join(f"contains(lower, '{p}')" for p in parts)
    equal = " and ".join(f"ws[i + {k}] = '{p}'" if k else f"ws[i] = '{p}'" for k, p in enumerate(parts))
    last = f"size(ws) - {len(parts)}"
    return f"if({gate} and {last} >= 0, filter(sequence(0, greatest({last}, 0)), i -> {equal}), cast(array() as array<int>))"


def scanned(docs: DataFrame, params: LicenseParams = LicenseParams()) -> DataFrame:
    """One pass over the texts: word counts, base places, the template words held, and their places.

    Places are kept only for texts that hold enough words of some template.
    """
    lists = sorted({tuple(_template_words(t)) for _, t in params.templates})
    vocabulary = ", ".join(f"'{w}'" for w in sorted({w for ws in lists for w in ws}))
    base = docs.select("doc_id", lowered("text").alias("lower"))
    base = base.withColumn("ws", words_of(F.col("lower")))
    for k, (phrase, _) in enumerate(PHRASES):
        base = base.withColumn(f"at{k}", F.expr(_places(phrase)))
    base = base.withColumn("held", F.expr(f"array_intersect(ws, array({vocabulary}))"))
    hits = ", ".join(f"at{k}" for k in range(len(PHRASES)))
    labels = F.concat(*[F.when(F.size(f"at{k}") > 0, F.array(F.lit(label))).otherwise(F.expr("cast(array() as array<string>)")) for k, (_, label) in enumerate(PHRASES)])
    enough = " or ".join(f"size(array_intersect(held, array({', '.join(map(repr, ws))}))) >= {_needed(len(ws), params.containment)}" for ws in lists)
    least = min(_needed(len(ws), params.containment) for ws in lists)
    places = f"filter(transform(ws, (w, i) -> if(w in ({vocabulary}), named_struct('i', i, 'w', w), null)), x -> x is not null)"
    out = base.select(
        "doc_id",
        F.size("ws").cast("long").alias("n_words"),
        F.expr(f"concat({hits})").alias("places"),
        labels.alias("base_labels"),
        "held",
        F.expr(f"if(size(held) >= {least} and ({enough}), {places}, cast(array() as array<struct<i:int,w:string>>))").alias("at"),
    )
    return out.withColumn("rid", F.monotonically_increasing_id())


def matched_blocks(texts: DataFrame, frequency: DataFrame, params: LicenseParams = LicenseParams()) -> DataFrame:
    """Exact join of the blocks of ``(rid, at)`` with the templates: (rid, label, share).

    ``at`` lists the template words of a text with their places, in order.
    """
    spark = texts.sparkSession
    rows = [(k, label, _template_words(text), _span(len(_split(text)), params)) for k, (label, text) in enumerate(params.templates)]
    rows = [(k, label, ws, _needed(len(ws), params.containment), span) for k, label, ws, span in rows]
    templates = spark.createDataFrame(rows, "template int, label string, t_set array<string>, needed int, span int")
    # one row a template word: of fixed size, as are the templates
    freq = F.broadcast(frequency)
    ordered = (
        templates.withColumn("word", F.explode("t_set"))
        .join(freq, "word", "left")
        .groupBy("template", "label", "t_set", "needed", "span")
        .agg(F.array_sort(F.collect_list(F.struct(F.coalesce("df", F.lit(0)).alias("df"), "word"))).alias("o"))
        .select("template", "label", "needed", "span", F.col("o.word").alias("t_ws"))
    )
    prefix = ordered.select("*", F.posexplode(F.expr("slice(t_ws, 1, size(t_ws) - needed + 1)")).alias("t_pos", "word"))
    # blocks are taken round the words of a prefix
    marks = texts.select("rid", "at", F.explode("at").alias("x")).select("rid", "at", F.col("x.i").alias("i"), F.col("x.w").alias("word"))
    # a block's rarest shared word is its mark, so that only words after the mark in the order can add to it
    near = F.expr("filter(at, x -> x.i > i - span and x.i < i + span and array_position(t_ws, x.w) > t_pos)")
    blocks = marks.join(F.broadcast(prefix), "word").withColumn("block", near).drop("at")
    blocks = blocks.filter(F.expr("size(array_distinct(block.w)) >= needed"))
    share = F.expr("array_max(transform(block, s -> size(array_distinct(transform(filter(block, x -> x.i >= s.i and x.i < s.i + span), x -> x.w)))))")
    found = blocks.select("rid", "label", "needed", F.size("t_ws").alias("t_size"), share.alias("n")).filter("n >= needed")
    return found.select("rid", "label", (F.col("n") / F.col("t_size")).alias("share"))


def licenses(docs: DataFrame, params: LicenseParams = LicenseParams()) -> DataFrame:
    """Base places, labels and a score for every row of ``docs``.

    Null and empty texts have no words and no labels; rows that repeat a doc_id
    give one row each; other columns are ignored.  ``score`` is 1 where a base
    phrase stands, else the greatest containment found, else 0.
    """
    rows = materialise(scanned(docs, params), "license_scan")
    frequency = rows.select(F.explode("held").alias("word")).groupBy("word").agg(F.count(F.lit(1)).alias("df"))
    found = matched_blocks(rows.filter("size(at) > 0").select("rid", "at"), frequency, params).groupBy("rid").agg(F.array_sort(F.collect_set("label")).alias("more"), F.max("share").alias("share"))
    out = rows.drop("at", "held").join(found, "rid", "left")
    none = F.expr("cast(array() as array<string>)")
    return out.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        "n_words",
        F.size("places").cast("long").alias("n_base"),
        F.array_min("places").cast("long").alias("first_word"),
        F.array_max("places").cast("long").alias("last_word"),
        F.array_join(F.array_sort("base_labels"), ",").alias("base_labels"),
        F.array_join(F.array_sort(F.array_union("base_labels", F.coalesce("more", none))), ",").alias("labels"),
        F.when(F.size("places") > 0, F.lit(1.0)).otherwise(F.coalesce("share", F.lit(0.0))).alias("score"),
    )


def op7_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    """License notices in the whole of ``documents``."""
    return licenses(spark.read.parquet(f"{sf_dir}/documents.parquet"))
