"""License scans by diagonal voting, in DataFrame functions only.

All rolling word 2-grams of all texts are hashed and joined to the positions of
the same hash in license templates (and in the base phrases). A match votes for
its diagonal, document position minus template position. Diagonals that lie
close together are merged, since an added or lost word moves the rest of a copy
to the next diagonal. A merged span is verified: every vote compared the words
themselves, and enough distinct template positions must have voted within a
span not much longer than the template.

Defined cases: a null text has no words; texts of one word have no 2-gram;
repeated rows and null ids give one result row each; an empty table gives an
empty result.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spreadmax.llm.common import WORD

#: The base phrases, and well-known notices that the method adds.
BASE = {"mit license": "mit", "apache license": "apache", "general public license": "gpl"}
NOTICES = {
    "released under the mit license": "mit",
    "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files": "mit",
    "licensed under the apache license version 2 0": "apache",
    "you may not use this file except in compliance with the license": "apache",
    "licensed under the gnu general public license version": "gpl",
    "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license": "gpl",
    "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met": "bsd",
    "this source code form is subject to the terms of the mozilla public license": "mpl",
    "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted": "isc",
    "this is free and unencumbered software released into the public domain": "unlicense",
    "licensed under cc by 4 0": "cc-by",
    "licensed under cc by sa 4 0": "cc-by-sa",
    "licensed under cc by nc 4 0": "cc-by-nc",
    "licensed under a creative commons attribution 4 0 international license": "cc-by",
}
#: 2-grams of these words alone do not vote: they are everywhere.
COMMON = frozenset("a an and any by for in is it may not of on or that the this to under use with you".split())
#: Votes that a long template needs, as a share of its positions; templates up to SHORT positions need all.
SHARE = 0.6
SHORT = 8
#: Diagonals this close merge.
DRIFT = 3


def _template_rows() -> list[tuple[int, str, bool, int, int, int, str, str]]:
    """(template, label, base, positions, words, position, first word, second word)."""
    rows = []
    texts = [(t, label, True) for t, label in BASE.items()] + [(t, label, False) for t, label in NOTICES.items()]
    for n, (text, label, base) in enumerate(texts):
        words = text.split()
        pairs = [p for p in enumerate(zip(words, words[1:], strict=False)) if base or not COMMON.issuperset(p[1])]
        if len(pairs) > 62:
            raise ValueError("a template votes with at most 62 positions")
        rows += [(n, label, base, len(pairs), len(words), k, at, *pair) for k, (at, pair) in enumerate(pairs)]
    return rows


def templates(spark: SparkSession) -> DataFrame:
    """The positions of all templates; a fixed table of a few hundred rows."""
    values = ", ".join(
        f"({n}, '{label}', {str(base).lower()}, {size}, {words}, {k}, {at}, '{a}', '{b}')"
        for n, label, base, size, words, k, at, a, b in _template_rows()
    )
    return spark.sql(
        "SELECT template, label, base, size, words, vote, at, t1, t2, xxhash64(t1, t2) AS h FROM VALUES "
        f"{values} AS t(template, label, base, size, words, vote, at, t1, t2)"
    )


def folded(text: Column) -> Column:
    """Lower case for matching against ASCII words. The Kelvin sign is the only other letter whose lower case is one ASCII letter."""
    return F.lower(F.replace(F.coalesce(text, F.lit("")), F.lit("K"), F.lit("ſ")))


def votes(docs: DataFrame) -> DataFrame:
    """doc_id, text_hash, n_words and one row per match; besides, one row without a match for every row of `docs`.

    A text is known by its id and hash, which do not change when a task runs again.
    """
    words = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.xxhash64(F.coalesce("text", F.lit(""))).alias("text_hash"),
        F.regexp_extract_all(folded(F.col("text")), F.lit(WORD), F.lit(0)).alias("w"),
    )
    grams = F.transform(
        "w",
        lambda x, i: F.struct(
            F.xxhash64(x, F.get(F.col("w"), i + 1)).alias("h"), x.alias("w1"), F.get(F.col("w"), i + 1).alias("w2")
        ),
    )
    mark = F.array(F.struct(F.lit(None).cast("long").alias("h"), F.lit(None).cast("string").alias("w1"), F.lit(None).cast("string").alias("w2")))
    names = ["doc_id", "text_hash", "n_words"]
    # the outer form: the inner one would bring a filter that extracts the words of a text once for each word
    hashed = words.select("doc_id", "text_hash", F.size("w").cast("long").alias("n_words"), F.concat(mark, grams).alias("gs"))
    rolled = hashed.select(*names, F.posexplode_outer("gs").alias("pos", "g"))
    rolled = rolled.select(*names, (F.col("pos") - 1).alias("pos"), F.col("g.h").alias("gh"), F.col("g.w1").alias("w1"), F.col("g.w2").alias("w2"))
    met = rolled.join(F.broadcast(templates(docs.sparkSession)), F.col("gh") == F.col("h"), "left")
    same = F.coalesce((F.col("w1") == F.col("t1")) & (F.col("w2") == F.col("t2")), F.lit(False))
    return (
        met.withColumn("same", same)
        .filter(F.col("same") | (F.col("pos") < 0))
        .select(
            *names, *[F.when(F.col("same"), F.col(c)).alias(c) for c in ("template", "label", "base", "size", "words", "vote", "pos")],
            F.when(F.col("same"), F.col("pos") - F.col("at")).cast("long").alias("diagonal"),
        )
    )


def scan_spans(docs: DataFrame) -> DataFrame:
    """One row per span (and one without a span for every text, with `copies`, the rows of `docs` that have it):
    doc_id, text_hash, n_words, found, label, base, start, stop, share, copies."""
    text = ["doc_id", "text_hash", "n_words"]
    by_diagonal = (
        votes(docs)
        .groupBy(*text, "template", "label", "base", "size", "words", "diagonal")
        .agg(
            F.expr("bit_or(shiftleft(1L, vote))").alias("voted"),
            F.min("pos").alias("start"),
            (F.max("pos") + 1).alias("stop"),
            F.count(F.when(F.col("template").isNull(), 1)).alias("copies"),
        )
    )
    near = Window.partitionBy(*text, "template").orderBy("diagonal")
    apart = (F.col("diagonal") - F.lag("diagonal").over(near) > DRIFT) | F.col("base") | F.lag("diagonal").over(near).isNull()
    merged = (
        by_diagonal.withColumn("first", F.coalesce(apart, F.lit(True)).cast("int"))
        .withColumn("run", F.sum("first").over(near))
        .groupBy(*text, "template", "label", "base", "size", "words", "run")
        .agg(
            F.max("copies").alias("copies"), F.bit_or("voted").alias("voted"), F.min("start").alias("start"), F.max("stop").alias("stop"), F.min("diagonal").alias("diagonal")
        )
    )
    share = F.bit_count("voted") / F.col("size")
    need = F.when(F.col("base") | (F.col("size") <= SHORT), 1.0).otherwise(SHARE)
    fits = F.col("stop") - F.col("start") + 1 <= 2 * F.col("words")
    return merged.select(
        *text, F.coalesce((share >= need) & fits, F.lit(False)).alias("found"),
        "label", "base", F.when(F.col("base"), F.col("diagonal")).otherwise(F.col("start")).cast("long").alias("start"),
        F.col("stop").cast("long").alias("stop"), share.alias("share"), "copies",
    )


def scan_licenses(docs: DataFrame) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score."""
    place = F.col("found") & F.col("base")
    names = lambda yes: F.concat_ws(",", F.array_sort(F.collect_set(F.when(yes, F.col("label")))))
    return (
        scan_spans(docs)
        .groupBy("doc_id", "text_hash", "n_words")
        .agg(
            F.count(F.when(place, 1)).alias("n_base"),
            F.min(F.when(place, F.col("start"))).alias("first_word"),
            F.max(F.when(place, F.col("start"))).alias("last_word"),
            names(place).alias("base_labels"),
            names(F.col("found")).alias("labels"),
            F.coalesce(F.max(F.when(F.col("found"), F.col("share"))), F.lit(0.0)).alias("score"),
            F.max("copies").alias("copies"),
        )
        .withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), "copies")))  # repeated rows come back
        .drop("text_hash", "copies", "copy")
    )


assert all(re.fullmatch("[a-z0-9 ]+", t) for t in (*BASE, *NOTICES))
