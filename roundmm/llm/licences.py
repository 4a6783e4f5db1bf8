"""Licence scans by diagonal voting: shared word k-grams vote for the offset between text and template."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from roundmm.llm.common import ascii_lower, empty_text, stored

#: Words are runs of ASCII digits, lower-case ASCII letters and all characters beyond ASCII.
BREAKS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
GRAM = 2
#: Offsets this close to each other vote together: so many words may be missing or added.
SLACK = 2
#: Share of a template's grams that a merged diagonal must show.
COVER = 0.7
#: Edits of words, as a share of the template's words, that an aligned span may have; rounded down.
EDITS = 0.3


@dataclass(frozen=True)
class Template:
    label: str
    words: tuple[str, ...]
    exact: bool = False

    @property
    def budget(self) -> int:
        return 0 if self.exact else int(EDITS * len(self.words) + 1e-9)

    @property
    def least_grams(self) -> int:
        n = len(self.words) - GRAM + 1
        return n if self.exact else math.ceil(COVER * n - 1e-9)


# Phrases that are licences by their words alone, and their labels.
PHRASES = (
    Template("gpl", ("gnu", "general", "public", "license"), True),
    Template("apache", ("apache", "license"), True),
    Template("cc-by", ("cc", "by"), True),
    Template("mit", ("mit", "license"), True),
)
# Opening or naming sentences of public licences; up to 60 words each.
SENTENCES = tuple(
    Template(label, tuple(text.split()))
    for label, text in (
        ("apache-2.0", "licensed under the apache license version 2 0"),
        ("mit-notice", "released under the mit license"),
        ("mit-grant", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files"),
        ("gpl-3.0", "this work is licensed under the gnu general public license version 3"),
        ("gpl-notice", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license"),
        ("lgpl", "under the terms of the gnu lesser general public license"),
        ("cc-by-4.0", "licensed under cc by 4 0"),
        ("cc-by-sa", "creative commons attribution sharealike license"),
        ("cc-attribution", "licensed under a creative commons attribution 4 0 international license"),
        ("bsd", "redistribution and use in source and binary forms with or without modification are permitted"),
        ("mpl-2.0", "subject to the terms of the mozilla public license v 2 0"),
        ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee"),
    )
)


def template_grams(spark: SparkSession, templates: tuple[Template, ...]) -> DataFrame:
    rows = [(i, t.label, t.exact, len(t.words) - GRAM + 1, p, t.words[p], t.words[p + 1]) for i, t in enumerate(templates) for p in range(len(t.words) - GRAM + 1)]
    grams = spark.createDataFrame(rows, "template int, label string, exact boolean, n_grams int, t_pos int, w0 string, w1 string")
    return grams.withColumn("gram", F.xxhash64("w0", "w1"))


def template_words(spark: SparkSession, templates: tuple[Template, ...]) -> DataFrame:
    rows = [(i, list(t.words), t.budget) for i, t in enumerate(templates)]
    return spark.createDataFrame(rows, "template int, t_words array<string>, budget int")


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(ascii_lower(text), BREAKS), "")


def scanned(docs: DataFrame, key: list[str], templates: tuple[Template, ...]) -> DataFrame:
    """``key, n_words, grams, words``: number of words of each text, and place, hash and words of its k-grams that stand in a template. The texts are split once;
    grams of no template are dropped where they are made, by the sets of the templates' first words and grams, so only others become rows.
    ``words`` is kept, for the alignment, where a text has as many of the grams of some sentence, wherever they stand, as the votes ask for, else null."""
    pairs = sorted({(t.words[p], t.words[p + 1]) for t in templates for p in range(len(t.words) - GRAM + 1)})
    firsts, joined = sorted({a for a, _ in pairs}), [f"{a} {b}" for a, b in pairs]
    held = docs.select(*key, words_of(empty_text()).alias("words"))
    in_template = lambda w, i: w.isin(firsts) & F.concat_ws(" ", w, F.get("words", i + 1)).isin(joined)
    places = F.array_compact(F.transform("words", lambda w, i: F.when(in_template(w, i), i)))
    held = held.select(*key, "words", F.size("words").cast("long").alias("n_words"), places.alias("places"))
    gram = lambda i: F.struct(i.alias("d_pos"), F.xxhash64(F.get("words", i), F.get("words", i + 1)).alias("gram"), F.get("words", i).alias("d0"), F.get("words", i + 1).alias("d1"))
    held = held.withColumn("found", F.array_distinct(F.transform("places", lambda i: F.concat_ws(" ", F.get("words", i), F.get("words", i + 1)))))
    may_hold = F.lit(False)
    for t in (t for t in templates if not t.exact):
        own = F.array(*[F.lit(f"{a} {b}") for a, b in zip(t.words, t.words[1:])])
        may_hold = may_hold | (F.size(F.filter(own, lambda g: F.array_contains("found", g))) >= t.least_grams)
    kept = F.when(may_hold, F.col("words"))
    return held.select(*key, "n_words", F.transform("places", gram).alias("grams"), kept.alias("words"))


def diagonals(scan: DataFrame, key: list[str], templates: tuple[Template, ...]) -> DataFrame:
    """One row per key, template and offset: ``mask`` has a bit for each template gram found there."""
    at = scan.select(*key, F.inline("grams"))
    # the templates are a constant of the program, so their size is known
    hit = at.join(F.broadcast(template_grams(scan.sparkSession, templates)), "gram").where("d0 = w0 and d1 = w1")
    return hit.groupBy(*key, "template", "label", "exact", "n_grams", (F.col("d_pos") - F.col("t_pos")).alias("offset")).agg(F.bit_or(F.expr("shiftleft(1L, t_pos)")).alias("mask"))


def voted(scan: DataFrame, key: list[str], templates: tuple[Template, ...]) -> DataFrame:
    """The diagonals whose run has enough votes: ``key, template, label, exact, offset, run, cover, ends``. A phrase's diagonal is a run of its own;
    neighbouring diagonals of a sentence make one. ``ends`` are the offsets so near to this one that a span within the edit budget may end on them."""
    reach = max((t.budget for t in templates), default=0)
    by = Window.partitionBy(*key, "template", "exact").orderBy("offset")
    new = F.coalesce((F.col("offset") - F.lag("offset").over(by) > SLACK).cast("int"), F.lit(1))
    found = diagonals(scan, key, templates).withColumn("ends", F.collect_list("offset").over(by.rangeBetween(-reach, reach)))
    found = found.withColumn("_new", F.when(F.col("exact"), 1).otherwise(new))
    found = found.withColumn("run", F.sum("_new").over(by.rowsBetween(Window.unboundedPreceding, 0)))
    mask = F.bit_or("mask").over(Window.partitionBy(*key, "template", "exact", "run"))
    found = found.withColumn("cover", F.bit_count(mask) / F.col("n_grams"))
    enough = F.when(F.col("exact"), F.col("cover") == 1).otherwise(F.col("cover") >= COVER)
    return found.where(enough).select(*key, "template", "label", "exact", "offset", "run", "cover", "ends")


def edits(words: Column, offset: Column, ends: Column, t_words: Column, budget: Column) -> Column:
    """The fewest inserted, deleted or exchanged words between the template and the text from ``offset`` up to the template's end on one of the
    diagonals ``ends``. Each word is written as one character, its place in the template, so the distance of strings is that of words."""
    coded = lambda ws: F.array_join(F.transform(ws, lambda w: F.char(F.array_position(t_words, w) + 32)), "")
    first = F.greatest(offset, F.lit(0))
    window = lambda end: F.slice(words, first + 1, end + F.size(t_words) - first)
    near = F.filter(ends, lambda e: F.abs(e - offset) <= budget)
    return F.array_min(F.transform(near, lambda e: F.levenshtein(coded(window(e)), coded(t_words))))


def spans(scan: DataFrame, key: list[str], templates: tuple[Template, ...] = PHRASES + SENTENCES) -> DataFrame:
    """Licence spans of :func:`scanned` texts: ``key, label, exact, start, cover, edits``. Phrases need all grams on one offset. Of sentences,
    neighbouring offsets are merged, must cover ``COVER`` of the grams, and the text at one of them must align with the template, word by word, within
    ``EDITS`` of its words; ``start`` is where the best alignment begins, the first of equals. Repeated rows vote once."""
    votes = stored(voted(scan, key, templates), "licence-votes")
    phrases = votes.where("exact").select(*key, "label", "exact", F.col("offset").cast("long").alias("start"), "cover", F.lit(0).alias("edits"))
    texts = scan.where("words is not null").select(*[F.col(k).alias(f"_of_{k}") for k in key], "words")
    same = [F.col(k).eqNullSafe(F.col(f"_of_{k}")) for k in key]
    # the templates are a constant of the program, so their size is known
    pair = votes.where("not exact").join(F.broadcast(template_words(scan.sparkSession, templates)), "template").join(texts, same)
    far = edits(F.col("words"), F.col("offset"), F.col("ends"), F.col("t_words"), F.col("budget"))
    each = pair.select(*key, "template", "label", "exact", "run", "cover", "budget", F.struct(far.alias("edits"), F.col("offset").cast("long").alias("start")).alias("at"))
    best = each.groupBy(*key, "template", "label", "exact", "run").agg(F.min("at").alias("at"), F.max("cover").alias("cover"), F.max("budget").alias("budget"))
    return phrases.unionAll(best.where("at.edits <= budget").select(*key, "label", "exact", "at.start", "cover", "at.edits"))


def licence_report(docs: DataFrame) -> DataFrame:
    """Per document: words, phrase places, labels and the best cover.

    Null and empty texts have no words and no labels; null ids and repeated rows each keep their own row with equal
    values; an empty table gives no rows; other columns of ``docs`` are ignored.
    """
    rows = docs.select("doc_id", "text").withColumn("_print", F.unhex(F.md5(empty_text().cast("binary"))))
    scan = stored(scanned(rows, ["doc_id", "_print"], PHRASES + SENTENCES), "licence-scan")
    found = spans(scan.select(F.col("doc_id").alias("_id"), F.col("_print").alias("_p"), "grams", "words"), ["_id", "_p"])
    base = F.when(F.col("exact"), F.col("label"))
    each = found.groupBy("_id", "_p").agg(
        F.count(base).alias("n_base"),
        F.min(F.when(F.col("exact"), F.col("start"))).alias("first_word"),
        F.max(F.when(F.col("exact"), F.col("start"))).alias("last_word"),
        F.concat_ws(",", F.array_sort(F.collect_set(base))).alias("base_labels"),
        F.concat_ws(",", F.array_sort(F.collect_set("label"))).alias("labels"),
        F.max("cover").alias("score"),
    )
    out = scan.select("doc_id", "_print", "n_words").join(each, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("_print") == F.col("_p")), "left")
    return out.select("doc_id", "n_words", F.coalesce("n_base", F.lit(0)).cast("long").alias("n_base"), "first_word", "last_word", F.coalesce("base_labels", F.lit("")).alias("base_labels"), F.coalesce("labels", F.lit("")).alias("labels"), F.coalesce("score", F.lit(0.0)).alias("score"))
