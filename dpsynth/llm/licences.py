"""Licence scan in DataFrame operations only: a positional index over rare licence words.

A fixed set of licence notices is indexed by word: postings (template, position).  Files keep
only the places of words that occur in the index.  Which of them are rare is measured on the
corpus (document frequency over all files).  Of each template that a file may hold, the rarest
words that the file has are looked up first, RARE_WORDS of those in its mandatory phrases, so a
file may hold any number of notices; their postings give alignments (template, file position -
template position).  The other words then confirm or refute an alignment by the same relative
position: a bit mask per alignment has the template words that stand where they should.  A label
needs its mandatory phrases whole and enough of the rest.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dpsynth.llm.common import byte_text, cut

#: The base phrases and their labels.
BASE = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}

#: Notices (lower case, words only; at most 62 words) and the phrases that must stand in them.
TEMPLATES = {
    "apache-2.0": ("licensed under the apache license version 2 0", ["apache license", "2 0"]),
    "gpl-3.0": ("this work is licensed under the gnu general public license version 3", ["gnu general public license", "version 3"]),
    "gpl-2.0": ("this work is licensed under the gnu general public license version 2", ["gnu general public license", "version 2"]),
    "lgpl": ("licensed under the gnu lesser general public license version", ["lesser general public license"]),
    "agpl": ("licensed under the gnu affero general public license version", ["affero general public license"]),
    "mit": ("released under the mit license", ["mit license"]),
    "mit-grant": ("permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", ["permission is hereby granted", "free of charge"]),
    "bsd": ("redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", ["redistribution and use in source and binary forms"]),
    "mpl-2.0": ("this source code form is subject to the terms of the mozilla public license v 2 0", ["mozilla public license"]),
    "isc": ("permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", ["permission to use copy modify"]),
    "cc-by-4.0": ("licensed under cc by 4 0", ["cc by 4 0"]),
    "cc-by-sa": ("licensed under cc by sa 4 0", ["cc by sa"]),
    "cc-by-nc": ("licensed under cc by nc 4 0", ["cc by nc"]),
    "cc-by-nd": ("licensed under cc by nd 4 0", ["cc by nd"]),
    "cc0": ("dedicated to the public domain under cc0 1 0 universal", ["cc0"]),
    "unlicense": ("this is free and unencumbered software released into the public domain", ["unencumbered software released into the public domain"]),
    "copyright": ("copyright c all rights reserved", ["all rights reserved"]),
}
#: Rarest mandatory words of each template that are looked up in a file, and the share of a template that must match.
RARE_WORDS, MIN_SHARE = 8, 0.6

POSTINGS = [(word, name, i) for name, (notice, _) in TEMPLATES.items() for i, word in enumerate(notice.split())]
VOCABULARY = sorted({w for w, _, _ in POSTINGS} | {w for p in BASE for w in p.split()})


def phrase_mask(notice: str, phrase: str) -> int:
    """Bits of the template positions that a phrase covers."""
    words, part = notice.split(), phrase.split()
    at = next(i for i in range(len(words)) if words[i : i + len(part)] == part)
    return ((1 << len(part)) - 1) << at


def word_places(docs: DataFrame) -> DataFrame:
    """doc_id, row_hash, n_words, hits: array<struct<p, w>> (the places of index words), and seen:
    the distinct words among them.

    The only step that reads texts; cut behind here, as the hits are used several times.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    words = F.regexp_extract_all(byte_text(F.col("text")), F.lit("[0-9a-z\\x{80}-\\x{ff}]+"), F.lit(0))
    places = F.filter(F.transform(words, lambda w, i: F.when(w.isin(VOCABULARY), F.struct(i.alias("p"), w.alias("w")))), lambda x: x.isNotNull())
    found = rows.select("doc_id", F.xxhash64("text").alias("row_hash"), F.size(words).cast("long").alias("n_words"), places.alias("hits"))
    return cut(found.withColumn("seen", F.array_distinct(F.transform("hits", lambda x: x["w"]))))


def base_places(hits: Column) -> Column:
    """array<struct<p, label>> of the base phrases: index words stand next to each other in hits
    if they do in the text, so a phrase is a run of hits with consecutive positions."""

    def label(x: Column, i: Column) -> Column:
        out = F.lit(None).cast("string")
        for phrase, name in BASE.items():
            words = phrase.split()
            fits = x["w"] == words[0]
            for k, w in enumerate(words[1:], 1):
                then = F.get(hits, i + k)
                fits = fits & F.coalesce((then["w"] == w) & (then["p"] == x["p"] + k), F.lit(False))
            out = F.when(fits, F.lit(name)).otherwise(out)
        return F.struct(x["p"].alias("p"), out.alias("label"))

    return F.filter(F.transform(hits, label), lambda x: x["label"].isNotNull())


def alignments(places: DataFrame, rare_words: int = RARE_WORDS) -> DataFrame:
    """doc_id, row_hash, label, share: templates found in a file with their mandatory phrases.

    Document frequencies are counted over all files and come to the driver: one number for each
    word of the fixed vocabulary.
    """
    spark = places.sparkSession
    seen = {r["w"]: r["n"] for r in places.select(F.explode("seen").alias("w")).groupBy("w").agg(F.count("*").alias("n")).collect()}
    total = sum(seen.values()) + 1
    idf = {w: math.log(total / (1 + seen.get(w, 0))) for w in VOCABULARY}
    order = {w: i for i, w in enumerate(sorted(VOCABULARY, key=lambda w: (-idf[w], w)))}
    # an alignment that counts has all mandatory words, so also the rarest of them, whatever else the file holds
    leads = {t: sorted({w for p in must for w in p.split()}, key=order.get)[:rare_words] for t, (_, must) in TEMPLATES.items()}
    posts = F.broadcast(spark.createDataFrame([(w, t, q, w in leads[t]) for w, t, q in POSTINGS], "w string, label string, q int, is_rare boolean"))
    # a template that lacks a word of its mandatory phrases cannot be in the file: most files end here
    must = F.array(*[F.struct(F.lit(t).alias("label"), F.array(*[F.lit(w) for w in sorted({w for p in must for w in p.split()})]).alias("words")) for t, (_, must) in TEMPLATES.items()])
    alive = places.where(F.size("seen") > 0).withColumn("alive", F.transform(F.filter(must, lambda t: F.size(F.array_except(t["words"], F.col("seen"))) == 0), lambda t: t["label"])).where(F.size("alive") > 0)
    each = alive.select("doc_id", "row_hash", "alive", F.explode("hits").alias("x")).select("doc_id", "row_hash", "alive", F.col("x.p").alias("p"), F.col("x.w").alias("w"))
    aligned = each.join(posts, "w").where(F.array_contains("alive", F.col("label"))).groupBy("doc_id", "row_hash", "label", (F.col("p") - F.col("q")).alias("offset")).agg(F.bit_or(F.expr("shiftleft(1L, q)")).alias("mask"), F.max("is_rare").alias("by_rare"))
    rules = F.broadcast(spark.createDataFrame([(t, len(n.split()), [phrase_mask(n, p) for p in must]) for t, (n, must) in TEMPLATES.items()], "label string, size int, must array<long>"))
    share = F.bit_count("mask") / F.col("size")
    whole = F.forall("must", lambda m: m.bitwiseAND(F.col("mask")) == m)
    return aligned.where("by_rare").join(rules, "label").where(whole & (share >= MIN_SHARE)).groupBy("doc_id", "row_hash", "label").agg(F.max(share).alias("share"))


def scan(docs: DataFrame, rare_words: int = RARE_WORDS) -> DataFrame:
    """Per row of ``docs``: doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score.

    The score is the largest share of a found template, 0 without one.  rare_words: how many of
    each template's mandatory words, rarest first, are looked up to find alignments; every
    alignment that counts has all of them, so any number gives the same labels.  Null and
    empty texts have no words; repeated rows each give a row; an empty table gives an empty
    result; other columns are not read.
    """
    places = word_places(docs)
    found = alignments(places, rare_words).groupBy("doc_id", "row_hash").agg(F.collect_set("label").alias("more"), F.max("share").alias("best"))
    found = found.select(F.col("doc_id").alias("found_id"), F.col("row_hash").alias("found_hash"), "more", "best")
    based = places.select("doc_id", "row_hash", "n_words", base_places(F.col("hits")).alias("base"))
    met = based.join(found, F.col("doc_id").eqNullSafe(F.col("found_id")) & (F.col("row_hash") == F.col("found_hash")), "left")
    at, names = F.transform("base", lambda x: x["p"]), F.transform("base", lambda x: x["label"])
    joined = lambda a: F.array_join(F.array_sort(F.array_distinct(a)), ",")
    return met.select("doc_id", "n_words", F.size("base").cast("long").alias("n_base"), F.array_min(at).cast("long").alias("first_word"), F.array_max(at).cast("long").alias("last_word"), joined(names).alias("base_labels"), joined(F.concat(names, F.coalesce("more", F.array().cast("array<string>")))).alias("labels"), F.coalesce("best", F.lit(0.0)).alias("score"))
