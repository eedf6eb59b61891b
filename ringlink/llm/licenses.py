"""License notices: exact phrases, and an exact set-similarity join of text blocks with templates. DataFrame functions only."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ringlink.llm.common import settle

PHRASES = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}
#: Our own short notices; a block that holds most of a notice's words gets its label. Of four words or fewer all are
#: needed at the threshold .8, so forms that differ in one word stay apart.
TEMPLATES = {
    "apache-2.0": "licensed under the apache license version 2.0",
    "cc-by-nc-4.0": "cc by nc 4",
    "gpl-3.0": "public license version 3",
    "mit": "permission is hereby granted free of charge to any person obtaining a copy of this software",
    "bsd": "redistribution and use in source and binary forms with or without modification are permitted",
    "apache": "apache license version 2",
    "mit-short": "under the mit license",
    "bsd-short": "under the bsd license",
    "cc-by-sa": "commons attribution sharealike license",
}
#: Labels of short forms that stand for a license above.
SAME = {"apache": "apache-2.0", "mit-short": "mit", "bsd-short": "bsd"}
_W = r"[0-9A-Za-z\x{80}-\x{10FFFF}]"
_GAP = r"[^0-9A-Za-z\x{80}-\x{10FFFF}]+"


def _lower(c: Column) -> Column:
    return F.translate(c, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def words(text: Column) -> Column:
    return F.filter(F.split(_lower(text), _GAP), lambda w: w != "")


def _regex(phrase: str) -> str:
    return f"(?<!{_W})" + _GAP.join(f"(?i:{w})" for w in phrase.split()) + f"(?!{_W})"


def base(docs: DataFrame) -> DataFrame:
    """docs (doc_id, text) with the phrase columns; null text is empty. Only texts with a phrase are split into words."""
    text = F.coalesce(F.col("text"), F.lit(""))
    hit = text.rlike("|".join(map(_regex, PHRASES)))
    out = docs.withColumn("n_words", F.regexp_count(text, F.lit(_W + "++")).cast("long")).withColumn("_w", F.when(hit, words(text)))

    def places(phrase: str) -> Column:
        p = phrase.split()
        last = F.size("_w") - len(p)
        at = F.sequence(F.lit(0), F.greatest(last, F.lit(0)))

        def here(i: Column) -> Column:
            same = i <= last
            for k, w in enumerate(p):
                same = same & (F.get("_w", i + k) == w)
            return F.coalesce(same, F.lit(False))

        return F.when(F.col("_w").isNotNull(), F.filter(at, here)).otherwise(F.array().cast("array<int>"))

    for i, phrase in enumerate(PHRASES):
        out = out.withColumn(f"_p{i}", places(phrase))
    all_ = F.concat(*(F.col(f"_p{i}") for i in range(len(PHRASES))))
    labels = F.array_sort(F.array_compact(F.array(*(F.when(F.size(f"_p{i}") > 0, F.lit(v)) for i, v in enumerate(PHRASES.values())))))
    out = out.withColumn("n_base", F.size(all_).cast("long")).withColumn("first_word", F.array_min(all_).cast("long")).withColumn("last_word", F.array_max(all_).cast("long")).withColumn("_base", labels)
    return out.drop("_w", *(f"_p{i}" for i in range(len(PHRASES))))


def containment_join(docs: DataFrame, threshold: float = 0.8) -> DataFrame:
    """(doc_id, hash, label, containment): every window of words that holds `threshold` or more of a template's distinct words.

    A block is any run of words half as long again as the template, over line ends, so a wrapped notice is found and
    words scattered over a page are none. Template words are ordered by how many documents have them, rarest first
    (global frequency order). A window that meets the threshold holds one of the template's first size - need + 1 words
    (prefix), so windows are tried only around those; it has `need` words at least (length); a match whose first word
    in that order is at place i can reach size - i (position), so around a word at place i only the words from i on
    count: a window with a rarer one is tried around that. The templates are a fixed list.
    """
    spark = docs.sparkSession
    vocab = sorted({w for t in TEMPLATES.values() for w in words_of(t)})
    text = F.coalesce(F.col("text"), F.lit(""))
    mine = docs.select("doc_id", F.xxhash64(text).alias("hash"), text.alias("text"))
    any_word = rf"(?<!{_W})(?i:" + "|".join(vocab) + rf")(?!{_W})"
    seen = mine.where(F.col("text").rlike(any_word)).select(F.explode(F.array_intersect(words("text"), F.array(*map(F.lit, vocab)))).alias("w")).groupBy("w").agg(F.count("*").alias("n"))
    often = {r["w"]: r["n"] for r in seen.collect()}  # the templates' words only
    rows, prefixes = [], set()
    for label, notice in TEMPLATES.items():
        order = sorted(words_of(notice), key=lambda w: (often.get(w, 0), w))
        need = math.ceil(threshold * len(order) - 1e-9)
        for i, w in enumerate(order[: len(order) - need + 1]):
            rows.append((SAME.get(label, label), w, i, need, len(order), math.ceil(1.5 * len(notice.split())), order[i:]))
            prefixes.add(w)
    prefix = spark.createDataFrame(rows, "label string, w string, place int, need int, size int, wide int, notice array<string>")
    rare = rf"(?<!{_W})(?i:" + "|".join(sorted(prefixes)) + rf")(?!{_W})"
    held = mine.where(F.col("text").rlike(rare)).select("doc_id", "hash", words("text").alias("tokens"))
    widest = max(r[5] for r in rows)
    # what stands around each place of a prefix word: a window's width on both sides, not the text
    wanted = F.array(*map(F.lit, sorted(prefixes)))
    at = F.filter(F.sequence(F.lit(0), F.size("tokens") - 1), lambda i: F.array_contains(wanted, F.get("tokens", i)))
    near = F.transform(at, lambda i: F.struct(F.get("tokens", i).alias("w"), F.least(i, F.lit(widest - 1)).alias("at"), F.slice("tokens", F.greatest(i - (widest - 1), F.lit(0)) + 1, F.lit(2 * widest - 1)).alias("near")))
    spots = held.where(F.size("tokens") > 0).select("doc_id", "hash", F.explode(near).alias("p")).select("doc_id", "hash", "p.*")
    pairs = spots.join(F.broadcast(prefix), "w").where((F.size("near") >= F.col("need")) & (F.size("notice") >= F.col("need")))
    starts = F.sequence(F.greatest(F.col("at") - F.col("wide") + 1, F.lit(0)), F.col("at"))
    both = F.array_max(F.transform(starts, lambda s: F.size(F.array_intersect(F.slice("near", s + 1, F.col("wide")), F.col("notice")))))
    return pairs.withColumn("both", both).where(F.col("both") >= F.col("need")).select("doc_id", "hash", "label", (F.col("both") / F.col("size")).alias("containment"))


def words_of(notice: str) -> list[str]:
    return sorted(set(notice.replace(".", " ").split()))


def digest(docs: DataFrame) -> DataFrame:
    docs = docs.select("doc_id", "text")
    more = settle(containment_join(docs).groupBy("doc_id", "hash").agg(F.collect_set("label").alias("_more"), F.max("containment").alias("_c")))
    b = base(docs.withColumn("hash", F.xxhash64(F.coalesce(F.col("text"), F.lit(""))))).drop("text")
    out = b.alias("b").join(more.select(F.col("doc_id").alias("_d"), F.col("hash").alias("_h"), "_more", "_c"), F.col("doc_id").eqNullSafe(F.col("_d")) & (F.col("hash") == F.col("_h")), "left")
    labels = F.array_sort(F.array_union("_base", F.coalesce("_more", F.array().cast("array<string>"))))
    score = F.when(F.size("_base") > 0, F.lit(1.0)).otherwise(F.coalesce("_c", F.lit(0.0)))
    return out.select("doc_id", "n_words", "n_base", "first_word", "last_word", F.array_join("_base", ",").alias("base_labels"), F.array_join(labels, ",").alias("labels"), score.alias("score"))
