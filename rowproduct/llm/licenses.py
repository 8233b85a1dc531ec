"""License scan by diagonal voting, in native expressions only.

Every adjacent word pair of a text is joined by its hash to the places it has in the license phrases, word for word;
a match votes for its diagonal (text place minus phrase place), and a diagonal keeps which of the phrase's places it
has. Neighbouring diagonals merge: from each, a band of `drift` more ones, never chained further, so that a
band is one copy with at most `drift` words put in. A band with enough different places is verified: the places must rise in
text and phrase together, in order, for the share `cover` of the phrase's pairs, and words that tell licenses apart
(`must`) have to be there. Of overlapping bands the best one stays. Base phrases need every pair on one diagonal.

Defined results: null and empty text has no words and no labels; repeated rows are scanned
alike; an empty table gives an empty result; a text's words never leave its row except in
matched pairs, so very long texts add no group; extra columns are ignored. Phrases have 2 to 64 words.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"


@dataclass(frozen=True)
class Phrase:
    """must: words without which a span is none of this phrase."""

    words: str
    label: str
    base: bool = False
    must: str = ""


# Base phrases and labels.
BASE = (Phrase("cc by", "cc-by", True), Phrase("general public license", "gpl", True), Phrase("all rights reserved", "reserved", True))
# Notices of well-known licenses.
NOTICES = (
    Phrase("released under the mit license", "mit", must="mit"),
    Phrase("permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", "mit"),
    Phrase("licensed under the apache license version 2 0", "apache-2.0", must="apache"),
    Phrase("you may not use this file except in compliance with the license", "apache-2.0"),
    Phrase("licensed under cc by nc 4 0", "cc-by-nc-4.0", must="cc by nc"),
    Phrase("licensed under cc by sa 4 0", "cc-by-sa-4.0", must="cc by sa"),
    Phrase("licensed under the gnu general public license version 3", "gpl-3.0", must="3"),
    Phrase("licensed under the gnu general public license version 2", "gpl-2.0", must="2"),
    Phrase("gnu lesser general public license", "lgpl", must="lesser"),
    Phrase("gnu affero general public license", "agpl", must="affero"),
    Phrase("redistribution and use in source and binary forms with or without modification are permitted", "bsd"),
    Phrase("permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", "isc"),
    Phrase("subject to the terms of the mozilla public license v 2 0", "mpl-2.0", must="mozilla"),
    Phrase("this is free and unencumbered software released into the public domain", "unlicense"),
)
COVER, DRIFT = 0.8, 2


def must_masks(p: Phrase) -> list[int]:
    """For each word that must be there, the places of pairs that hold it, as bits."""
    w = p.words.split()
    bits = lambda word: sum(1 << i for i in range(len(w) - 1) if word in (w[i], w[i + 1]))
    return [bits(x) for x in p.must.split()]


def pair_table(spark, phrases) -> DataFrame:
    """Places of every adjacent word pair; as many rows as the fixed phrases have words."""
    if any(not 2 <= len(p.words.split()) <= 64 for p in phrases):
        raise ValueError("phrases have 2 to 64 words")
    rows = [(k, i, w[i], w[i + 1]) for k, p in enumerate(phrases) for w in [p.words.split()] for i in range(len(w) - 1)]
    return spark.createDataFrame(rows, "phrase int, at int, ta string, tb string").withColumn("h", F.xxhash64("ta", "tb"))


def phrase_table(spark, phrases) -> DataFrame:
    rows = [(k, p.label, p.base, len(p.words.split()) - 1, must_masks(p)) for k, p in enumerate(phrases)]
    return spark.createDataFrame(rows, "phrase int, label string, base boolean, pairs int, must array<long>")


def _rising(band, pairs):
    """The most places of a band's diagonals (d, mask) that rise in text and phrase together."""
    places = F.flatten(F.transform(band, lambda x: F.transform(
        F.filter(F.sequence(F.lit(0), pairs - 1), lambda i: F.getbit(x["mask"], i) == 1),
        lambda i: F.struct((x["d"] + i).alias("t"), (-i).alias("back")))))
    longest = lambda acc, m: F.transform(acc, lambda x, j: F.when(
        j == -m["back"], F.greatest(x, F.coalesce(F.array_max(F.slice(acc, 1, -m["back"])), F.lit(0)) + 1)).otherwise(x))
    return F.array_max(F.aggregate(F.array_sort(places), F.array_repeat(F.lit(0), pairs), longest))


def spans(df: DataFrame, id_col: str = "doc_id", text: str = "text", phrases=BASE + NOTICES, cover: float = COVER, drift: int = DRIFT) -> DataFrame:
    """One row per text and found span (label null where nothing is found): row key, n_words,
    label, base, first word, last word, places and cover."""
    # lower() would fold the Kelvin sign to k: it is kept apart, so only A-Z meet the phrases' letters.
    low = F.lower(F.replace(F.coalesce(text, F.lit("")), F.lit("K"), F.lit("ĸ")))
    rows = df.select(F.col(id_col), F.monotonically_increasing_id().alias("_row"), F.regexp_extract_all(low, F.lit(WORD), F.lit(0)).alias("_w"))
    rows = rows.withColumn("n_words", F.size("_w").cast("long"))
    pairs = rows.select(id_col, "_row", "n_words", F.posexplode_outer(F.arrays_zip(F.col("_w").alias("a"), F.slice("_w", 2, F.greatest(F.size("_w"), F.lit(1))).alias("b"))).alias("at_text", "p"))
    pairs = pairs.select(id_col, "_row", "n_words", "at_text", F.col("p.a").alias("a"), F.col("p.b").alias("b")).withColumn("h", F.xxhash64("a", "b"))
    t = F.broadcast(pair_table(df.sparkSession, phrases))  # fixed size
    hit = pairs.join(t, (pairs.h == t.h) & (pairs.a == t.ta) & (pairs.b == t.tb), "left")
    key = [id_col, "_row", "n_words"]
    # Votes by diagonal, a bit for each place. Texts without a match keep one row, whose phrase is null.
    diag = hit.groupBy(*key, "phrase", F.when(F.col("phrase").isNotNull(), F.col("at_text") - F.col("at")).alias("d")).agg(F.bit_or(F.expr("shiftleft(1L, at)")).alias("mask"))
    diag = diag.join(F.broadcast(phrase_table(df.sparkSession, phrases)), "phrase", "left")  # fixed size
    per = W.partitionBy("_row", "phrase").orderBy("d")
    ahead, beside = per.rangeBetween(0, drift), per.rangeBetween(-drift, drift)
    band = diag.withColumn("band", F.when(F.col("base"), F.array(F.struct("d", "mask"))).otherwise(F.collect_list(F.struct("d", "mask")).over(ahead)))
    band = band.withColumn("any", F.aggregate("band", F.lit(0).cast("long"), lambda x, y: x.bitwiseOR(y["mask"])))
    enough = F.bit_count("any") >= F.col("pairs") * F.when(F.col("base"), F.lit(1.0)).otherwise(F.lit(cover))
    told = F.forall("must", lambda m: m.bitwiseAND(F.col("any")) != 0)
    band = band.withColumn("votes", F.when(enough & told, F.when(F.col("base"), F.col("pairs")).otherwise(_rising(F.col("band"), F.col("pairs")))))
    band = band.withColumn("cover", F.col("votes") / F.col("pairs")).withColumn("cover", F.when(F.col("cover") >= cover, F.col("cover")))
    band = band.withColumn("best", F.max(F.when(F.col("cover").isNotNull(), F.struct("cover", (-F.col("d")).alias("d")))).over(beside))
    good = F.col("cover").isNotNull() & (F.col("base") | (F.col("best.d") == -F.col("d")))
    # From the band's first place in the text to the word after its last.
    places = lambda f: F.transform("band", f)
    low_bit = lambda m: F.length(F.regexp_extract(F.reverse(F.bin(m)), "^0*", 0))
    first = F.array_min(places(lambda x: x["d"] + low_bit(x["mask"])))
    last = F.array_max(places(lambda x: x["d"] + F.length(F.bin(x["mask"]))))  # the last pair's second word
    out = band.withColumn("good", F.coalesce(good, F.lit(False)))
    blank = lambda c, name: F.when(F.col("good"), c).alias(name)
    return out.select(*key, blank(F.col("label"), "label"), blank(F.col("base"), "base"), blank(first, "first_word"), blank(last, "last_word"), blank(F.col("votes"), "votes"), blank(F.col("cover"), "cover"))


def scan(df: DataFrame, id_col: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """One row per text: words, base places with their first and last start, labels and a score,
    which is the largest share of a phrase's pairs that a span holds in order."""
    s = spans(df, id_col, text, **options)
    base = F.col("base")
    join = lambda c: F.array_join(F.array_sort(F.collect_set(c)), ",")
    return s.groupBy(id_col, "_row", "n_words").agg(
        F.count(F.when(base, 1)).alias("n_base"),
        F.min(F.when(base, F.col("first_word"))).cast("long").alias("first_word"),
        F.max(F.when(base, F.col("first_word"))).cast("long").alias("last_word"),
        join(F.when(base, F.col("label"))).alias("base_labels"), join("label").alias("labels"),
        F.coalesce(F.max("cover"), F.lit(0.0)).alias("score"),
    ).drop("_row")
