"""Licence scans by a positional index of rare words.

Every template is a short licence text with mandatory key phrases. Its words are posted with their
positions and weighted by their rarity among templates (IDF); words too common to tell licences
apart are left out. Of every template whose key phrases all stand in a file, each posted word is
looked up there; a posting votes with its weight for the place where the template would begin in the
file, and places where enough different words agree count. No template hides another. Everything is
DataFrame expressions; only words of the index leave a file's row.

Null and empty texts have no words and no label. Rows are scored one by one, so repeated rows give
repeated results. An empty table gives no row. Columns but doc_id and text are not read.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from strel.llm.words import SEPARATORS_ANY_CASE
from strel.runtime import materialize

# Base phrases and labels.
BASE = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}
# Label, text, key phrases.
TEMPLATES = [
    ("apache-2.0", "licensed under the apache license version 2 0", ["apache license"]),
    ("mit", "released under the mit license permission is hereby granted free of charge to any person obtaining a copy", ["mit license"]),
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software", ["permission is hereby granted", "obtaining a copy"]),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted", ["redistribution and use in source and binary forms"]),
    ("gpl", "licensed under the gnu general public license version 3", ["gnu general public license"]),
    ("gpl", "free software you can redistribute it and or modify it under the terms of the gnu general public license", ["general public license"]),
    ("lgpl", "licensed under the gnu lesser general public license version 3", ["lesser general public license"]),
    ("agpl", "licensed under the gnu affero general public license version 3", ["affero general public license"]),
    ("mpl-2.0", "this source code form is subject to the terms of the mozilla public license v 2 0", ["mozilla public license"]),
    ("cc-by", "licensed under a creative commons attribution 4 0 international license", ["creative commons attribution"]),
    ("cc-by-nc", "licensed under cc by nc 4 0", ["cc by nc"]),
    ("cc-by-sa", "licensed under cc by sa 4 0", ["cc by sa"]),
    ("cc-by-nd", "licensed under cc by nd 4 0", ["cc by nd"]),
    ("cc0", "dedicated to the public domain under cc0 1 0 universal", ["cc0"]),
    ("reserved", "copyright all rights reserved", ["all rights reserved"]),
    ("apache-2.0", "you may not use this file except in compliance with the license you may obtain a copy of the license at", ["compliance with the license"]),
    ("mit", "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software", ["permission notice shall be included"]),
    ("bsd", "neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products", ["endorse or promote products"]),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", ["permission to use copy modify"]),
    ("zlib", "provided as is without any express or implied warranty in no event will the authors be held liable for any damages", ["authors be held liable for any damages"]),
    ("unlicense", "this is free and unencumbered software released into the public domain", ["unencumbered software"]),
    ("bsl-1.0", "distributed under the boost software license version 1 0", ["boost software license"]),
    ("epl-2.0", "made available under the terms of the eclipse public license v 2 0", ["eclipse public license"]),
    ("gpl", "this program is distributed in the hope that it will be useful but without any warranty without even the implied warranty", ["hope that it will be useful"]),
]
# Words too common to be posted.
_COMMON = set("the a an and or of to in is it this that with under any you can be are for at as on from by 0 1 2 3 4 v".split())
#: How many words must agree on a place (if a template has as many).
MIN_VOTES = 2


def _postings() -> list[tuple[str, int, int]]:
    return [(w, t, i) for t, (_, text, _) in enumerate(TEMPLATES) for i, w in enumerate(text.split()) if w not in _COMMON]


def _rarity() -> dict[str, float]:
    """IDF of the posted words over the templates."""
    kinds = [{w for w, u, _ in _postings() if u == t} for t in range(len(TEMPLATES))]
    return {w: round(math.log(1 + len(TEMPLATES) / sum(w in k for k in kinds)), 6) for w in set().union(*kinds)}


def _runs(low: Column, phrase: str) -> Column:
    """Positions at which the words of a phrase stand one after the other."""
    first, *rest = phrase.split()
    at = F.filter(F.transform(low, lambda w, i: F.when(w == first, i)), lambda i: i.isNotNull())
    for j, w in enumerate(rest, 1):
        at = F.filter(at, _stands(low, j, w))
    return at


def _stands(low: Column, ahead: int, word: str):
    return lambda i: F.get(low, i + ahead).eqNullSafe(F.lit(word))


def _labelled(label: str):
    return lambda i: F.struct(i.cast("long").alias("i"), F.lit(label).alias("label"))


def scan(docs: DataFrame) -> DataFrame:
    """Licences of every whole text of ``docs`` (doc_id, text).

    Columns: doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, and
    matches (label, first word of the place).
    """
    posted = _postings()
    vocab = sorted({w for w, _, _ in posted})
    phrases = sorted({p for _, _, ps in TEMPLATES for p in ps} | set(BASE))
    starts = sorted({p.split()[0] for p in phrases})
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = docs.select(F.monotonically_increasing_id().alias("row"), F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"))
    # a row without a first word of a phrase has nothing to find; words end where ``ws`` is split
    apart = SEPARATORS_ANY_CASE.removesuffix("+")
    hint = F.col("text").rlike(f"(?i)(?:^|{apart})(?:" + "|".join(starts) + f")(?:\\z|{apart})")
    ws = F.filter(F.split("text", SEPARATORS_ANY_CASE), lambda w: w != "")
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    rows = rows.withColumn("ws", ws).withColumn("n_words", F.size("ws").cast("long"))
    rows = rows.withColumn("low", F.when(hint, F.transform("ws", lambda w: F.translate(w, upper, lower))).otherwise(F.array().cast("array<string>")))
    seen = F.filter(F.transform("low", lambda w, i: F.struct(w.alias("w"), i.alias("i"))), lambda x: x["w"].isin(vocab))
    bits = F.lit(0).cast("long")
    for k, p in enumerate(phrases):
        bits = bits.bitwiseOR(F.when((F.size("low") > 0) & (F.size(_runs(F.col("low"), p)) > 0), F.lit(1 << k)).otherwise(F.lit(0)).cast("long"))
    base = F.flatten(F.array(*[F.transform(_runs(F.col("low"), p), _labelled(BASE[p])) for p in BASE]))
    none = F.array().cast("array<struct<i:bigint,label:string>>")
    flat = materialize(
        rows.select(
            "row", "doc_id", "n_words",
            F.when(F.size("low") > 0, base).otherwise(none).alias("base"),
            bits.alias("phrases"),
            F.when(F.size("low") > 0, seen).otherwise(F.array().cast("array<struct<w:string,i:int>>")).alias("seen"),
        ),
        "licence-words",
    )
    spark = docs.sparkSession
    idf = _rarity()
    index = spark.createDataFrame([(w, t, i, idf[w]) for w, t, i in posted], "w string, t int, p int, idf double")
    per = spark.createDataFrame([(t, lab, sum(1 << phrases.index(p) for p in ps), len(ws_ := {w for w, u, _ in posted if u == t}), sum(idf[w] for w in ws_)) for t, (lab, _, ps) in enumerate(TEMPLATES)], "t int, label string, need long, posted int, weight double")
    # only templates whose key phrases all stand in the file can count
    held = F.broadcast(index.join(F.broadcast(per), "t"))
    words = flat.where("phrases <> 0").select("row", "phrases", F.explode("seen").alias("x")).select("row", "phrases", "x.w", "x.i")
    hits = words.join(held, "w").where(F.col("phrases").bitwiseAND(F.col("need")) == F.col("need")).withColumn("at", F.col("i") - F.col("p"))
    each = hits.groupBy("row", "t", "at", "label", "posted", "weight", "w").agg(F.max("idf").alias("idf"))
    votes = each.groupBy("row", "t", "at", "label", "posted", "weight").agg(F.count(F.lit(1)).alias("votes"), F.sum("idf").alias("idf"))
    good = votes.where(F.col("votes") >= F.least(F.lit(MIN_VOTES), F.col("posted")))
    good = good.withColumn("share", F.least(F.lit(1.0), F.round(F.col("idf") / F.col("weight"), 6)))
    found = good.groupBy("row").agg(F.sort_array(F.collect_set(F.struct("label", F.col("at").cast("long").alias("at"), "share"))).alias("matches"))
    out = flat.select("row", "doc_id", "n_words", "base").join(found, "row", "left")
    own = F.array_sort(F.array_distinct(F.transform("base", lambda b: b["label"])))
    more = F.transform(F.coalesce("matches", F.array().cast("array<struct<label:string,at:bigint,share:double>>")), lambda m: m["label"])
    place = F.transform("base", lambda b: b["i"])
    best = F.coalesce(F.array_max(F.transform("matches", lambda m: m["share"])), F.lit(0.0))
    return out.select(
        "doc_id", "n_words",
        F.size("base").cast("long").alias("n_base"),
        F.array_min(place).alias("first_word"),
        F.array_max(place).alias("last_word"),
        F.array_join(own, ",").alias("base_labels"),
        F.array_join(F.array_sort(F.array_union(own, more)), ",").alias("labels"),
        F.when(F.size("base") > 0, F.lit(1.0)).otherwise(best).alias("score"),
        F.transform("matches", lambda m: F.concat_ws(":", m["label"], m["at"].cast("string"))).alias("matches"),
    )
