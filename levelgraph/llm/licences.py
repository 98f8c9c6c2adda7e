"""Licence scan with a positional rare-token index, in DataFrame functions only.

The words of known notices form an index: word -> (template, position).  Each file looks up every
notice word it holds, weighed by inverse document frequency (counted over all files), shifts
every posting to the offset at which that template would start, and lets the shifts vote.  A
template is a candidate when words of most of its weight agree on one offset, whether or not the
file holds the others; it is labelled when its mandatory key phrase, with the version where the
label has one, also occurs in the file.  Bare names of a licence are templates of their own.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from levelgraph.runtime import materialize

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
BREAK = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"

# Base phrases with their labels.
BASE = (("cc by", "cc-by"), ("general public license", "gpl"), ("all rights reserved", "reserved"))

# Label, words of a common notice, mandatory key phrase.
TEMPLATES = (
    ("apache-2.0", "licensed under the apache license version 2 0", "apache license version 2"),
    ("mit", "released under the mit license", "mit license"),
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", "permission is hereby granted free of charge"),
    ("gpl-3.0", "this work is licensed under the gnu general public license version 3", "gnu general public license version 3"),
    ("gpl-3.0", "under the terms of the gnu general public license as published by the free software foundation either version 3 of the license", "published by the free software foundation either version 3"),
    ("gpl-3.0", "under the terms of the gnu general public license as published by the free software foundation version 3 of the license", "published by the free software foundation version 3"),
    ("gpl", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license", "gnu general public license"),
    ("lgpl", "licensed under the gnu lesser general public license", "lesser general public license"),
    ("cc-by-nc", "licensed under cc by nc 4 0", "cc by nc"),
    ("cc-by-sa", "licensed under cc by sa 4 0", "cc by sa"),
    ("cc-by", "this work is licensed under a creative commons attribution 4 0 international license", "creative commons attribution 4 0"),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted", "redistribution and use in source and binary forms"),
    ("mpl-2.0", "this source code form is subject to the terms of the mozilla public license v 2 0", "mozilla public license v 2"),
    ("bsd", "redistribution and use in source and binary forms are permitted", "redistribution and use in source and binary forms"),
    ("proprietary", "copyright c all rights reserved", "all rights reserved"),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", "distribute this software for any purpose with or without fee"),
    ("unlicense", "this is free and unencumbered software released into the public domain", "unencumbered software released into the public domain"),
    ("zlib", "this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages", "will the authors be held liable for any damages"),
    ("bsl-1.0", "distributed under the boost software license version 1 0", "boost software license version 1"),
    ("agpl-3.0", "under the gnu affero general public license version 3", "affero general public license version 3"),
    ("agpl-3.0", "under the terms of the gnu affero general public license as published by the free software foundation either version 3 of the license", "gnu affero general public license as published by the free software foundation either version 3"),
    ("epl-2.0", "eclipse public license v 2 0", "eclipse public license v 2"),
    # bare names: the whole name is both template and key phrase
    *((label, name, name) for label, names in (
        ("apache-2.0", ("apache license version 2", "apache license 2", "apache license v2", "apache license v 2")),
        ("mit", ("mit license",)),
        ("gpl-3.0", ("gnu general public license version 3", "gnu general public license v3", "gnu general public license v 3", "gnu general public license 3")),
        ("lgpl", ("lesser general public license",)),
        ("cc-by-nc", ("cc by nc",)),
        ("cc-by-sa", ("cc by sa",)),
        ("cc-by", ("creative commons attribution license", *(f"creative commons attribution {v}" for v in ("1 0", "2 0", "2 5", "3 0", "4 0")))),
        ("epl-2.0", ("eclipse public license 2", "eclipse public license v2", "eclipse public license version 2")),
        ("mpl-2.0", ("mozilla public license version 2", "mozilla public license 2", "mozilla public license v2", "mozilla public license v 2")),
        ("proprietary", ("all rights reserved",)),
    ) for name in names),
)
# Words too common in any text to be posted.
COMMON = ("a", "and", "any", "are", "by", "can", "free", "in", "is", "it", "of", "or", "as", "be", "for", "from", "no", "into", "will", "the", "this", "to", "under", "use", "with", "you", "work", "c", "v", "0")
MIN_SHARE = 0.75


def _words(text: str) -> list[str]:
    return text.split(" ")


VOCABULARY = tuple(sorted({w for _, t, _ in TEMPLATES for w in _words(t)} - set(COMMON)))
PHRASES = tuple(sorted({p for _, _, p in TEMPLATES}))


def lowered(text: Column) -> Column:
    return F.translate(F.coalesce(text.cast("string"), F.lit("")), UPPER, LOWER)


def _places(words: Column, joined: Column, phrase: str) -> Column:
    """Word positions at which a phrase starts; looked for only where the joined words hold it."""
    p = _words(phrase)

    def here(i: Column) -> Column:
        ok = F.lit(True)
        for k, w in enumerate(p):
            ok = ok & (F.get(words, i + k) == w)
        return F.coalesce(ok, F.lit(False))

    none = F.array().cast("array<int>")
    return F.when(joined.contains(f" {phrase} "), F.filter(F.sequence(F.lit(0), F.size(words) - 1), here)).otherwise(none)


def _read(docs: DataFrame, text: str) -> DataFrame:
    """One pass over the texts: base places, notice words with positions, key phrases."""
    joined = F.trim(F.regexp_replace(lowered(F.col(text)), BREAK, " "))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), joined.alias("j"))
    rows = rows.select("doc_id", F.concat(F.lit(" "), "j", F.lit(" ")).alias("joined"), F.when(F.col("j") != "", F.split("j", " ")).otherwise(F.array().cast("array<string>")).alias("words"))
    rows = rows.withColumn("present", F.array_intersect("words", F.array(*map(F.lit, VOCABULARY))))
    at = F.filter(F.transform("words", lambda w, i: F.struct(w.alias("w"), i.alias("i"))), lambda x: F.array_contains(F.col("present"), x["w"]))
    none = F.array().cast("array<struct<w:string,i:int>>")
    return rows.select(
        F.monotonically_increasing_id().alias("row"), "doc_id", F.size("words").cast("long").alias("n_words"),
        *(_places(F.col("words"), F.col("joined"), p).alias(f"base{k}") for k, (p, _) in enumerate(BASE)),
        "present",
        F.when(F.size("present") > 0, at).otherwise(none).alias("hits"),
        F.array(*(F.col("joined").contains(f" {p} ") for p in PHRASES)).alias("phrases"),
    )


def scan_licences(docs: DataFrame, text: str = "text", min_share: float = MIN_SHARE) -> DataFrame:
    """Licence labels of each row of ``docs``.

    Returns ``doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score``.
    Null and empty texts have no words, no labels and score 0.  Repeated rows are scanned each.
    The score is the share of a template's whole weight that agrees on its offset, 1 for base
    phrases.
    """
    read = materialize(_read(docs, text), "licence_words")
    n = read.count()
    found = {r["w"]: r["n"] for r in read.select(F.explode("present").alias("w")).groupBy("w").agg(F.count("*").alias("n")).collect()}  # at most len(VOCABULARY) rows
    idf = {w: math.log((n + 1) / (found.get(w, 0) + 0.5)) for w in VOCABULARY}
    weight = F.create_map(*[F.lit(x) for w in VOCABULARY for x in (w, idf[w])])
    posted = [(w, t, p) for t, (_, body, _) in enumerate(TEMPLATES) for p, w in enumerate(_words(body)) if w in idf]
    lists = {w: [(t, p) for v, t, p in posted if v == w] for w in VOCABULARY}
    index = F.create_map(*[x for w in VOCABULARY for x in (F.lit(w), F.array(*(F.struct(F.lit(t).alias("t"), F.lit(p).alias("p")) for t, p in lists[w])))])

    hot = read.where(F.size("present") > 0)
    votes = hot.select("row", "phrases", F.explode("hits").alias("h"))
    votes = votes.select("row", "phrases", F.col("h.w").alias("w"), F.col("h.i").alias("i"), F.explode(index[F.col("h.w")]).alias("post"))
    votes = votes.select("row", "phrases", "w", F.col("post.t").alias("t"), (F.col("i") - F.col("post.p")).alias("offset"))
    agree = votes.groupBy("row", "t", "offset").agg(F.collect_set("w").alias("agreed"), F.first("phrases").alias("phrases"))
    total = lambda words: F.aggregate(words, F.lit(0.0), lambda a, w: a + weight[w])
    # all posted words of the template, those that the file lacks too
    due = F.get(F.array(*(F.lit(math.fsum(idf[w] for w in set(_words(b)) if w in idf)) for _, b, _ in TEMPLATES)), F.col("t"))
    phrase_at = F.array(*(F.lit(PHRASES.index(p)) for _, _, p in TEMPLATES))
    agree = agree.withColumns({"share": total("agreed") / due, "sure": F.get(F.col("phrases"), F.get(phrase_at, F.col("t")))})
    names = F.array(*(F.lit(label) for label, _, _ in TEMPLATES))
    more = agree.where((F.col("share") >= min_share) & F.col("sure")).groupBy("row").agg(
        F.collect_set(F.get(names, F.col("t"))).alias("more"), F.max("share").alias("share")
    )
    places = F.concat(*(F.col(f"base{k}") for k in range(len(BASE))))
    base = F.array_compact(F.array(*(F.when(F.size(f"base{k}") > 0, F.lit(label)) for k, (_, label) in enumerate(BASE))))
    out = read.join(more, "row", "left").withColumns({"places": places, "base": F.array_sort(base)})
    return out.select(
        "doc_id", "n_words", F.size("places").cast("long").alias("n_base"),
        F.array_min("places").cast("long").alias("first_word"), F.array_max("places").cast("long").alias("last_word"),
        F.array_join("base", ",").alias("base_labels"),
        F.array_join(F.array_sort(F.array_union("base", F.coalesce("more", F.array().cast("array<string>")))), ",").alias("labels"),
        F.least(F.greatest(F.coalesce("share", F.lit(0.0)), F.when(F.size("places") > 0, 1.0).otherwise(0.0)), F.lit(1.0)).alias("score"),
    )


def op8_licences(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licences(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
