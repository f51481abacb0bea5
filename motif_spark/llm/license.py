"""Licence scan by a positional index of rare words, in DataFrame functions only.

The index is built once on the driver from the fixed notices below: for each notice its words of highest
IDF with their places. A text's rare words are looked up, each posting votes for the shift between text and
notice, and a notice whose rare words agree on one shift and whose key phrases stand in the text is named.

Defined cases: a null or empty text has no words, no labels and score 0; rows are judged alone, so repeated
rows get equal answers; ties between shifts do not matter, as only the best vote counts; a very long text is
scanned whole, and only its indexed words are held as hits; extra columns are left out, so their names do not matter.
"""

from __future__ import annotations

import math
import re
from collections import Counter

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower

# Phrases that name a licence, and notices as (label, words, phrase that must stand in the text).
BASE = (("mit", "mit license"), ("apache", "apache license"), ("gpl", "general public license"))
NOTICES = (
    ("all-rights-reserved", "all rights reserved", "all rights reserved"),
    ("apache", "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license you may obtain a copy of the license at", "apache license"),
    ("apache", "licensed under the apache license", "apache license"),
    ("agpl", "you can redistribute it and or modify it under the terms of the gnu affero general public license as published by the free software foundation", "affero general public license"),
    ("boost", "permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying documentation covered by this license", "boost software license"),
    ("boost", "distributed under the boost software license", "boost software license"),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", "source and binary forms"),
    ("cc0", "to the extent possible under law the author has dedicated all copyright and related and neighboring rights to this software to the public domain worldwide", "dedicated all copyright"),
    ("cc-by", "licensed under a creative commons attribution 4 0 international license", "creative commons attribution"),
    ("cc-by-nc", "licensed under cc by nc 4 0", "cc by nc"),
    ("cc-by-sa", "licensed under cc by sa 4 0", "cc by sa"),
    ("epl", "this program and the accompanying materials are made available under the terms of the eclipse public license", "eclipse public license"),
    ("gpl", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation", "general public license"),
    ("gpl", "licensed under the gnu general public license version 3", "general public license"),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", "with or without fee is hereby granted"),
    ("lgpl", "licensed under the gnu lesser general public license", "lesser general public license"),
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files to deal in the software without restriction", "hereby granted free of charge"),
    ("mit", "released under the mit license", "mit license"),
    ("mpl", "this source code form is subject to the terms of the mozilla public license", "mozilla public license"),
    ("ofl", "this font software is licensed under the sil open font license", "open font license"),
    ("unlicense", "this is free and unencumbered software released into the public domain", "unencumbered software"),
    ("zlib", "this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages arising from the use of this software", "arising from the use of this software"),
)
COMMON = "a all and any as at be by for from in into is it of or that the this to under will with without you".split()
#: Words of a notice that are indexed, those of highest IDF over the notices; numbers are not, as versions differ.
RARE_WORDS = 6
#: Share of a notice's indexed words that must agree on one shift.
AGREE = 0.75
NO_WORD = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
_STEP = 1 << 33


def rare_index(notices=NOTICES, most: int = RARE_WORDS) -> list[tuple[str, int, int]]:
    """(word, notice, place): the words of highest IDF over the notices, the longer of equals, each once, in their places."""
    df = Counter(w for _, text, _ in notices for w in set(text.split()))
    found = []
    for t, (_, text, _) in enumerate(notices):
        words = text.split()
        best = sorted((k for k in range(len(words)) if words[k] not in COMMON and not words[k].isdigit() and words.index(words[k]) == k), key=lambda k: (-math.log(len(notices) / df[words[k]]), -len(words[k]), k))[:most]
        found += [(words[k], t, k) for k in sorted(best)]
    return found


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", notices=NOTICES) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score for every row."""
    index = rare_index(notices)
    lit = lambda xs: F.array(*[F.lit(x) for x in xs])
    rare = sorted({w for w, _, _ in index} | {p.split()[-1] for _, p in BASE})
    postings = F.array(*[F.struct(F.lit(w).alias("w"), F.lit(t * _STEP - k).alias("at")) for w, t, k in index])
    df = docs.select(F.col(id_col).alias("doc_id"), F.array_remove(F.split(ascii_lower(F.col(text_col)), NO_WORD), "").alias("_w"))
    df = df.withColumns({"n_words": F.size("_w").cast("long"), "_any": F.arrays_overlap("_w", lit(rare))})
    placed = F.transform("_w", lambda w, i: F.struct(w.alias("w"), i.cast("long").alias("i")))
    no_hit = F.array().cast("array<struct<w:string,i:bigint>>")
    df = df.withColumn("_hits", F.when(F.col("_any"), F.filter(placed, lambda h: h["w"].isin(rare))).otherwise(no_hit))
    before = lambda h, k, w: F.coalesce(F.get("_w", (h["i"] - k).cast("int")) == w, F.lit(False))

    def base(h: Column) -> Column:
        out = F.lit(None).cast("struct<i:bigint,label:string>")
        for label, phrase in BASE:
            *head, last = phrase.split()
            ok = h["w"] == last
            for k, w in enumerate(reversed(head), 1):
                ok = ok & before(h, k, w)
            out = F.when(ok, F.struct((h["i"] - len(head)).alias("i"), F.lit(label).alias("label"))).otherwise(out)
        return out

    df = df.withColumn("_base", F.filter(F.transform("_hits", base), lambda b: b.isNotNull()))
    # Each vote is notice * STEP + shift + STEP / 2; equal votes stand together once sorted.
    votes = F.flatten(F.transform("_hits", lambda h: F.transform(F.filter(postings, lambda p: p["w"] == h["w"]), lambda p: h["i"] + p["at"] + _STEP // 2)))
    df = df.withColumn("_votes", F.sort_array(votes))
    starts = F.filter(F.transform("_votes", lambda v, j: F.when((j == 0) | (v != F.get("_votes", j - 1)), j)), lambda j: j.isNotNull())
    df = df.withColumn("_starts", starts)
    runs = F.transform("_starts", lambda s, j: F.struct(F.floor(F.get("_votes", s) / _STEP).alias("t"), (F.coalesce(F.get("_starts", j + 1), F.size("_votes")) - s).alias("n")))
    df = df.withColumns({"_runs": runs, "_joined": F.when(F.size("_hits") > 0, F.concat(F.lit(" "), F.array_join("_w", " "), F.lit(" "))).otherwise("")})
    # One expression for all notices, however many there are.
    total = Counter(t for _, t, _ in index)
    known = F.array(*[F.struct(F.lit(t).alias("t"), F.lit(label).alias("label"), F.lit(total[t]).alias("total"), F.lit(f" {phrase} ").alias("phrase")) for t, (label, _, phrase) in enumerate(notices)])
    votes_of = lambda z: F.coalesce(F.array_max(F.transform(F.filter("_runs", lambda r: r["t"] == z["t"]), lambda r: r["n"])), F.lit(0))
    judged = F.transform(known, lambda z: F.struct(z.alias("z"), votes_of(z).alias("n")))
    stands = lambda j: (j["n"] >= AGREE * j["z"]["total"]) & F.col("_joined").contains(j["z"]["phrase"])
    named = F.transform(judged, lambda j: F.struct(j["z"]["label"].alias("label"), stands(j).alias("ok"), (j["n"] / j["z"]["total"]).alias("score")))
    some = F.size("_hits") > 0
    none = F.array().cast("array<struct<label:string,ok:boolean,score:double>>")
    df = df.withColumn("_named", F.when(some, named).otherwise(none))
    base_labels = F.array_distinct(F.transform("_base", lambda b: b["label"]))
    own = F.transform(F.filter("_named", lambda x: x["ok"]), lambda x: x["label"])
    places = F.transform("_base", lambda b: b["i"])
    return df.select(
        "doc_id",
        "n_words",
        F.size("_base").cast("long").alias("n_base"),
        F.array_min(places).alias("first_word"),
        F.array_max(places).alias("last_word"),
        F.array_join(F.sort_array(base_labels), ",").alias("base_labels"),
        F.array_join(F.sort_array(F.array_union(base_labels, own)), ",").alias("labels"),
        F.least(F.lit(1.0), F.coalesce(F.array_max(F.transform("_named", lambda x: x["score"])), F.lit(0.0))).alias("score"),
    )


def words_of(text: str) -> list[str]:
    """The words of scan(), for tests."""
    return [w for w in re.split(NO_WORD, re.sub("[A-Z]+", lambda m: m[0].lower(), text or "")) if w]
