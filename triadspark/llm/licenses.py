"""Licence detection by a positional index of rare licence words; built-in functions only.

Templates are short public notices.  Their words but the most ordinary make the lexicon; document frequencies over all documents give each an
inverse frequency.  Every template is looked up by the rarest word of its mandatory phrases (by all its words where these have none in
the lexicon): a match has that word in its place, so each of the word's places in a file, less its place in the template, is an
alignment and no match is missed.  A template labels the file where enough of its words, weighted by rarity, stand at their aligned
places and every mandatory phrase does so in full.

Fixed base phrases give labels of their own wherever their words stand consecutively.

Edge cases: null or empty text has no words, no labels, score 0 and null first and last word.  Overlapping and repeated phrases all count.  Repeated rows
give a row each.  Empty tables give no rows.  Other columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import slim, stored, table

UPPER, LOWERED = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"

#: fixed values: base phrases and their labels
BASE = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}

#: fixed values: label, notice, mandatory phrases
TEMPLATES = [
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", ["permission is hereby granted free of charge"]),
    ("mit", "released under the mit license", ["mit license"]),
    ("apache-2.0", "licensed under the apache license version 2 0", ["apache license version 2"]),
    ("gpl", "this work is licensed under the gnu general public license version 3", ["gnu general public license"]),
    ("lgpl", "licensed under the gnu lesser general public license", ["gnu lesser general public license"]),
    ("agpl", "licensed under the gnu affero general public license", ["gnu affero general public license"]),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted", ["redistribution and use in source and binary forms"]),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", ["permission to use copy modify"]),
    ("mpl-2.0", "this source code form is subject to the terms of the mozilla public license v 2 0", ["mozilla public license"]),
    ("unlicense", "this is free and unencumbered software released into the public domain", ["free and unencumbered software"]),
    ("cc-by-nc", "licensed under cc by nc 4 0", ["cc by nc"]),
    ("cc-by-sa", "licensed under cc by sa 4 0", ["cc by sa"]),
    ("cc0", "to the extent possible under law the author has waived all copyright cc0 1 0 universal", ["cc0 1 0 universal"]),
]
#: fixed values: words too ordinary for the lexicon
ORDINARY = {"the", "a", "of", "to", "is", "in", "and", "or", "for", "with", "this", "any", "by", "are", "all", "under", "has", "use", "from", "0", "1", "2", "3", "4", "v"}


def lexicon(templates=TEMPLATES) -> list[str]:
    return sorted({w for _, notice, _ in templates for w in notice.split()} - ORDINARY | {p.split()[0] for p in BASE} - ORDINARY | {"reserved"})


def _words(text: Column) -> Column:
    return F.array_remove(F.split(F.translate(F.coalesce(text, F.lit("")), UPPER, LOWERED), SEPARATORS), "")


def _phrase_places(words: Column, phrase: str) -> Column:
    p = phrase.split()
    hit = lambda i: [F.get(words, i + j) == w for j, w in enumerate(p)]
    def whole(i):
        out = hit(i)[0]
        for x in hit(i)[1:]:
            out = out & x
        return out
    spots = F.filter(F.sequence(F.lit(0), F.greatest(F.size(words) - len(p), F.lit(0))), lambda i: F.coalesce(whole(i), F.lit(False)))
    return spots


def scan_licenses(docs: DataFrame, templates=TEMPLATES, least: float = 0.6) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score of every row of docs."""
    spark = docs.sparkSession
    lex = lexicon(templates)
    lit = lambda ws: F.array(*(F.lit(w) for w in ws))
    split = slim(docs).select(F.monotonically_increasing_id().alias("row"), "doc_id", _words(F.col("text")).alias("words"))
    known = split.withColumn("lex", F.array_intersect("words", lit(lex)))
    none = F.array().cast("array<int>")
    for k, phrase in enumerate(BASE):
        rare = phrase.split()[-1] if phrase.split()[0] in ORDINARY else phrase.split()[0]
        known = known.withColumn(f"base{k}", F.when(F.array_contains("lex", rare), _phrase_places(F.col("words"), phrase)).otherwise(none))
    files = stored(known.select("row", "doc_id", F.size("words").cast("long").alias("n_words"), "lex", *(f"base{k}" for k in range(len(BASE))), F.when(F.size("lex") > 0, F.col("words")).alias("words")), "licence-files")

    # at most one row a lexicon word comes back
    n = max(files.count(), 1)
    df = {r["w"]: r["n"] for r in files.select(F.explode("lex").alias("w")).groupBy("w").agg(F.count("*").alias("n")).collect()}
    idf = {w: math.log((n + 1) / (df.get(w, 0) + 1)) + 1e-6 for w in lex}

    postings, notices = [], []
    for t, (label, notice, keys) in enumerate(templates):
        ws = notice.split()
        weights = [float(idf.get(w, 0.0)) for w in ws]
        places = []
        for key in keys:
            k = key.split()
            places.append(next(i for i in range(len(ws)) if ws[i : i + len(k)] == k))
        must = sorted({i + j for i, key in zip(places, keys, strict=True) for j in range(len(key.split()))})
        notices.append((t, label, ws, weights, must, sum(weights)))
        anchors = [i for i in must if ws[i] in idf]
        # rarity picks the word that gives the fewest alignments
        anchors = [max(anchors, key=lambda i: idf[ws[i]])] if anchors else [i for i, w in enumerate(ws) if w in idf]  # noqa: B023
        postings += [(ws[i], t, i) for i in anchors]
    post = F.broadcast(spark.createDataFrame(postings, "w string, t int, at int"))  # size fixed by the templates
    note = F.broadcast(spark.createDataFrame(notices, "t int, label string, ws array<string>, weights array<double>, must array<int>, total double"))

    looked = sorted({w for w, _, _ in postings})
    some = files.where(F.arrays_overlap("lex", lit(looked)))
    spots = some.select("row", F.explode(F.filter(F.transform("words", lambda w, i: F.struct(i.alias("p"), w.alias("w"))), lambda x: x["w"].isin(looked))).alias("x")).select("row", "x.p", "x.w")
    aligned = spots.join(post, "w").select("row", "t", (F.col("p") - F.col("at")).alias("shift")).distinct()
    # a file's row holds its alignments as numbers, template by template
    per_file = (aligned.groupBy("row", "t").agg(F.collect_list("shift").alias("shifts")).join(note, "t")
                .groupBy("row").agg(F.collect_list(F.struct("label", "ws", "weights", "must", "total", "shifts")).alias("cand")))
    place = lambda at, j: F.when(at + j >= 0, F.get(F.col("words"), at + j))
    right = lambda c, at, j: F.coalesce(place(at, j) == F.get(c["ws"], j), F.lit(False))
    whole = lambda c: F.filter(c["shifts"], lambda at: F.forall(c["must"], lambda j: right(c, at, j)))
    share = lambda c, at: F.aggregate(F.sequence(F.lit(0), F.size(c["ws"]) - 1), F.lit(0.0), lambda acc, j: acc + F.when(right(c, at, j), F.get(c["weights"], j)).otherwise(0.0)) / c["total"]
    judged = some.join(per_file, "row").select("row", F.transform("cand", lambda c: F.struct(c["label"].alias("label"), F.array_max(F.transform(whole(c), lambda at: share(c, at))).alias("share"))).alias("cand"))
    good = judged.select("row", F.filter("cand", lambda c: c["share"] >= least).alias("cand")).where("size(cand) > 0").select("row", F.transform("cand", lambda c: c["label"]).alias("own"), F.array_max(F.transform("cand", lambda c: c["share"])).alias("best"))

    bases = [F.col(f"base{k}") for k in range(len(BASE))]
    places = F.concat(*bases)
    found = F.array_compact(F.array(*(F.when(F.size(b) > 0, F.lit(label)) for b, label in zip(bases, BASE.values(), strict=True))))
    return files.join(good, "row", "left").select(
        "doc_id", "n_words", F.size(places).cast("long").alias("n_base"), F.array_min(places).cast("long").alias("first_word"), F.array_max(places).cast("long").alias("last_word"),
        F.array_join(F.array_sort(F.array_distinct(found)), ",").alias("base_labels"),
        F.array_join(F.array_sort(F.array_distinct(F.concat(found, F.coalesce("own", F.array().cast("array<string>"))))), ",").alias("labels"),
        F.round(F.least(F.lit(1.0), F.greatest(F.coalesce("best", F.lit(0.0)), F.when(F.size(places) > 0, 0.5).otherwise(0.0))), 6).alias("score"))


def op7_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licenses(table(spark, sf_dir, "documents"))


QUERIES = {"op7_license_scan": op7_license_scan}
