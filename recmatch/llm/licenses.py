"""Licence scan by a positional index of rare tokens.

Templates are short licence notices. Of each, the words with the highest IDF over all documents form the
index: word, template, position. A document looks up every index word it holds; postings whose
relative position agrees mark a place where the template may start; there the template is compared word by
word, and its key phrases must stand in that stretch. The score is the best share of words that agree.

A template has two index words more than words that may differ, so two agree wherever the score is reached:
the result is that of comparing every template at every place.

DataFrame functions only. Words are runs of characters other than ASCII signs and blanks, A-Z
lower-cased. Null, empty and wordless texts: no words, no places, empty label strings, score 0. Repeated
rows are rows of their own. Extra columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import documents, stored

#: Base phrases and their labels.
PHRASES = (("cc by", "cc-by"), ("general public license", "gpl"), ("all rights reserved", "reserved"))
#: Label, notice, key phrases that must stand in it.
TEMPLATES = (
    ("gpl-3.0", "licensed under the gnu general public license version 3", ("general public license", "version 3")),
    ("gpl-2.0", "licensed under the gnu general public license version 2", ("general public license", "version 2")),
    ("lgpl", "licensed under the gnu lesser general public license", ("lesser general public license",)),
    ("agpl-3.0", "licensed under the gnu affero general public license version 3", ("affero general public license",)),
    ("apache-2.0", "licensed under the apache license version 2 0", ("apache license", "version 2 0")),
    ("mit", "released under the mit license", ("mit license",)),
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", ("permission is hereby granted", "free of charge")),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", ("source and binary forms", "following conditions")),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", ("copy modify", "hereby granted")),
    ("mpl-2.0", "this source code form is subject to the terms of the mozilla public license v 2 0", ("mozilla public license",)),
    ("cc-by-4.0", "licensed under cc by 4 0", ("cc by 4 0",)),
    ("cc-by-nc-4.0", "licensed under cc by nc 4 0", ("cc by nc 4 0",)),
    ("cc-by-sa-4.0", "licensed under cc by sa 4 0", ("cc by sa 4 0",)),
    ("cc-by-4.0", "licensed under a creative commons attribution 4 0 international license", ("creative commons attribution 4 0",)),
    ("cc0-1.0", "dedicated to the public domain under cc0 1 0", ("cc0 1 0",)),
)
SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
RARE_OF_TEMPLATE, LEAST_SCORE = 4, 0.8


def tokens(text: Column) -> Column:
    """Lower-cased words. Only one non-ASCII letter lower-cases into ASCII, the Kelvin sign; it must stay itself."""
    plain = F.lower(F.replace(F.coalesce(text, F.lit("")), F.lit("K"), F.lit("¢")))
    return F.array_remove(F.split(plain, SEPARATORS), "")


def vocabulary() -> list[str]:
    return sorted({w for _, t, _ in TEMPLATES for w in t.split()} | {w for p, _ in PHRASES for w in p.split()})


def anchors() -> list[str]:
    """Words of which every base phrase has one, and every template one in a key phrase; a file without any of them has no licence."""
    return ["license", "cc", "cc0", "reserved", "hereby", "binary", "commons"]


def index_words(n: int) -> int:
    """Index words of a template of n words: two more than may differ, RARE_OF_TEMPLATE at least."""
    return max(RARE_OF_TEMPLATE, n - math.ceil(LEAST_SCORE * n) + 2)


def places(words: Column, phrase: str) -> Column:
    """Where the words of a phrase stand consecutively; only for files with its first word."""
    want = phrase.split()
    n = len(want)
    last = F.size(words) - n
    at = F.filter(
        F.sequence(F.lit(0), F.greatest(last, F.lit(0))),
        lambda i: F.slice(words, i + 1, n) == F.array(*map(F.lit, want)),
    )
    found = F.array_contains(words, want[0]) & F.array_contains(words, want[-1]) & (last >= 0)
    return F.when(found, at).otherwise(F.array().cast("array<int>"))


def index(spark: SparkSession, idf: DataFrame) -> DataFrame:
    """Positional postings of each template's rarest words: word, template, position. As small as the templates."""
    rows = [(n, index_words(len(t.split())), i, w) for n, (_, t, _) in enumerate(TEMPLATES) for i, w in enumerate(t.split())]
    post = spark.createDataFrame(rows, "template int, size int, position int, word string").join(F.broadcast(idf), "word", "left").fillna({"idf": 99.0})
    ranked = post.groupBy("template", "size").agg(F.sort_array(F.collect_list(F.struct((-F.col("idf")).alias("r"), "word", "position"))).alias("p"))
    return ranked.select("template", F.explode(F.slice("p", F.lit(1), F.col("size"))).alias("p")).select("template", "p.word", "p.position")


def scan(docs: DataFrame) -> DataFrame:
    """n_words, base places and labels, the method's labels and score of each row of docs (doc_id, text)."""
    spark = docs.sparkSession
    words = docs.select(F.col("doc_id").cast("long").alias("doc_id"), tokens(F.col("text").cast("string")).alias("w"))
    known = F.arrays_overlap("w", F.array(*map(F.lit, anchors())))
    vocab = F.array(*map(F.lit, vocabulary()))
    files = words.select(F.monotonically_increasing_id().alias("row_no"), "doc_id", F.size("w").cast("long").alias("n_words"), F.when(known, F.col("w")).alias("w"), F.array_intersect("w", vocab).alias("of_vocab"))
    files = stored(files, "files")
    held = files.filter("w is not null")

    # IDF over all documents of the licence vocabulary, whether or not they have an anchor.
    rows = files.count()
    df = files.select(F.explode("of_vocab").alias("word")).groupBy("word").count()
    idf = stored(df.select("word", F.log(F.lit(float(rows or 1)) / F.col("count")).alias("idf")), "idf")
    post = stored(index(spark, idf), "postings")

    own = held.select("row_no", F.posexplode("w").alias("i", "word"))
    hits = own.join(F.broadcast(post), "word").select("row_no", "template", (F.col("i") - F.col("position")).alias("start"), "position")
    starts = hits.groupBy("row_no", "template", "start").agg(F.count_distinct("position").alias("agree"))

    table = spark.createDataFrame([(n, label, t.split(), [f" {p} " for p in phrases]) for n, (label, t, phrases) in enumerate(TEMPLATES)], "template int, label string, t array<string>, phrases array<string>")
    at = starts.filter("agree >= 2").join(F.broadcast(table), "template").join(held.select("row_no", "w"), "row_no")
    stretch = F.slice("w", F.greatest(F.col("start"), F.lit(0)) + 1, F.size("t"))
    at = at.withColumn("stretch", F.when(F.col("start") >= 0, stretch).otherwise(F.slice("w", 1, F.size("t"))))
    same = F.aggregate(F.zip_with("stretch", "t", lambda a, b: F.when(a.eqNullSafe(b), 1).otherwise(0)), F.lit(0), lambda a, b: a + b)
    text = F.concat(F.lit(" "), F.concat_ws(" ", "stretch"), F.lit(" "))
    at = at.withColumn("score", same / F.size("t")).filter(F.col("score") >= LEAST_SCORE).filter(F.forall("phrases", lambda p: F.contains(text, p)))
    labels = at.groupBy("row_no").agg(F.collect_set("label").alias("found"), F.max("score").alias("score"))

    spots = {label: places(F.col("w"), phrase) for phrase, label in PHRASES}
    base = held.select("row_no", *(p.alias(f"p{i}") for i, p in enumerate(spots.values())))
    all_places = F.concat(*(F.col(f"p{i}") for i in range(len(spots))))
    base = base.select(
        "row_no",
        F.size(all_places).cast("long").alias("n_base"),
        F.array_min(all_places).cast("long").alias("first_word"),
        F.array_max(all_places).cast("long").alias("last_word"),
        F.array_compact(F.array(*(F.when(F.size(f"p{i}") > 0, F.lit(label)) for i, label in enumerate(spots)))).alias("base"),
    )
    none = F.array().cast("array<string>")
    out = files.select("row_no", "doc_id", "n_words").join(base, "row_no", "left").join(labels, "row_no", "left")
    union = F.array_union(F.coalesce("base", none), F.coalesce("found", none))
    return out.select(
        "doc_id", "n_words", F.coalesce("n_base", F.lit(0)).alias("n_base"), "first_word", "last_word",
        F.concat_ws(",", F.sort_array(F.coalesce("base", none))).alias("base_labels"),
        F.concat_ws(",", F.sort_array(union)).alias("labels"), F.coalesce("score", F.lit(0.0)).alias("score"),
    )


def op8_rare_token_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(documents(spark, sf_dir))
