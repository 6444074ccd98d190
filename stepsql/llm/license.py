"""License scans by diagonal voting, with DataFrame operations only.

Templates are short phrases and longer notices. Every rolling 2-gram of a text's words (the shortest
template has two) is joined by hash to the positions of that 2-gram in
the templates; equal hashes are checked by the words themselves. A hit votes for the diagonal
`word position - template position`. Every diagonal is merged with its neighbours up to `slack` further on (words put
in or left out), which gives a span no longer than the template and the slack. A span is verified: each template position
counts once, on the span's heaviest diagonal that has it, and only in the template's order; enough of them have to be
there, and each of the words that set the template apart from others. Then templates compete: a place of the text
counts for the label of the best-covered span there alone, and spans that keep enough places stand.
For a base phrase all of its 2-grams must vote on one diagonal, which is the case exactly where its words stand consecutively.

The joined side is the template table, whose size is fixed by the templates given. All rows of a
text stay together by a row number, so one shuffle serves every aggregation; a text's hits are
bounded by its own length, and texts without hits travel as one sentinel row.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import pick

# Phrases whose places count as base, and their labels.
BASE = (
    ("cc by", "cc-by"),
    ("general public license", "gpl"),
    ("all rights reserved", "reserved"),
)

# Words of public licence notices, a label for each, and the words that none of its copies lacks.
NOTICES = (
    ("permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", "mit", ""),
    ("the software is provided as is without warranty of any kind express or implied", "mit", ""),
    ("released under the mit license", "mit", "mit"),
    ("licensed under the mit license", "mit", "mit"),
    ("licensed under the apache license version 2 0", "apache-2.0", "apache"),
    ("you may not use this file except in compliance with the license you may obtain a copy of the license at", "apache-2.0", ""),
    ("redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", "bsd", ""),
    ("this program is free software you can redistribute it and or modify it under the terms of the gnu general public license", "gpl", "gnu general"),
    ("this work is licensed under the gnu general public license version 3", "gpl", "gnu general"),
    ("under the terms of the gnu lesser general public license", "lgpl", "lesser"),
    ("licensed under the gnu affero general public license", "agpl", "affero"),
    ("this source code form is subject to the terms of the mozilla public license v 2 0", "mpl-2.0", "mozilla"),
    ("permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", "isc", ""),
    ("this is free and unencumbered software released into the public domain", "unlicense", "unencumbered"),
    ("licensed under cc by nc 4 0", "cc-by-nc", "nc"),
    ("licensed under cc by sa 4 0", "cc-by-sa", "sa"),
    ("this work is licensed under a creative commons attribution 4 0 international license", "cc-by", "commons attribution"),
    ("this work is licensed under a creative commons attribution sharealike 4 0 international license", "cc-by-sa", "sharealike"),
    ("this work is licensed under a creative commons attribution noncommercial 4 0 international license", "cc-by-nc", "noncommercial"),
    ("this work has been dedicated to the public domain", "cc0", "dedicated"),
)

#: Words are runs of ASCII letters and digits and of anything beyond ASCII.
WORD = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"


@dataclass(frozen=True)
class Config:
    base: tuple[tuple[str, str], ...] = BASE
    notices: tuple[tuple[str, str, str], ...] = NOTICES
    slack: int = 6  # a diagonal is merged with those of its template no further on than this
    least: float = 0.6  # share of a notice's 2-grams that a span needs

    @property
    def templates(self) -> list[tuple[list[str], str, list[list[int]]]]:
        """(words, label, for each word that must be there the 2-gram positions that hold it) by template number, base first."""
        found = []
        for phrase, label, *needed in (*self.base, *self.notices):
            words = phrase.lower().split()
            if len(words) < 2:
                raise ValueError("a template needs two words or more")
            need = [[p for p in (i - 1, i) if 0 <= p < len(words) - 1] for i, word in enumerate(words) if needed and word in needed[0].split()]
            found.append((words, label, need))
        return found


def template_rows(config: Config) -> list[tuple]:
    """(first, second, template, position): a row for each 2-gram of each template."""
    return [(*words[p : p + 2], number, p) for number, (words, _, _) in enumerate(config.templates) for p in range(len(words) - 1)]


def _words(text: str) -> Column:
    """Words in lower case. Lower-casing beyond A-Z changes neither where words end nor which words
    are ASCII, once the Kelvin sign, the one other letter with an ASCII lower case, is put aside."""
    return F.regexp_extract_all(F.lower(F.replace(F.coalesce(F.col(text), F.lit("")), F.lit("K"), F.lit("Å"))), F.lit(WORD), F.lit(0))


def _by_template(values: list[Column]) -> Column:
    """The value of a row's template."""
    return F.get(F.array(*values), F.col("template"))


def _verified(config: Config) -> Column:
    """(position, at) of every template position that the merged diagonals of column near (votes, diagonal, positions) have in order."""
    heaviest = F.array_sort(F.transform("near", lambda d: F.struct((-d["votes"]).alias("less"), d["diagonal"].alias("diagonal"), d["positions"].alias("positions"))))
    places = F.transform(
        F.sequence(F.lit(0), F.col("grams") - 1),
        lambda p: F.struct(p.alias("position"), (F.get(F.filter(heaviest, lambda d: F.array_contains(d["positions"], p)), F.lit(0))["diagonal"] + p).alias("at")),
    )
    empty = F.array().cast("array<struct<position:int,at:int>>")
    return F.aggregate(
        F.filter(places, lambda x: x["at"].isNotNull()), empty,
        lambda held, x: F.when((F.size(held) == 0) | (x["at"] > F.element_at(held, -1)["at"]), F.concat(held, F.array(x))).otherwise(held),
    )


def scan(docs: DataFrame, config: Config = Config()) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, spans for every row of docs.

    n_base counts every place of every base phrase, overlapping ones too; first_word and last_word are
    the smallest and largest start (null without one); labels adds those of the notices found;
    score is the largest share of a notice's or phrase's 2-grams that one standing span holds (0 without
    any); spans lists the standing spans as (label, first word, 2-grams, share), where spans of one label may overlap.
    A word said over and over counts once; of templates that meet at one place the best covered counts. Null and empty texts
    have no words and no labels. Repeated rows give repeated results, also
    under one doc_id or none. Whole texts count, however long. Other columns are ignored.
    """
    spark = docs.sparkSession
    templates = config.templates
    # fixed size: a row for each 2-gram of the given templates
    sentinel = [("", "", -1, 0)]
    table = F.broadcast(spark.createDataFrame(template_rows(config) + sentinel, "first string, second string, template int, position int").withColumn("hash", F.xxhash64("first", "second")))

    rows = pick(docs, "doc_id", "text").select(
        F.col("doc_id").cast("bigint").alias("doc_id"), F.monotonically_increasing_id().alias("row"), _words("text").alias("w")
    )

    ends = F.size("w") - 2
    starts = F.when(ends >= 0, F.sequence(F.lit(0), ends)).otherwise(F.array().cast("array<int>"))
    rolling = F.transform(starts, lambda i: F.struct(i.alias("at"), F.xxhash64(F.get("w", i), F.get("w", i + 1)).alias("hash")))
    alone = F.array(F.struct(F.lit(-1).alias("at"), F.xxhash64(F.lit(""), F.lit("")).alias("hash")))
    hits = (
        rows.select("doc_id", "row", "w", F.size("w").cast("bigint").alias("n_words"), F.explode(F.concat(alone, rolling)).alias("g"))
        .join(table, F.col("g.hash") == table["hash"])
        # equal hashes are not enough: the words have to be the template's
        .where((F.col("g.at") < 0) == (F.col("template") < 0))
        .where((F.col("template") < 0) | ((F.get("w", F.col("g.at")) == F.col("first")) & (F.get("w", F.col("g.at") + 1) == F.col("second"))))
        .select("doc_id", "row", "n_words", "template", "position", F.col("g.at").alias("at"))
        .repartition(F.col("row"))
    )
    notice = F.col("template") >= len(config.base)
    grams = F.coalesce(_by_template([F.lit(len(words) - 1) for words, _, _ in templates]), F.lit(0))
    votes = hits.groupBy("row", "doc_id", "n_words", "template", (F.col("at") - F.col("position")).alias("diagonal")).agg(F.collect_set("position").alias("positions"))
    votes = votes.withColumn("votes", F.size("positions")).withColumn("grams", grams)

    # diagonals that can be part of a span with votes enough; base phrases need all on one diagonal
    line = Window.partitionBy("row", "template").orderBy("diagonal")
    onward, back = line.rangeBetween(0, config.slack), line.rangeBetween(-config.slack, 0)
    strong = F.sum("votes").over(onward) >= config.least * F.col("grams")
    alive = votes.withColumn("strong", strong).withColumn("alive", F.max("strong").over(back)).where(F.when(notice, F.col("alive")).otherwise((F.col("template") < 0) | (F.col("votes") == F.col("grams"))))
    merged = alive.withColumn("near", F.when(notice, F.collect_list(F.struct("votes", "diagonal", "positions")).over(onward)))
    need = _by_template([F.array(*[F.array(*map(F.lit, held)) for held in need]).cast("array<array<int>>") for _, _, need in templates])
    spans = (
        merged.withColumn("taken", F.when(notice & F.col("strong"), _verified(config)))
        .withColumn("share", F.when(notice, F.size("taken") / F.col("grams")).otherwise(F.lit(1.0)))
        .where(~notice | (F.col("strong") & (F.col("share") >= config.least) & F.forall(need, lambda held: F.exists("taken", lambda x: F.array_contains(held, x["position"])))))
        .withColumn("label", _by_template([F.lit(label) for _, label, _ in templates]))
        .select("row", "doc_id", "n_words", "template", "diagonal", "grams", "label", "share", F.explode_outer(F.when(notice, F.col("taken.at"))).alias("at"))
    )
    # one label a place: that of the span there with the largest share, or else the longest, or else the last by name
    best = F.max(F.struct("share", "grams", "label")).over(Window.partitionBy("row", "at"))
    standing = (
        spans.withColumn("won", F.when(F.col("at").isNull() | (best["label"] == F.col("label")), 1).otherwise(0))
        .groupBy("row", "doc_id", "n_words", "template", "diagonal", "grams", "label", "share")
        .agg(F.sum("won").alias("won"), F.min("at").alias("begin"), F.max("at").alias("end"))
        .where(~notice | (F.col("won") >= config.least * F.col("grams")))
    )
    whole = (F.col("template") >= 0) & ~notice
    start = F.when(whole, F.col("diagonal").cast("bigint"))
    found = F.when(F.col("template") >= 0, F.struct("label", F.coalesce("begin", "diagonal").alias("first"), F.coalesce(F.col("end") - F.col("begin") + 1, F.col("grams")).alias("grams"), "share"))
    joined = lambda c: F.array_join(F.array_sort(F.collect_set(F.when(c, F.col("label")))), ",")
    return (
        standing.groupBy("row", "doc_id", "n_words")
        .agg(
            F.count_if(whole).alias("n_base"),
            F.min(start).alias("first_word"),
            F.max(start).alias("last_word"),
            joined(whole).alias("base_labels"),
            joined(F.col("template") >= 0).alias("labels"),
            F.coalesce(F.max(F.when(F.col("template") >= 0, F.col("share"))), F.lit(0.0)).alias("score"),
            F.array_sort(F.collect_list(found)).alias("spans"),
        )
        .drop("row")
    )
