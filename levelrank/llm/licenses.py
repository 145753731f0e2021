"""License scans by diagonal voting, in DataFrame operations only.

Every word position of every text asks a small broadcast index for the template
positions that start with its rolling word gram. A hit votes for a diagonal (word position minus
template position). Diagonals of one template that lie within its gap merge, which bridges
words that were added or left out. A merged span is verified before it counts: the longest chain of
its words that runs forward in text and template alike must cover enough of the template, all of it for
phrases, and stand in a stretch of the text that is little longer than the template. Only hits leave the
scan stage.

Null and empty texts have no words and no places. Repeated rows and rows without doc_id are scanned one
by one. A very long text is one row of the scan and as many votes as it has hits. Columns other than
doc_id and text are not read, so clashing names do no harm.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: What separates words once A-Z are lower-cased.
SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: The two characters outside ASCII whose lower case would begin with an ASCII letter.
FOLDING = ("K", "İ")
MAX_TEMPLATE_WORDS = 200_000
#: Words by which a verified stretch may pass its template, as a share of the template.
STRETCH = 0.3


@dataclass(frozen=True)
class Template:
    label: str
    text: str
    exact: bool = False
    gram: int = 2
    gap: int = 3
    cover: float = 0.8


#: The base phrases and their labels.
PHRASES = (Template("cc-by", "cc by", exact=True), Template("gpl", "general public license", exact=True), Template("reserved", "all rights reserved", exact=True))
#: Common notices, as their licenses ask for them.
NOTICES = (
    Template("apache-2.0", "licensed under the apache license version 2 0"),
    Template("mit", "released under the mit license"),
    Template("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", gram=3),
    Template("gpl", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation", gram=3),
    Template("gpl", "this work is licensed under the gnu general public license version 3", gram=3),
    Template("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", gram=3),
    Template("mpl-2.0", "this source code form is subject to the terms of the mozilla public license v 2 0", gram=3),
    Template("cc-by", "this work is licensed under a creative commons attribution 4 0 international license", gram=3),
    Template("cc-by-nc", "licensed under cc by nc 4 0"),
)


def words_of(text: Column) -> Column:
    """Words of a text, A-Z lower-cased; other characters may lose their case too, which no template sees."""
    plain = F.coalesce(text, F.lit(""))
    for c in FOLDING:
        plain = F.replace(plain, F.lit(c), F.lit("ⓐ"))
    return F.array_remove(F.split(F.lower(plain), SEPARATORS, -1), "")


def template_index(spark, templates) -> DataFrame:
    """One row per template position: hash of its first two words, the whole gram, the template's facts."""
    rows = []
    for t, x in enumerate(templates):
        w = x.text.split()
        k = min(x.gram, len(w))
        if k < 2:
            raise ValueError("a template needs two words")
        rows += [(t, x.label, x.exact, 0 if x.exact else x.gap, 1.0 if x.exact else x.cover, len(w), i, w[i : i + k]) for i in range(len(w) - k + 1)]
    if len(rows) > MAX_TEMPLATE_WORDS:
        raise ValueError("the template index is too large to broadcast")
    index = spark.createDataFrame(rows, "template int, label string, exact boolean, gap int, cover double, size int, tpos int, gram array<string>")
    return index.withColumn("h", F.xxhash64(F.get("gram", F.lit(0)), F.get("gram", F.lit(1))))


def _chain(places: Column, size: Column, room: Column) -> Column:
    """The best chain (n, start, end) over sorted (pos, down) places, down being minus the template position:
    both positions rise strictly along it. Of chains with as many words the one that starts last wins, and one
    whose stretch would pass ``room`` words starts anew.

    The state holds, per template position, the best chain that ends there; positions come in ascending
    order and, within one, the later template positions first, so a text word is used once."""
    none = F.struct(F.lit(0).alias("n"), F.lit(-1).alias("start"), F.lit(-1).alias("end"))

    def step(state: Column, place: Column) -> Column:
        pos, at = place["pos"], -place["down"]
        before = F.array_max(F.transform(F.filter(F.slice(state, F.lit(1), at), lambda x: pos - x["start"] < room), lambda x: F.struct(x["n"].alias("n"), x["start"].alias("start"))))
        fresh = F.struct((F.coalesce(F.when(before["n"] > 0, before["n"]), F.lit(0)) + 1).alias("n"), F.coalesce(F.when(before["n"] > 0, before["start"]), pos).alias("start"), (pos + 1).alias("end"))
        better = lambda x: F.when((fresh["n"] > x["n"]) | ((fresh["n"] == x["n"]) & (fresh["start"] > x["start"])), fresh).otherwise(x)
        return F.transform(state, lambda x, i: F.when(i == at, better(x)).otherwise(x))

    return F.array_max(F.aggregate(places, F.array_repeat(none, size), step))


def scan(docs: DataFrame, templates=PHRASES + NOTICES) -> DataFrame:
    """Spans and a marker row per input row: row, doc_id, n_words, template, label, exact, start, end_word, covered, share, accepted."""
    index = template_index(docs.sparkSession, templates)
    rows = docs.select(F.monotonically_increasing_id().alias("row"), F.col("doc_id").cast("long").alias("doc_id"), words_of(F.col("text")).alias("words"))
    places = rows.select("row", "doc_id", "words", F.posexplode_outer("words").alias("pos", "word"))
    gram = (F.xxhash64("word", F.get("words", F.col("pos") + 1)) == F.col("h")) & (F.slice("words", F.col("pos") + 1, F.size("gram")) == F.col("gram"))
    voted = places.join(F.broadcast(index), gram, "left").where(F.col("template").isNotNull() | F.coalesce(F.col("pos") == 0, F.lit(True)))
    votes = voted.select("row", "doc_id", F.size("words").alias("n_words"), "template", "label", "exact", "gap", "cover", "size", "tpos", (F.col("pos") - F.col("tpos")).alias("d"), F.size("gram").alias("k"))
    votes = votes.repartition("row")
    per_template = Window.partitionBy("row", "template").orderBy("d")
    seen = F.array_distinct(F.flatten(F.collect_list(F.sequence("tpos", F.col("tpos") + F.col("k") - 1))))
    diagonals = votes.groupBy("row", "doc_id", "n_words", "template", "label", "exact", "gap", "cover", "size", "d").agg(seen.alias("seen"))
    fresh = F.coalesce((F.col("d") - F.lag("d").over(per_template) > F.col("gap")).cast("int"), F.lit(0))
    merged = diagonals.withColumn("fresh", fresh).withColumn("cluster", F.sum("fresh").over(per_template))
    on_text = F.transform("seen", lambda t: F.struct((F.col("d") + t).cast("int").alias("pos"), (-t).cast("int").alias("down")))
    spans = merged.groupBy("row", "doc_id", "n_words", "template", "label", "exact", "cover", "size", "cluster").agg(
        F.min(F.col("d") + F.array_min("seen")).alias("lo"), F.max(F.col("d") + F.array_max("seen") + 1).alias("hi"), F.size(F.array_distinct(F.flatten(F.collect_list("seen")))).alias("touched"),
        F.flatten(F.collect_list(F.when(~F.col("exact"), on_text).otherwise(F.slice(on_text, F.lit(1), F.lit(0))))).alias("places"),
    )
    room = F.ceil(F.col("size") * (1 + STRETCH)).cast("int")
    enough = F.col("touched") >= F.col("cover") * F.col("size")
    whole = F.struct(F.col("touched").alias("n"), F.col("lo").cast("int").alias("start"), F.col("hi").cast("int").alias("end"))  # one diagonal without a gap is its own chain
    chain = F.when(F.col("exact"), whole).when(enough, _chain(F.array_sort(F.array_distinct("places")), F.col("size"), room))
    out = spans.withColumn("chain", chain)
    covered = F.coalesce("chain.n", F.lit(0))
    out = out.select("row", "doc_id", "n_words", "template", "label", "exact", "cover", F.coalesce("chain.start", "lo").alias("start"), F.coalesce("chain.end", "hi").alias("end_word"), covered.alias("covered"), (covered / F.col("size")).alias("share"))
    return out.withColumn("accepted", F.coalesce(F.col("share") >= F.col("cover"), F.lit(False)))


def report(docs: DataFrame) -> DataFrame:
    """One row per row of ``docs``. Null or empty texts have no words, no places and score 0."""
    spans = scan(docs)
    ok, base = F.col("accepted"), F.col("accepted") & F.col("exact")
    joined = lambda c: F.array_join(F.array_sort(F.collect_set(F.when(c, F.col("label")))), ",")
    out = spans.groupBy("row", "doc_id").agg(
        F.first("n_words").cast("long").alias("n_words"), F.count_if(base).alias("n_base"), F.min(F.when(base, F.col("start"))).cast("long").alias("first_word"), F.max(F.when(base, F.col("start"))).cast("long").alias("last_word"),
        joined(base).alias("base_labels"), joined(ok).alias("labels"), F.coalesce(F.max(F.when(ok, F.col("share"))), F.lit(0.0)).alias("score"),
    )
    return out.drop("row")
