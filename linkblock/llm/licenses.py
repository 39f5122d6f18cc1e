"""License scan by diagonal voting.

Every rolling word k-gram of every text is hashed and joined, in Spark, to the
positions of the same k-gram in license templates. A hit votes for the
diagonal (position in the text minus position in the template). Votes are
summed by diagonal, neighbouring diagonals of one template are merged where
the text has words more or fewer, and the merged spans are verified: base
phrases need every k-gram on one diagonal; for longer templates the k-grams
are chained by rising positions in text and template, each counts once, every
DRIFT words of drift between diagonals cost one, and a share of the template's
k-grams must be left.

The templates are a bounded configuration, so their table is broadcast. The
workers drop k-grams whose hash is in no template before they reach the join
(a filter of the join's own keys), and the join compares the words besides the
hash, so a collision can't count.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from linkblock.llm.common import as_bytes, narrow

#: ASCII letters (lower-cased) and digits stay, other ASCII becomes a blank, all else is part of words.
WORDS = bytes(b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256))


@dataclass(frozen=True)
class Template:
    """words of a license text; k: gram length; share: of its grams that a span must show (1: every one, in a row)."""

    label: str
    text: str
    k: int
    share: float
    base: bool = False

    @property
    def words(self) -> list[bytes]:
        return self.text.encode().translate(WORDS).split()


#: The contract's phrases.
BASE = (
    Template("gpl", "gnu general public license", 2, 1.0, True), Template("apache", "apache license", 2, 1.0, True),
    Template("cc-by", "cc by", 2, 1.0, True), Template("mit", "mit license", 2, 1.0, True),
)
#: Opening or granting sentences of public licenses.
LONGER = (
    Template("mit", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction", 4, 0.5),
    Template("apache", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at", 4, 0.5),
    Template("gpl", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation", 4, 0.5),
    Template("bsd", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met", 4, 0.5),
    Template("isc", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted", 4, 0.5),
    Template("mpl", "This Source Code Form is subject to the terms of the Mozilla Public License", 4, 0.5),
    Template("cc-by", "This work is licensed under a Creative Commons Attribution 4.0 International License", 4, 0.5),
    Template("cc0", "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work", 4, 0.5),
    Template("unlicense", "This is free and unencumbered software released into the public domain", 4, 0.5),
    Template("reserved", "all rights reserved", 2, 1.0),
)
TEMPLATES = BASE + LONGER
#: Words that a text may have more or fewer between two diagonals of one span, and between two k-grams of a chain.
DRIFT = 4

_MIX = np.uint64(0x9E3779B97F4A7C15)


def gram_hashes(words: Sequence[bytes], k: int) -> np.ndarray:
    """64-bit hashes of all rolling k-grams, from one hash a word."""
    if len(words) < k:
        return np.zeros(0, np.uint64)
    one = np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))
    n = len(words) - k + 1
    rolled = np.zeros(n, np.uint64)
    for i in range(k):
        rolled = rolled * _MIX + one[i : i + n]
        rolled ^= rolled >> np.uint64(29)
    return rolled


def best_chain(hits: list[tuple[int, int]]) -> tuple[float, int, int]:
    """(k-grams less drift / DRIFT, first and last text position) of the best chain of hits (text position, template position), sorted.

    Both positions rise along a chain, and a step changes the diagonal by at
    most DRIFT words. Of equal chains the first found stays. For each template
    position only hits that a later one can still reach are held, so the time
    grows with the hits.
    """
    best, longest = (0.0, 0, 0), max((t for _, t in hits), default=0)
    ends: dict[int, list[tuple[int, float, int]]] = {}
    for pos, t in hits:
        score, start = 1.0, pos
        for t_before, held in ends.items():
            if t_before < t:
                for at, value, began in reversed(held):
                    drift = abs((pos - t) - (at - t_before))
                    if at < pos and drift <= DRIFT and value + 1 - drift / DRIFT > score:
                        score, start = value + 1 - drift / DRIFT, began
        held = ends.setdefault(t, [])
        held.append((pos, score, start))
        while held[0][0] < pos - longest - DRIFT:
            held.pop(0)
        if score > best[0]:
            best = (score, start, pos)
    return best


def _chains(pos: pd.Series, t_pos: pd.Series) -> pd.DataFrame:
    made = [best_chain(list(zip(p.tolist(), t.tolist(), strict=True))) for p, t in zip(pos, t_pos, strict=True)]
    return pd.DataFrame(made, columns=["votes", "first", "last"])


def template_positions(spark: SparkSession, templates: Sequence[Template]) -> DataFrame:
    """(h, gram, template, t_pos): every k-gram of every template, a few hundred rows."""
    rows = []
    for at, t in enumerate(templates):
        words = t.words
        rows += [(int(h), b" ".join(words[i : i + t.k]).decode(), at, i) for i, h in enumerate(gram_hashes(words, t.k).view(np.int64))]
    return spark.createDataFrame(rows, "h bigint, gram string, template int, t_pos int")


def _grams(templates: Sequence[Template]):
    """The worker's part: a row for each document, and a row for each gram that may be in a template."""
    lengths = sorted({t.k for t in templates})
    seen = {k: np.zeros(1 << 16, bool) for k in lengths}
    for t in templates:
        seen[t.k][(gram_hashes(t.words, t.k) & np.uint64(0xFFFF)).astype(np.int64)] = True
    schema = pa.schema([("doc_id", pa.int64()), ("digest", pa.string()), ("n_words", pa.int64()), ("pos", pa.int64()), ("h", pa.int64()), ("gram", pa.string())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 256):
                part, rows = whole.slice(at, 256), []
                for doc_id, text in zip(part.column("doc_id").to_pylist(), part.column("text").to_pylist(), strict=True):
                    words, digest = text.translate(WORDS).split(), xxhash.xxh3_128_hexdigest(text)
                    rows.append((doc_id, digest, len(words), None, None, None))
                    for k in lengths:
                        hashes = gram_hashes(words, k)
                        for i in np.flatnonzero(seen[k][(hashes & np.uint64(0xFFFF)).astype(np.int64)]).tolist():
                            rows.append((doc_id, digest, None, i, int(hashes[i].view(np.int64)), b" ".join(words[i : i + k]).decode()))
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)

    return run


def _spans(docs: DataFrame, id_col: str, text_col: str, templates: Sequence[Template]) -> DataFrame:
    """Spans of every document, besides one row for the document itself (no label; n_words, copies).

    One exchange by document; diagonals, spans and the caller's totals all keep it.
    """
    grams = as_bytes(narrow(docs, id_col, text_col)).mapInArrow(_grams(templates), "doc_id bigint, digest string, n_words bigint, pos bigint, h bigint, gram string")
    where = template_positions(docs.sparkSession, templates)
    hits = grams.join(F.broadcast(where), ["h", "gram"], "left").where("n_words IS NOT NULL OR template IS NOT NULL").repartition("doc_id", "digest")
    facts = docs.sparkSession.createDataFrame(
        [(i, t.label, len(t.words), t.k, float(t.share), t.base) for i, t in enumerate(templates)],
        "template int, label string, t_words int, k int, share double, base boolean",
    )
    key = ["doc_id", "digest", "template"]
    diagonals = (
        hits.groupBy(*key, (F.col("pos") - F.col("t_pos")).alias("diagonal"))
        .agg(F.collect_set("pos").alias("at"), F.count("n_words").alias("copies"), F.max("n_words").alias("n_words"))
        .select(*key, "diagonal", "at", "copies", "n_words", F.size("at").alias("votes"), F.array_min("at").alias("first"), F.array_max("at").alias("last"))
        .join(F.broadcast(facts), "template", "left")
    )
    order = Window.partitionBy(*key).orderBy("diagonal")
    apart = (F.col("share") >= 1) | (F.col("diagonal") - F.lag("diagonal").over(order) > DRIFT)
    exact = F.col("share") >= 1
    spans = (
        diagonals.withColumn("span", F.sum(F.coalesce(apart, F.lit(True)).cast("int")).over(order))
        .withColumn("hits", F.when(~exact, F.transform("at", lambda p: F.struct(p.alias("p"), (p - F.col("diagonal")).alias("t")))))
        .groupBy(*key, "label", "t_words", "k", "share", "base", "span")
        .agg(
            F.array_sort(F.flatten(F.collect_list("hits"))).alias("hits"), F.sum("votes").cast("double").alias("votes"), F.min("first").alias("first"), F.max("last").alias("last"),
            F.max("copies").alias("copies"), F.max("n_words").alias("n_words"),
        )
        .withColumn("chain", F.pandas_udf(_chains, "struct<votes:double,first:bigint,last:bigint>")(F.transform("hits", lambda h: h["p"]), F.transform("hits", lambda h: h["t"])))
    )
    of = lambda name: F.when(exact, F.col(name)).otherwise(F.col(f"chain.{name}"))
    coverage = F.when(F.col("label").isNotNull(), F.least(F.lit(1.0), of("votes") / (F.col("t_words") - F.col("k") + 1)))
    return spans.select(
        *key, "label", "base", of("first").alias("start"), (of("last") + F.col("k")).alias("stop"), "copies", "n_words", coverage.alias("coverage"), (coverage >= F.col("share")).alias("verified")
    )


def license_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", templates: Sequence[Template] = TEMPLATES) -> DataFrame:
    """(doc_id, label, base, start, stop, coverage): verified spans, positions in words from 0; of merged diagonals the best chain.

    Repeated rows (same id and text) count once here.
    """
    return _spans(docs, id_col, text_col, templates).where("verified").select("doc_id", "label", "base", "start", "stop", "coverage")


def scan_licenses(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", templates: Sequence[Template] = TEMPLATES) -> DataFrame:
    """One row a document: n_words, base places (n_base, first_word, last_word, base_labels), labels, score.

    score: the best coverage of any template's span, 1 for a whole phrase. Null
    and empty texts have no words, empty labels and score 0. Repeated rows give
    repeated rows; rows that share an id but not the text are judged apart.
    """
    place = F.when(F.col("base") & F.col("verified"), F.col("start"))
    named = lambda c: F.array_join(F.array_sort(F.collect_set(c)), ",")
    return (
        _spans(docs, id_col, text_col, templates).groupBy("doc_id", "digest")
        .agg(
            F.max("copies").cast("int").alias("copies"), F.max("n_words").alias("n_words"), F.count(place).alias("n_base"),
            F.min(place).alias("first_word"), F.max(place).alias("last_word"),
            named(F.when(F.col("base") & F.col("verified"), F.col("label"))).alias("base_labels"),
            named(F.when(F.col("verified"), F.col("label"))).alias("labels"),
            F.coalesce(F.max("coverage"), F.lit(0.0)).alias("score"),
        )
        .select(F.explode(F.array_repeat(F.struct("doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score"), F.col("copies"))).alias("r"))
        .select("r.*")
    )
