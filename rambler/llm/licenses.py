"""License detection by diagonal voting over word k-grams, beside plain phrase places.

Words of the license templates are numbered, and k of them pack into one 64-bit key without loss. Every rolling k-gram of a
document that holds template words alone (no other can meet a template) is joined to the templates' k-gram positions. Each meeting
votes for a diagonal, position in the document less position in the template; neighbouring diagonals merge into one span, so that
a few inserted or lost words don't break it. Every span with votes enough is then verified: its k-grams have to stand in the
template's order, within a stretch of bounded length, and still be enough of the template's.
"""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD_TABLE, byte_texts, pick, written

# Phrases with their labels, and the opening or characteristic sentences of well-known public licenses.
PHRASES = {"mit license": "mit", "apache license": "apache", "general public license": "gpl"}
TEMPLATES = {
    "mit": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the Software), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software",
    "apache": "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License. You may obtain a copy of the License at",
    "gpl": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version",
    "bsd": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer",
    "isc": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies",
    "mpl": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at",
    "apache-short": "Licensed under the Apache License, Version 2.0",
    "gpl-short": "This work is licensed under the GNU General Public License, version 3",
    "mit-short": "Released under the MIT License",
    "cc-by-nc": "Licensed under CC BY-NC 4.0",
    "cc-by": "This work is licensed under a Creative Commons Attribution 4.0 International License",
    "unlicense": "This is free and unencumbered software released into the public domain",
}
LABEL_OF = {"apache-short": "apache", "gpl-short": "gpl", "mit-short": "mit"}


def words_of(raw: bytes) -> list[bytes]:
    return raw.translate(WORD_TABLE).split()


def template_grams(templates: dict[str, str], k: int) -> tuple[dict[bytes, int], list[tuple[int, str, int, int]]]:
    """Numbers of the templates' words, from 1; and (key, template, position, number of k-grams). Templates need k words at least."""
    split = {name: words_of(text.encode()) for name, text in templates.items()}
    number = {w: i + 1 for i, w in enumerate(sorted({w for ws in split.values() for w in ws}))}
    bits = 63 // k
    if len(number) >= 1 << bits or any(len(ws) < k for ws in split.values()):
        raise ValueError(f"templates need {k} words at least, and fewer than {1 << bits} different ones in all")
    return number, [(sum(number[w] << bits * j for j, w in enumerate(ws[i : i + k])), name, i, len(ws) - k + 1) for name, ws in split.items() for i in range(len(ws) - k + 1)]


def _scanner(number: dict[bytes, int], phrases: dict[str, str], k: int):
    wanted = [(p.encode().split(), label) for p, label in phrases.items()]
    heads = {ws[0] for ws, _ in wanted}
    bits = 63 // k

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        serial = 0
        for batch in batches:
            rows = []
            for doc, raw in zip(batch.column(0).to_pylist(), byte_texts(batch.column(1))):
                ws = words_of(raw)
                found, labels = [], set()
                if heads & (own := set(ws)):
                    for i, w in enumerate(ws):
                        if w in heads:
                            for phrase, label in wanted:
                                if ws[i : i + len(phrase)] == phrase:
                                    found.append(i)
                                    labels.add(label)
                grams = []
                if len(own & number.keys()) and len(ws) >= k:
                    ids = np.fromiter(map(number.get, ws, [0] * len(ws)), np.int64, len(ws))
                    n = len(ws) - k + 1
                    key, whole = np.zeros(n, np.int64), np.ones(n, bool)
                    for j in range(k):
                        part = ids[j : j + n]
                        key |= part << (bits * j)
                        whole &= part > 0
                    grams = [{"pos": p, "key": x} for p, x in zip(np.flatnonzero(whole).tolist(), key[whole].tolist())]
                rows.append((doc, len(ws), len(found), min(found, default=None), max(found, default=None), sorted(labels), grams))
            types = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.string()), pa.list_(pa.struct([("pos", pa.int64()), ("key", pa.int64())])))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), types)], ["doc_id", "n_words", "n_base", "first_word", "last_word", "base", "grams"])
                serial += len(rows)

    return run


def aligned(met: list[tuple[int, int]], size: int, gap: int) -> list[tuple[int, int, int]]:
    """(first position, last position, k-grams) of the stretches in which k-grams (position, place in the template) stand in the template's order.

    The longest rising chain of each stretch is taken; a stretch ends where the next k-gram is farther than the template is long, and
    is cut at the chain's widest gap while the chain is longer than twice the template and `gap`."""
    met, out, todo = sorted(met, key=lambda x: (x[0], -x[1])), [], []
    start = 0
    for i in range(1, len(met) + 1):
        if i == len(met) or met[i][0] - met[i - 1][0] > size + gap:
            todo.append(met[start:i])
            start = i
    while todo:
        part = todo.pop()
        ends, at, before = [], [], []  # of the best chain of each length: its last place in the template, and where that stands
        for i, (_, t) in enumerate(part):
            k = bisect_left(ends, t)
            ends[k : k + 1], at[k : k + 1] = [t], [i]
            before.append(at[k - 1] if k else -1)
        chain, i = [], at[-1]
        while i >= 0:
            chain.append(part[i][0])
            i = before[i]
        chain.reverse()
        if chain[-1] - chain[0] <= 2 * size + gap:
            out.append((chain[0], chain[-1], len(chain)))
        else:
            _, cut = max((b - a, b) for a, b in zip(chain[:-1], chain[1:]))
            todo += [x for x in ([m for m in part if m[0] < cut], [m for m in part if m[0] >= cut]) if x]
    return out


def _verify(k: int, gap: int, least: float):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for row, template, size, met in zip(*(batch.column(i).to_pylist() for i in range(4))):
                for first, last, n in aligned([(m["diagonal"] + t, t) for m in met for t in m["met"]], size, gap):
                    if n >= least * size:
                        rows.append((row, template, first, last + k, n / size))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.float64()))], ["row", "template", "start", "end", "share"])

    return run


def scan_licenses(docs: DataFrame, templates: dict[str, str] | None = None, phrases: dict[str, str] | None = None, k: int = 4, gap: int = 8, least: float = 0.6) -> tuple[DataFrame, DataFrame]:
    """(rows, spans). rows: a stored table (row, doc_id, n_words, n_base, first_word, last_word, base); spans: (row, template, start, end, share).

    gap: diagonals at most so far apart merge; least: share of a template's k-grams that a span has to meet. Null text counts as
    empty. Rows are told apart by `row`, so repeated rows and doc_ids do no harm; an empty table gives none."""
    number, grams = template_grams(templates or TEMPLATES, k)
    spark = docs.sparkSession
    table = F.broadcast(spark.createDataFrame(grams, "key long, template string, tpos long, size long"))  # constants: a few hundred rows
    schema = "doc_id long, n_words long, n_base long, first_word long, last_word long, base array<string>, grams array<struct<pos: long, key: long>>"
    rows = written(pick(docs, "doc_id", "text").mapInArrow(_scanner(number, phrases or PHRASES, k), schema).withColumn("row", F.monotonically_increasing_id()))
    met = rows.select("row", F.inline("grams")).join(table, "key").withColumn("diagonal", F.col("pos") - F.col("tpos"))
    votes = met.groupBy("row", "template", "diagonal").agg(F.collect_set("tpos").alias("met"), F.first("size").alias("size"))
    by = Window.partitionBy("row", "template").orderBy("diagonal")
    # A document may hold a template often, on far diagonals: each run of near ones is a span of its own.
    runs = votes.withColumn("new", F.coalesce((F.col("diagonal") - F.lag("diagonal").over(by) > gap).cast("int"), F.lit(1))).withColumn("run", F.sum("new").over(by))
    spans = runs.groupBy("row", "template", "run").agg(F.first("size").alias("size"), F.collect_list(F.struct("diagonal", "met")).alias("met"))
    enough = spans.where(F.size(F.array_distinct(F.flatten("met.met"))) >= F.lit(least) * F.col("size"))
    return rows.drop("grams"), enough.select("row", "template", "size", "met").mapInArrow(_verify(k, gap, least), "row long, template string, start long, end long, share double")


def license_labels(docs: DataFrame, **how) -> DataFrame:
    """(doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score) of each row: labels joined by commas, score the best share of a template (1 if a base phrase stands there and no span is better)."""
    rows, spans = scan_licenses(docs, **how)
    label = F.coalesce(F.element_at(F.create_map(*[F.lit(x) for pair in LABEL_OF.items() for x in pair]), F.col("template")), F.col("template"))
    best = spans.groupBy("row").agg(F.collect_set(label).alias("more"), F.max("share").alias("share"))
    none = F.array().cast("array<string>")
    return rows.join(best, "row", "left").select(
        "doc_id", "n_words", "n_base", "first_word", "last_word", F.array_join("base", ",").alias("base_labels"),
        F.array_join(F.array_sort(F.array_union("base", F.coalesce("more", none))), ",").alias("labels"),
        F.greatest(F.coalesce("share", F.lit(0.0)), F.when(F.col("n_base") > 0, 1.0).otherwise(0.0)).alias("score"),
    )
