"""License scan by diagonal voting.

The rolling hashes of every ``k`` consecutive words of all documents are joined, in Spark, to the positions at which
the same words stand in license templates (a fixed set, so that side is broadcast).  A match votes for the diagonal "position
in the document minus position in the template".  Votes are counted by diagonal; diagonals a few words apart that follow
each other are merged (words were added or dropped in between); a merged span is kept if enough of its template and enough of
the span itself matched.  Short phrases are templates of their own that must match whole, on a single diagonal.

Words are maximal runs of ASCII letters and digits and all other non-ASCII characters, A-Z lower-cased.  A null or empty text has no words and no labels;
repeated rows are scanned one by one and give equal results; a null id is kept; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from segcube.llm import kernel as K

# Phrases and their labels.
PHRASES = (
    ("gnu general public license", "gpl"),
    ("apache license", "apache"),
    ("cc by", "cc-by"),
    ("mit license", "mit"),
)
# Public license notices and their labels.
NOTICES = (
    ("mit-text", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the Software), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software."),
    ("apache-2.0", "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an AS IS BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License."),
    ("gpl-notice", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details."),
    ("bsd", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."),
    ("isc", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("mpl-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/."),
    ("unlicense", "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means."),
    ("cc-by-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("cc-by-sa-4.0", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("gpl-line", "This work is licensed under the GNU General Public License, version 3."),
    ("apache-line", "Licensed under the Apache License, Version 2.0."),
    ("mit-line", "Released under the MIT License."),
)

#: Words of a gram of a phrase and of a notice.
PHRASE_GRAM, NOTICE_GRAM = 2, 4
#: Diagonals at most so far apart, with at most so many words between, are merged.
DRIFT, GAP = 4, 24
#: A notice's span is kept if at least so much of the notice and of the span matched.
MIN_COVER, MIN_DENSE = 0.6, 0.5
#: Joins the row that every document has.
_ANCHOR = -1


def _hashes(text: str) -> np.ndarray:
    data, offsets = K.text_bytes(pa.array([text]))
    data = K.LOWER[data]
    starts, ends, _ = K.find_words(data, offsets, K.ALNUM)
    return K.hash_spans(data, starts, ends)


def template_positions(spark: SparkSession, phrases=PHRASES, notices=NOTICES) -> DataFrame:
    """``gram, template, at, label, grams, phrase``: each gram of each template with its place; fixed and small."""
    rows = [(_ANCHOR, -1, 0, None, 0, False)]
    templates = [(text, label, PHRASE_GRAM, True) for text, label in phrases] + [(text, label, NOTICE_GRAM, False) for label, text in notices]
    for number, (text, label, k, phrase) in enumerate(templates):
        grams = K.roll(_hashes(text), k).view(np.int64)
        if not len(grams):
            raise ValueError(f"a template needs at least {k} words: {text}")
        rows += [(int(g), number, i, label, len(grams), phrase) for i, g in enumerate(grams)]
    types = {"gram": pa.int64(), "template": pa.int32(), "at": pa.int64(), "label": pa.string(), "grams": pa.int32(), "phrase": pa.bool_()}
    return spark.createDataFrame(pa.table({n: pa.array(c, t) for (n, t), c in zip(types.items(), zip(*rows, strict=True), strict=True)}))


def rolling_grams(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per document ``row_id, doc_id, n_words`` and all its grams: phrase gram and notice gram of word 0, of word 1, ..., then the anchor."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        row = TaskContext.get().partitionId() << 33
        for batch in batches:
            for part in K.steps(batch, "text", 1 << 20):
                data, offsets = K.text_bytes(part.column("text"))
                data = K.LOWER[data]
                starts, ends, first = K.find_words(data, offsets, K.ALNUM)
                words = K.hash_spans(data, starts, ends)
                n = np.diff(first)
                left = np.repeat(first[1:], n) - np.arange(len(words))  # words from here to the document's end
                grams = np.full((len(words) + 1, 2), _ANCHOR, dtype=np.int64)
                for column, k in enumerate((PHRASE_GRAM, NOTICE_GRAM)):
                    rolled = K.roll(words, k).view(np.int64)
                    grams[: len(rolled), column] = rolled
                    grams[: len(words), column][left < k] = 0  # crosses a border: matches no template
                out = np.full(2 * len(words) + len(n), _ANCHOR, dtype=np.int64)
                bounds = 2 * first + np.arange(len(n) + 1)
                out[K.ranges(bounds[:-1], 2 * n)] = grams[: len(words)].ravel()
                lists = pa.ListArray.from_arrays(pa.array(bounds.astype(np.int32)), pa.array(out))
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(row, row + len(n))), part.column("doc_id"), pa.array(n), lists], names=["row_id", "doc_id", "n_words", "grams"])
                row += len(n)

    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(run, "row_id bigint, doc_id bigint, n_words bigint, grams array<bigint>")


def scan(docs: DataFrame, phrases=PHRASES, notices=NOTICES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per document: phrase places, labels, score, and ``spans`` (label, first and last word, share of the template)."""
    templates = template_positions(docs.sparkSession, phrases, notices).withColumnRenamed("grams", "template_grams")
    grams = rolling_grams(docs, id_col, text_col).select("row_id", "doc_id", "n_words", F.posexplode("grams").alias("slot", "gram"))
    votes = grams.join(F.broadcast(templates), "gram")  # the templates are a fixed set
    votes = votes.select("row_id", "doc_id", "n_words", "template", "label", "template_grams", "phrase", F.floor(F.col("slot") / 2).alias("word"), "at")
    document = ["row_id", "doc_id", "n_words"]
    template = ["template", "label", "template_grams", "phrase"]
    by_diagonal = votes.repartition("row_id").groupBy(*document, *template, (F.col("word") - F.col("at")).alias("diagonal")).agg(F.count(F.lit(1)).alias("votes"), F.min("word").alias("low"), F.max("word").alias("high"))
    order = Window.partitionBy("row_id", "template").orderBy("low", "diagonal")
    parts = (F.col("phrase") | F.lag("low").over(order).isNull() | (F.abs(F.col("diagonal") - F.lag("diagonal").over(order)) > DRIFT) | (F.col("low") - F.lag("high").over(order) > GAP)).cast("int")
    spans = by_diagonal.withColumn("new", parts).withColumn("span", F.sum("new").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    spans = spans.groupBy(*document, *template, "span").agg(F.sum("votes").alias("votes"), F.min("low").alias("low"), F.max("high").alias("high"))
    share = F.least(F.lit(1.0), F.col("votes") / F.greatest("template_grams", F.lit(1)))
    whole = F.when(F.col("phrase"), F.col("votes") == F.col("template_grams")).otherwise((share >= MIN_COVER) & (F.col("votes") >= MIN_DENSE * (F.col("high") - F.col("low") + 1)))
    kept = F.when(F.col("template") < 0, False).otherwise(whole)
    spans = spans.withColumn("kept", kept).withColumn("share", share)
    base, found = F.col("kept") & F.col("phrase"), F.col("kept")
    size = F.when(F.col("phrase"), PHRASE_GRAM).otherwise(NOTICE_GRAM)
    per_document = spans.groupBy(*document).agg(
        F.count_if(base).alias("n_base"), F.min(F.when(base, F.col("low"))).alias("first_word"), F.max(F.when(base, F.col("low"))).alias("last_word"),
        F.array_sort(F.collect_set(F.when(base, F.col("label")))).alias("base_label_list"), F.array_sort(F.collect_set(F.when(found, F.col("label")))).alias("label_list"),
        F.coalesce(F.max(F.when((F.col("template") >= 0) & (found | ~F.col("phrase")), F.col("share"))), F.lit(0.0)).alias("score"),
        F.array_sort(F.collect_list(F.when(found, F.struct("low", (F.col("high") + size - 1).alias("high"), "label", "share")))).alias("spans"),
    )
    return per_document.select(
        "doc_id", "n_words", "n_base", "first_word", "last_word", F.array_join("base_label_list", ",").alias("base_labels"), F.array_join("label_list", ",").alias("labels"), "score", "spans"
    )
