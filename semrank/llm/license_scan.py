"""License scans by diagonal voting. DataFrame functions only.

Every place of a text where two consecutive words stand in some template gives a k-gram hash (k = 2); these join the
template positions by hash. A hit's diagonal is its place in the text less its place in the template, so one copy of
a template votes for one diagonal, and an inserted or missing word moves the votes to a neighbouring one. Votes are
summed by document, template and diagonal. Neighbouring diagonals, as far apart as the words that a copy of that length
may gain or lose (``DRIFT`` of the template's words), make a candidate span; it is verified by the longest run of hits
whose places rise with their positions, each hit having been compared word by word: the run must hold ``COVER`` of the
template's k-grams, and all those of the template's key words, which tell versions of one license apart. So a span is
never longer than the template and its drift, whatever else the text says, and shuffled or scattered words are none.

Short phrases (``PHRASES``) count where all their words stand consecutively: all votes on one diagonal.

Cases: a null, empty or wordless text has no words and no labels; repeated rows are searched one by one;
other columns are ignored; a null doc_id is kept; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import only

#: Phrases that count wherever they stand, and their labels.
PHRASES = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}
#: Public license texts, or the notices that stand for them, as words; their labels; and the words that must be there.
TEMPLATES = (
    (
        "mit",
        "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction "
        "including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so "
        "subject to the following conditions the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software "
        "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement "
        "in no event shall the authors or copyright holders be liable for any claim damages or other liability whether in an action of contract tort or otherwise arising from out of or in connection with the software or the use or other dealings in the software",
        "",
    ),
    ("mit-notice", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction", ""),
    (
        "bsd",
        "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met "
        "redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer "
        "redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution",
        "",
    ),
    ("bsd-notice", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", ""),
    ("bsd-3-clause", "neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission", ""),
    (
        "bsd-warranty",
        "this software is provided by the copyright holders and contributors as is and any express or implied warranties including but not limited to the implied warranties of merchantability and fitness for a particular purpose are disclaimed "
        "in no event shall the copyright holder or contributors be liable for any direct indirect incidental special exemplary or consequential damages including but not limited to procurement of substitute goods or services loss of use data or profits "
        "or business interruption however caused and on any theory of liability whether in contract strict liability or tort including negligence or otherwise arising in any way out of the use of this software even if advised of the possibility of such damage",
        "",
    ),
    (
        "apache-2.0",
        "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license you may obtain a copy of the license at http www apache org licenses license 2 0 "
        "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied "
        "see the license for the specific language governing permissions and limitations under the license",
        "apache license version 2 0",
    ),
    ("apache-2.0-notice", "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license", "version 2 0"),
    ("mpl-2.0", "this source code form is subject to the terms of the mozilla public license v 2 0 if a copy of the mpl was not distributed with this file you can obtain one at http mozilla org mpl 2 0", "license v 2 0"),
    ("mpl-2.0-notice", "this source code form is subject to the terms of the mozilla public license v 2 0", "license v 2 0"),
    ("gpl-notice", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation", ""),
    ("gpl-2.0", "you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 2 of the license or at your option any later version", "version 2"),
    ("gpl-3.0-or-later", "you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version", "version 3"),
    ("gpl-3.0", "this work is licensed under the gnu general public license version 3", "version 3"),
    ("lgpl", "you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation", "lesser general public"),
    ("agpl", "you can redistribute it and or modify it under the terms of the gnu affero general public license as published by the free software foundation", "affero general public"),
    (
        "isc",
        "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies "
        "the software is provided as is and the author disclaims all warranties with regard to this software including all implied warranties of merchantability and fitness "
        "in no event shall the author be liable for any special direct indirect or consequential damages or any damages whatsoever resulting from loss of use data or profits whether in an action of contract negligence or other tortious action "
        "arising out of or in connection with the use or performance of this software",
        "",
    ),
    ("isc-notice", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", ""),
    (
        "zlib",
        "this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages arising from the use of this software "
        "permission is granted to anyone to use this software for any purpose including commercial applications and to alter it and redistribute it freely subject to the following restrictions "
        "the origin of this software must not be misrepresented you must not claim that you wrote the original software",
        "",
    ),
    (
        "bsl-1.0",
        "permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying documentation covered by this license the software "
        "to use reproduce display distribute execute and transmit the software and to prepare derivative works of the software and to permit third parties to whom the software is furnished to do so",
        "",
    ),
    ("cc-by-4.0", "this work is licensed under a creative commons attribution 4 0 international license", "attribution 4 0"),
    ("cc-by-sa-4.0", "licensed under cc by sa 4 0", "by sa 4 0"),
    ("cc-by-nc-4.0", "licensed under cc by nc 4 0", "by nc 4 0"),
    (
        "unlicense",
        "this is free and unencumbered software released into the public domain anyone is free to copy modify publish use compile sell or distribute this software either in source code form or as a compiled binary "
        "for any purpose commercial or non commercial and by any means",
        "",
    ),
    ("unlicense-notice", "this is free and unencumbered software released into the public domain", ""),
)
#: Words that a copy may have gained or lost, as a share of the template's words; the share of its k-grams from which a span counts.
DRIFT, COVER = 0.2, 0.8
#: The words ``[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+`` of lower-cased text, most frequent characters first.
WORD = "[a-z\\x{80}-\\x{10FFFF}0-9]++"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def words_of(text: Column) -> Column:
    """Words, A-Z lower-cased. lower() is the fast way; the two letters whose lower case is or holds an ASCII letter go by hand."""
    odd = text.contains("\u212a") | text.contains("\u0130")
    lowered = F.when(odd, F.translate(text, _UPPER, _LOWER)).otherwise(F.lower(text))
    return F.regexp_extract_all(lowered, F.lit(WORD), F.lit(0))


def template_rows() -> list[tuple]:
    """(template, label, base, size, drift, must, words) of each phrase and template; must: places of the pairs of the key words."""
    out = []
    for label, text, key in (*((label, text, "") for text, label in PHRASES.items()), *TEMPLATES):
        words, wanted, base = text.split(" "), key.split(" "), len(out) < len(PHRASES)
        at = next((i for i in range(len(words)) if key and words[i : i + len(wanted)] == wanted), 0)
        out.append((len(out), label, base, len(words), 0.5 if base else max(1.0, float(int(DRIFT * len(words) + 1e-9))), list(range(at, at + len(wanted) - 1)), words))
    return out


def templates(spark: SparkSession) -> DataFrame:
    """(template, label, base, size, drift, must): one row per phrase and template. A fixed, small table."""
    return spark.createDataFrame([t for *t, _ in template_rows()], "template int, label string, base boolean, size int, drift double, must array<int>")


def template_grams(spark: SparkSession) -> DataFrame:
    """(template, place, t_a, t_b, hash): one row per pair of consecutive words. A fixed, small table."""
    rows = [(number, i, words[i], words[i + 1]) for number, *_, words in template_rows() for i in range(len(words) - 1)]
    grams = spark.createDataFrame(rows, "template int, place int, t_a string, t_b string")
    return grams.withColumn("hash", F.xxhash64("t_a", "t_b"))


def hits(docs: DataFrame) -> DataFrame:
    """(row, template, place, pos, doc_id, n_words): every place where a template's pair of words stands.

    Each row of ``docs`` also gives one row without a template; that alone carries its doc_id and number of words.
    """
    firsts = sorted({w for *_, words in template_rows() for w in words[:-1]})
    seconds = sorted({w for *_, words in template_rows() for w in words[1:]})
    rows = docs.select("doc_id", F.monotonically_increasing_id().alias("row"), F.coalesce(words_of(F.col("text")), F.array().cast("array<string>")).alias("words"))
    # a pair with a word that no template has there can't join, so it isn't made
    places = F.filter(F.sequence(F.lit(0), F.greatest(F.size("words") - 2, F.lit(0))), lambda i: F.get("words", i).isin(firsts) & F.coalesce(F.get("words", i + 1).isin(seconds), F.lit(False)))
    pairs = F.transform(places, lambda i: F.struct(i.alias("pos"), F.get("words", i).alias("a"), F.get("words", i + 1).alias("b")))
    none = F.array(F.struct(F.lit(None).cast("int").alias("pos"), F.lit(None).cast("string").alias("a"), F.lit(None).cast("string").alias("b")))
    grams = rows.select("row", "doc_id", F.size("words").cast("long").alias("n_words"), F.inline(F.concat(none, pairs))).withColumn("hash", F.xxhash64("a", "b"))
    joined = grams.join(F.broadcast(template_grams(docs.sparkSession)), "hash", "left").filter("pos is null or (a = t_a and b = t_b)")
    return joined.select("row", "template", "place", "pos", *(F.when(F.col("pos").isNull(), F.col(c)).alias(c) for c in ("doc_id", "n_words")))


def rising(found: Column) -> Column:
    """The length of the longest run of hits (pos, place) with rising places; hits in order of pos, equal pos by falling place.

    The array kept is, for each length, the smallest place that a run of that length ends with."""
    step = lambda ends, h: F.concat(
        F.filter(ends, lambda e: e < h["place"]), F.array(h["place"]), F.slice(ends, F.size(F.filter(ends, lambda e: e < h["place"])) + 2, F.size(ends) + 1)
    )
    return F.size(F.aggregate(found, F.array().cast("array<int>"), step))


def spans(docs: DataFrame) -> DataFrame:
    """(row, doc_id, n_words, label, base, first_word, last_word, score) of every verified span; words count from 0.

    A row of ``docs`` without spans gives one row without a label. Of neighbouring candidates the best stands for all.
    Hits are dealt by rows of ``docs`` once; everything after that happens where they are.
    """
    spark = docs.sparkSession
    dealt = hits(only(docs, "doc_id", "text")).repartition("row")
    votes = (
        dealt.groupBy("row", "template", (F.col("pos") - F.col("place")).alias("diagonal"))
        .agg(F.sort_array(F.collect_list("place")).alias("places"), F.max("doc_id").alias("doc_id"), F.max("n_words").alias("n_words"))
        .join(F.broadcast(templates(spark)), "template", "left")
    )
    # one order for all templates of a row: a template's drift is 1,000 steps, and templates lie far apart
    votes = votes.withColumn("at", F.coalesce(F.col("template") * F.lit(1 << 40) + F.floor(F.col("diagonal") * 1000.0 / F.col("drift")), F.lit(-(1 << 40))))
    along = W.partitionBy("row").orderBy("at")
    ahead, behind = along.rangeBetween(0, 1001), along.rangeBetween(-1001, 0)
    # a candidate is a diagonal and those that follow it within the drift; only where their votes suffice are the hits brought together
    need = F.when(F.col("base"), F.col("size") - 1).otherwise(F.ceil((F.col("size") - 1) * COVER - F.lit(1e-9)))
    hopeful = votes.withColumn("enough", F.coalesce(F.sum(F.size("places")).over(ahead) >= need, F.lit(True)))
    hopeful = hopeful.withColumn("near", F.max("enough").over(behind)).filter("near")
    own = F.transform("places", lambda p: F.struct((p + F.col("diagonal")).alias("pos"), (-p).alias("fall"), p.alias("place")))
    found = hopeful.withColumn("found", F.when(F.col("base"), own).otherwise(F.array_sort(F.flatten(F.collect_list(own).over(ahead))))).filter("enough")
    placed = F.transform("found", lambda h: h["place"])
    # a phrase has all its votes on one diagonal, where places rise anyway
    run = F.when(F.col("base"), F.size("found")).when(F.size(F.array_distinct(placed)) >= need, rising(F.col("found")))
    scored = found.withColumn("n", F.when(F.col("template").isNotNull() & (F.size(F.array_except("must", placed)) == 0), run))
    good = scored.filter(F.col("template").isNull() | (F.col("n") >= need)).withColumn("score", F.col("n") / (F.col("size") - 1))
    good = good.withColumns({"first_word": F.try_element_at("found", F.lit(1))["pos"], "last_word": F.try_element_at("found", F.lit(-1))["pos"] + 1})
    # verified neighbours are one span; a row's own doc_id and number of words stand on its row without a template
    before = F.when(F.lag("template").over(along) == F.col("template"), F.lag("diagonal").over(along))
    apart = F.coalesce(F.col("base"), F.lit(True)) | F.coalesce(F.col("diagonal") - before > F.col("drift"), F.lit(True))
    whole = W.partitionBy("row").orderBy("at").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    numbered = good.withColumns({"new": apart.cast("int"), "doc_id": F.max("doc_id").over(whole), "n_words": F.max("n_words").over(whole)}).withColumn("span", F.sum("new").over(along))
    best = numbered.groupBy("row", "doc_id", "n_words", "template", "label", "base", "span").agg(F.max(F.struct("score", (-F.col("first_word")).alias("neg"), "last_word")).alias("m"))
    return best.select("row", "doc_id", "n_words", "label", "base", (-F.col("m.neg")).alias("first_word"), F.col("m.last_word").alias("last_word"), F.col("m.score").alias("score"))


def scan(docs: DataFrame) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score: one row per row of ``docs``."""
    base_start = F.when(F.col("base"), F.col("first_word"))
    found = spans(docs).groupBy("row", "doc_id", "n_words").agg(
        F.coalesce(F.sum(F.col("base").cast("long")), F.lit(0)).alias("n_base"),
        F.min(base_start).cast("long").alias("first_word"),
        F.max(base_start).cast("long").alias("last_word"),
        F.concat_ws(",", F.array_sort(F.collect_set(F.when(F.col("base"), F.col("label"))))).alias("base_labels"),
        F.concat_ws(",", F.array_sort(F.collect_set("label"))).alias("labels"),
        F.coalesce(F.max("score"), F.lit(0.0)).alias("score"),
    )
    return found.drop("row")
