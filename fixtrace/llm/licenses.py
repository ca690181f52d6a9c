"""Licence scan: ordered signature rules behind a keyword prefilter, DataFrame functions only.

Each rule is tried only where its keyword is one of the text's words; every match of a rule holds its keyword, so the
prefilter rejects no text that a rule matches.  A rule is a regular expression over the words joined by single
spaces; every match becomes a word interval.  Overlaps are resolved within a text: a detection that overlaps one of
higher priority is suppressed, and so is one that lies inside another of equal priority (of equal intervals the first
rule stays).  Both are windows over intervals sorted by start, one for each priority, so no pairs of detections are
made.  The three base phrases are found on the word array itself and their labels always stay.

Rules are written by hand: names of licences, sentences of their texts, notices.  Each name stands in five forms.

Defined results: a null or empty text has no words, no labels (empty strings) and score 0; repeated rows are
scanned one by one; an empty table gives no rows.  Only ``doc_id`` and ``text`` are read.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from fixtrace.llm.common import fold_lower, table

#: Words before and after A-Z are lower-cased have the same bounds.
WORDS = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"

#: label, words of the name as a regular expression over single-spaced words, keyword, which all that it matches holds.
FAMILIES = (
    ("mit", "mit", "mit"), ("mit-0", "mit (?:0|no attribution)", "mit"), ("expat", "expat", "expat"), ("apache", "apache", "apache"),
    ("apache-1.1", "apache(?: version)? 1 1", "apache"), ("apache-2.0", "apache(?: version| license version)? 2(?: 0)?", "apache"),
    ("gpl", "(?:gnu )?general public", "general"), ("gpl", "(?:gnu )?gpl", "gpl"), ("gpl-2.0", "(?:gnu )?gpl(?:(?: version)?(?: v| v | )| version)2(?: 0)?", "gpl"), ("gpl-2.0", "gplv2", "gplv2"), ("gpl-2.0", "(?:gnu )?gpl2(?: 0)?", "gpl2"),
    ("gpl-3.0", "(?:gnu )?gpl(?:(?: version)?(?: v| v | )| version)3(?: 0)?", "gpl"), ("gpl-3.0", "gplv3", "gplv3"), ("gpl-3.0", "(?:gnu )?gpl3(?: 0)?", "gpl3"), ("lgpl", "(?:gnu )?lgpl", "lgpl"), ("lgpl", "(?:gnu )?(?:lesser|library) general public", "general"),
    ("lgpl-2.1", "lgpl(?:(?: version)?(?: v| v | )| version)2 1", "lgpl"), ("lgpl-2.1", "lgpl2 1", "lgpl2"), ("lgpl-3.0", "lgpl(?:(?: version)?(?: v| v | )| version)3(?: 0)?", "lgpl"), ("lgpl-3.0", "lgpl3(?: 0)?", "lgpl3"),
    ("agpl", "(?:gnu )?agpl", "agpl"), ("agpl", "(?:gnu )?agplv3", "agplv3"), ("agpl", "(?:gnu )?affero general public", "affero"),
    ("bsd", "bsd", "bsd"), ("bsd-2-clause", "(?:simplified bsd|bsd 2 clause|2 clause bsd)", "bsd"), ("bsd-3-clause", "(?:new bsd|modified bsd|bsd 3 clause|3 clause bsd)", "bsd"), ("bsd-4-clause", "(?:original bsd|bsd 4 clause|4 clause bsd)", "bsd"),
    ("mpl", "mpl", "mpl"), ("mpl", "mozilla public", "mozilla"), ("mpl-2.0", "mozilla public(?: license)?(?: version)? 2(?: 0)?", "mozilla"), ("epl", "eclipse public", "eclipse"), ("cddl", "common development and distribution", "distribution"),
    ("cpl", "common public", "common"), ("isc", "isc", "isc"), ("zlib", "zlib", "zlib"), ("boost", "boost(?: software)?", "boost"), ("unlicense", "unlicense", "unlicense"),
    ("wtfpl", "wtfpl", "wtfpl"), ("artistic", "artistic", "artistic"), ("python", "psf", "psf"), ("python", "python(?: software foundation)?", "python"), ("postgresql", "postgresql", "postgresql"),
    ("eupl", "eupl", "eupl"), ("eupl", "european union public", "european"), ("ofl", "ofl", "ofl"), ("ofl", "sil open font", "font"), ("cc0", "cc0", "cc0"), ("cc0", "creative commons zero", "commons"),
    ("cc-by", "cc by", "cc"), ("cc-by", "creative commons attribution", "attribution"), ("cc-by-sa", "cc by sa", "cc"), ("cc-by-nc", "cc by nc", "cc"),
    ("cc-by-sa", "creative commons attribution share ?alike", "commons"), ("cc-by-nc", "creative commons attribution non ?commercial", "commons"), ("cecill", "cecill", "cecill"), ("ncsa", "ncsa", "ncsa"),
    ("openssl", "openssl", "openssl"), ("php", "php", "php"), ("ruby", "ruby", "ruby"), ("vim", "vim", "vim"), ("odbl", "odbl", "odbl"), ("odbl", "open database", "database"),
)
#: suffix of the rule's name, expression around a family's words, priority, relevance.
FORMS = (
    ("named", "(?:the )?{} licen[sc]e", 20, 0.7),
    ("versioned", "(?:the )?{} licen[sc]e (?:version |v ?)?[0-9](?: [0-9])?", 40, 0.9),
    ("tag", "spdx license identifier {}(?: only| or later)?", 60, 1.0),
    ("granted", "(?:licensed|released|distributed|available|published) under (?:the )?(?:terms of (?:the )?)?{}(?: licen[sc]e)?", 50, 0.95),
    ("dual", "dual licensed under (?:the )?{}", 55, 0.9),
)
#: A name with a version goes before one without.
VERSION_BONUS = 25
#: Notices that name no family: label, expression, keyword, priority, relevance.
NOTICES = (
    ("public-domain", "(?:in|into|to) the public domain", "domain", 30, 0.6),
    ("copyright-notice", "copyright (?:c )?[0-9]{4}", "copyright", 10, 0.2),
    ("all-rights-reserved", "all rights reserved", "reserved", 10, 0.3),
    ("no-warranty", "without warrant(?:y|ies) of any kind", "without", 15, 0.5),
    ("permission-notice", "permission is hereby granted free of charge", "hereby", 45, 0.9),
    ("redistribution", "redistribution and use in source and binary forms", "redistribution", 45, 0.9),
)
#: Sentences that stand in the texts or headers of licences: label, expression, keyword.
SENTENCES = (
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software", "hereby"),
    ("mit", "to deal in the software without restriction including without limitation the rights to use", "restriction"),
    ("mit", "the above copyright notice and this permission notice shall be included in all copies", "permission"),
    ("x11", "except as contained in this notice the names? of .{0,80}? shall not be used in advertising", "advertising"),
    ("bsd", "redistributions of source code must retain the above copyright notice", "redistributions"),
    ("bsd", "redistributions in binary form must reproduce the above copyright notice", "redistributions"),
    ("bsd-3-clause", "neither the names? of .{0,80}? nor the names of its contributors may be used to endorse", "endorse"),
    ("bsd-4-clause", "all advertising materials mentioning features or use of this software must display", "advertising"),
    ("bsd-4-clause", "must display the following acknowledge?ment this product includes software developed by", "display"),
    ("isc", "permission to use copy modify and (?:or )?distribute this software for any purpose with or without fee", "fee"),
    ("isc", "the software is provided as is and the author disclaims all warranties", "disclaims"),
    ("0bsd", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted the software", "fee"),
    ("ntp", "permission to use copy modify and distribute this software and its documentation for any purpose", "documentation"),
    ("hpnd", "the above copyright notice appears? in all copies and that both that copyright notice and this permission notice appear in supporting documentation", "supporting"),
    ("zlib", "this software is provided as is without any express or implied warranty in no event will the authors be held liable", "liable"),
    ("zlib", "the origin of this software must not be misrepresented", "misrepresented"),
    ("zlib", "altered source versions must be plainly marked as such", "plainly"),
    ("zlib", "this notice may not be removed or altered from any source distribution", "altered"),
    ("libpng", "the png reference library is supplied as is", "png"),
    ("boost", "permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying documentation", "organization"),
    ("boost", "unless such copies or derivative works are solely in the form of machine executable object code", "solely"),
    ("unlicense", "this is free and unencumbered software released into the public domain", "unencumbered"),
    ("unlicense", "anyone is free to copy modify publish use compile sell or distribute this software", "anyone"),
    ("wtfpl", "do what the fuck you want to", "fuck"),
    ("beerware", "if we meet some day and you think this stuff is worth it you can buy me a beer", "beer"),
    ("apache-2.0", "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis", "basis"),
    ("apache-2.0", "you may not use this file except in compliance with the license", "compliance"),
    ("apache-2.0", "you may obtain a copy of the license at http www apache org licenses license 2 0", "apache"),
    ("apache-2.0", "see the license for the specific language governing permissions and limitations", "governing"),
    ("apache-2.0", "subject to the terms and conditions of this license each contributor hereby grants to you a perpetual", "perpetual"),
    ("apache-2.0", "apache license version 2 0", "apache"), ("mpl-2.0", "mozilla public license version 2 0", "mozilla"),
    ("apache-1.1", "this product includes software developed by the apache software foundation", "apache"),
    ("apache-1.1", "products derived from this software may not be called apache", "apache"),
    ("gpl", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license", "gnu"),
    ("gpl", "you should have received a copy of the gnu general public license along with this program", "gnu"),
    ("gpl", "this program is distributed in the hope that it will be useful but without any warranty", "hope"),
    ("gpl", "the licenses for most software are designed to take away your freedom to share and change it", "freedom"),
    ("gpl-2.0", "gnu general public license as published by the free software foundation either version 2", "gnu"),
    ("gpl-2.0", "gnu general public license version 2 as published by", "gnu"),
    ("gpl-2.0", "version 2 june 1991", "1991"),
    ("gpl-3.0", "gnu general public license as published by the free software foundation either version 3", "gnu"),
    ("gpl-3.0", "gnu general public license version 3 as published by", "gnu"),
    ("gpl-3.0", "gnu general public license version 3 29 june 2007", "gnu"),
    ("lgpl", "gnu (?:lesser|library) general public license as published by the free software foundation", "gnu"),
    ("lgpl", "you should have received a copy of the gnu (?:lesser|library) general public license along with", "gnu"),
    ("lgpl", "a program that contains no derivative of any portion of the library but is designed to work with the library", "derivative"),
    ("lgpl-2.1", "(?:gnu )?lesser general public license version 2 1 february 1999", "lesser"),
    ("lgpl-2.1", "gnu lesser general public license as published by the free software foundation either version 2 1", "lesser"),
    ("lgpl-3.0", "gnu lesser general public license as published by the free software foundation either version 3", "lesser"),
    ("agpl", "gnu affero general public license as published by the free software foundation", "affero"),
    ("agpl", "you should have received a copy of the gnu affero general public license along with", "affero"),
    ("agpl", "offer all users interacting with it remotely through a computer network", "remotely"),
    ("gfdl", "permission is granted to copy distribute and or modify this document under the terms of the gnu free documentation license", "documentation"),
    ("gfdl", "with no invariant sections no front cover texts and no back cover texts", "invariant"),
    ("mpl", "the contents of this file are subject to the mozilla public license", "mozilla"),
    ("mpl-1.1", "the contents of this file are subject to the mozilla public license version 1 1", "mozilla"),
    ("mpl-2.0", "this source code form is subject to the terms of the mozilla public license v 2 0", "mozilla"),
    ("mpl-2.0", "if a copy of the mpl was not distributed with this file you can obtain one at", "mpl"),
    ("epl", "this program and the accompanying materials are made available under the terms of the eclipse public license", "eclipse"),
    ("epl-1.0", "eclipse public license v(?:ersion)? ?1 0", "eclipse"),
    ("epl-2.0", "eclipse public license v(?:ersion)? ?2 0", "eclipse"),
    ("cpl", "the accompanying program is provided under the terms of this common public license", "common"),
    ("cddl", "the contents of this file are subject to the terms of the common development and distribution license", "development"),
    ("cddl", "when distributing covered code include this cddl header notice in each file", "cddl"),
    ("artistic", "the intent of this document is to state the conditions under which a package may be copied", "intent"),
    ("artistic", "you may redistribute it and or modify it under the same terms as perl itself", "perl"),
    ("artistic-2.0", "the artistic license 2 0", "artistic"),
    ("perl", "licensed under the same terms as perl itself", "perl"),
    ("python", "psf is making python available to licensee on an as is basis", "psf"),
    ("python", "this license agreement is between the python software foundation", "python"),
    ("postgresql", "permission to use copy modify and distribute this software and its documentation for any purpose without fee and without a written agreement", "agreement"),
    ("openssl", "this product includes software developed by the openssl project", "openssl"),
    ("ssleay", "this product includes cryptographic software written by eric young", "cryptographic"),
    ("php", "this product includes php software freely available from", "php"),
    ("php", "this source file is subject to version [0-9](?: [0-9]+)? of the php license", "php"),
    ("ruby", "you can redistribute it and or modify it under either the terms of the 2 clause bsdl", "bsdl"),
    ("vim", "vim is charityware you can use and copy it as much as you like", "charityware"),
    ("curl", "except as contained in this notice the name of a copyright holder shall not be used in advertising", "holder"),
    ("ncsa", "university of illinois ncsa open source license", "illinois"),
    ("ofl", "this font software is licensed under the sil open font license", "font"),
    ("ofl", "the font software may be sold as part of a larger software package but no copy", "font"),
    ("cecill", "this software is governed by the cecill license under french law", "cecill"),
    ("eupl", "licensed under the eupl version 1 [12] or as soon they will be approved by the european commission", "eupl"),
    ("ms-pl", "microsoft public license(?: ms pl)?", "microsoft"),
    ("ms-rl", "microsoft reciprocal license(?: ms rl)?", "microsoft"),
    ("afl", "academic free license(?: version)?(?: [0-9] [0-9])?", "academic"),
    ("osl", "licensed under the open software license(?: version)? 3 0", "licensed"),
    ("qpl", "the q public license(?: version)? 1 0", "q"),
    ("sleepycat", "redistributions in any form must be accompanied by information on how to obtain complete source code", "accompanied"),
    ("json", "the software shall be used for good not evil", "evil"),
    ("cc0", "to the extent possible under law .{0,80}? has waived all copyright and related or neighboring rights", "waived"),
    ("cc0", "cc0 1 0 universal", "cc0"),
    ("cc-by", "this work is licensed under a creative commons attribution(?: [0-9] [0-9])?(?: international| unported)? license", "attribution"),
    ("cc-by-sa", "this work is licensed under a creative commons attribution share ?alike", "attribution"),
    ("cc-by-nc", "this work is licensed under a creative commons attribution non ?commercial", "attribution"),
    ("cc-by-nd", "creative commons attribution no ?deriv(?:s|atives|ative works)", "attribution"),
    ("cc-by-nc-sa", "creative commons attribution non ?commercial share ?alike", "attribution"),
    ("cc-by-nc-nd", "creative commons attribution non ?commercial no ?deriv(?:s|atives|ative works)", "attribution"),
    ("cc-by-nc-sa", "cc by nc sa", "cc"), ("cc-by-nc-nd", "cc by nc nd", "cc"), ("cc-by-nd", "cc by nd", "cc"),
    ("odbl", "this .{0,40}? is made available under the open database license", "database"),
    ("odc-by", "open data commons attribution license", "commons"),
    ("pddl", "open data commons public domain dedication and licen[sc]e", "dedication"),
    ("sspl", "server side public license(?: version)?(?: 1)?", "server"),
    ("busl", "business source license(?: 1 1)?", "business"),
    ("elastic", "elastic license(?: 2 0| version)?", "elastic"),
    ("commons-clause", "the software is provided to you by the licensor under the license as defined below subject to the following condition", "licensor"),
    ("proprietary", "this (?:software|document|file) is (?:the )?confidential(?: and proprietary)?", "confidential"),
    ("proprietary", "this (?:software|document|file) is (?:the )?proprietary(?: and confidential)?", "proprietary"),
    ("proprietary", "(?:unauthori[sz]ed|any) (?:copying|reproduction|distribution|use) (?:of this .{0,40}? )?is strictly prohibited", "strictly"),
    ("proprietary", "trade secrets? (?:of|and|or)", "trade"),
    ("evaluation", "for evaluation (?:purposes )?only", "evaluation"),
    ("non-commercial", "for non commercial (?:use|purposes) only", "commercial"), ("non-commercial", "for noncommercial (?:use|purposes) only", "noncommercial"),
    ("non-commercial", "may not be used for commercial purposes", "commercial"),
    ("personal-use", "for (?:your )?personal use only", "personal"),
    ("research-use", "for (?:educational and )?academic (?:use|purposes) only", "academic"), ("research-use", "for (?:academic and )?educational (?:use|purposes) only", "educational"),
    ("research-use", "for (?:academic and |educational and )?research (?:use|purposes) only", "research"),
    ("export-notice", "subject to (?:the )?export (?:control|administration) (?:laws|regulations)", "export"),
    ("warranty-disclaimer", "the software is provided as is without warranty of any kind express or implied", "warranty"),
    ("warranty-disclaimer", "this software is provided by .{0,80}? as is and any express or implied warranties", "warranties"),
    ("warranty-disclaimer", "without even the implied warranty of merchantability or fitness for a particular purpose", "merchantability"),
    ("liability-disclaimer", "in no event shall .{0,80}? be liable for any (?:claim|direct|damages)", "liable"),
    ("patent-grant", "hereby grants? .{0,60}? patent license to make have made use", "patent"),
    ("contributor-agreement", "contributor license agreement", "contributor"),
    ("third-party", "third party (?:software|licenses|notices)", "third"),
    ("see-license-file", "see (?:the )?license(?: txt| md)?(?: file)? for (?:more |full |further )?(?:details|information)", "license"),
    ("see-license-file", "see (?:the )?licence(?: txt| md)?(?: file)? for (?:more |full |further )?(?:details|information)", "licence"),
    ("see-license-file", "see (?:the )?copying(?: txt| md)?(?: file)? for (?:more |full |further )?(?:details|information)", "copying"),
    ("same-terms", "under the same terms as", "terms"), ("same-terms", "under the same license as", "license"),
)


def rule_rows() -> list[tuple]:
    """(rule, label, pattern, keyword, priority, relevance) of every rule, in order."""
    rows = [(f"{label}/{n}/{suffix}", label, f" {form.format(name)}(?= )", keyword, priority + (VERSION_BONUS if label[-1].isdigit() else 0), relevance) for n, (label, name, keyword) in enumerate(FAMILIES) for suffix, form, priority, relevance in FORMS]
    rows += [(f"notice/{label}", label, f" {pattern}(?= )", keyword, priority, relevance) for label, pattern, keyword, priority, relevance in NOTICES]
    return rows + [(f"sentence/{label}/{n}", label, f" {pattern}(?= )", keyword, 70, 0.95) for n, (label, pattern, keyword) in enumerate(SENTENCES)]


def _base(words):
    """Array of (start, label) of the base phrases."""

    def at(w, i):
        back = lambda k: F.try_element_at(words, F.when(i >= k, i - k + 1).otherwise(F.size(words) + 1))
        return (
            F.when(w != "license", F.lit(None))
            .when(back(1) == "mit", F.struct((i - 1).cast("long").alias("start"), F.lit("mit").alias("label")))
            .when(back(1) == "apache", F.struct((i - 1).cast("long").alias("start"), F.lit("apache").alias("label")))
            .when((back(1) == "public") & (back(2) == "general"), F.struct((i - 2).cast("long").alias("start"), F.lit("gpl").alias("label")))
        )

    return F.filter(F.transform(words, at), lambda x: x.isNotNull())


def _intervals(joined, pattern):
    """Array of (first, last) word numbers of the matches of ``pattern``; a match starts at a space before a word."""
    parts, found = F.split(joined, pattern), F.regexp_extract_all(joined, pattern, F.lit(0))
    spaces = lambda x: F.char_length(x) - F.char_length(F.replace(x, F.lit(" "), F.lit("")))
    seen = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<first:int,last:int>>").alias("out"))

    def step(acc, x):
        first = acc["at"] + spaces(x["before"])
        last = first + spaces(x["match"]) - 1
        return F.struct((last + 1).alias("at"), F.array_append(acc["out"], F.struct(first.alias("first"), last.alias("last"))).alias("out"))

    pairs = F.zip_with(F.slice(parts, F.lit(1), F.size(found)), found, lambda b, m: F.struct(b.alias("before"), m.alias("match")))
    return F.aggregate(pairs, seen, step, lambda acc: acc["out"])


def suppressed(found: DataFrame, keys: list[str]) -> DataFrame:
    """The detections (``first``, ``last``, ``priority``, ``rule``) of each text that overlaps leave standing.

    For each priority, the reach of the higher ones is a running maximum of ``last`` from the left and a running
    minimum of ``first`` from the right.
    """
    levels = sorted({r[4] for r in rule_rows()})
    same_start = lambda w: w.rangeBetween(W.unboundedPreceding, W.currentRow)
    left = W.partitionBy(*keys).orderBy("first")
    right = W.partitionBy(*keys).orderBy(F.desc("first"))
    over = F.lit(False)
    for level in levels[:-1]:
        higher = F.col("priority") > level
        reach = F.max(F.when(higher, F.col("last"))).over(same_start(left))
        start = F.min(F.when(higher, F.col("first"))).over(same_start(right))
        over = F.when(F.col("priority") == level, F.coalesce(reach >= F.col("first"), F.lit(False)) | F.coalesce(start <= F.col("last"), F.lit(False))).otherwise(over)
    inside = W.partitionBy(*keys, "priority").orderBy("first", F.col("last").desc(), "rule").rowsBetween(W.unboundedPreceding, -1)
    held = found.withColumns({"__over": over, "__before": F.max("last").over(inside)})
    return held.where(~F.col("__over") & (F.col("__before").isNull() | (F.col("__before") < F.col("last")))).drop("__over", "__before")


def scan(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(texts, detections): a row for each document, and the detections that survive suppression.

    A text meets each of its keywords once, with one expression that any of the keyword's rules matches; only where
    that does is it tried against the rules one by one.
    """
    spark = docs.sparkSession
    words = F.regexp_extract_all(fold_lower(F.coalesce(F.col("text"), F.lit(""))), F.lit(WORDS), F.lit(0))
    split = docs.select("doc_id", F.xxhash64("text").alias("text_hash"), words.alias("words"))
    texts = split.select("doc_id", "text_hash", F.size("words").cast("long").alias("n_words"), "words")
    rules = spark.createDataFrame(rule_rows(), "rule string, label string, pattern string, keyword string, priority int, relevance double")
    grouped: dict[str, list[str]] = {}
    for _, _, pattern, keyword, _, _ in rule_rows():
        grouped.setdefault(keyword, []).append(pattern)
    gates = spark.createDataFrame([(k, "|".join(v)) for k, v in grouped.items()], "keyword string, gate string")
    hits = split.withColumn("met", F.array_intersect("words", F.array(*map(F.lit, sorted(grouped))))).where(F.size("met") > 0)
    hits = hits.select("doc_id", "text_hash", F.concat(F.lit(" "), F.array_join("words", " "), F.lit(" ")).alias("joined"), F.explode("met").alias("keyword"))
    passed = hits.join(F.broadcast(gates), "keyword").where(F.expr("joined rlike gate")).drop("gate")
    tried = passed.join(F.broadcast(rules), "keyword").where(F.expr("joined rlike pattern"))
    found = tried.select("doc_id", "text_hash", "rule", "label", "priority", "relevance", F.explode(_intervals(F.col("joined"), F.col("pattern"))).alias("x")).select("*", "x.first", "x.last").drop("x")
    return texts, suppressed(found.distinct(), ["doc_id", "text_hash"])


def label_texts(docs: DataFrame) -> DataFrame:
    """One row for each document, base and method labels together."""
    texts, found = scan(docs)
    per_text = found.groupBy("doc_id", "text_hash").agg(F.collect_set("label").alias("more"), F.max("relevance").alias("top"))
    base = texts.select("doc_id", "text_hash", "n_words", F.when(F.array_contains("words", "license"), _base(F.col("words"))).alias("base"))
    per_text = per_text.select(F.col("doc_id").alias("__doc"), F.col("text_hash").alias("__hash"), "more", "top")
    out = base.join(per_text, F.col("doc_id").eqNullSafe(F.col("__doc")) & (F.col("text_hash") == F.col("__hash")), "left")
    starts = F.col("base.start")
    labels = F.array_sort(F.array_distinct(F.coalesce(F.col("base.label"), F.array().cast("array<string>"))))
    every = F.array_sort(F.array_union(labels, F.coalesce(F.col("more"), F.array().cast("array<string>"))))
    n = F.coalesce(F.when(F.col("base").isNotNull(), F.size("base")), F.lit(0)).cast("long")
    return out.select(
        "doc_id", "n_words", n.alias("n_base"), F.array_min(starts).alias("first_word"), F.array_max(starts).alias("last_word"),
        F.array_join(labels, ",").alias("base_labels"), F.array_join(every, ",").alias("labels"),
        F.greatest(F.coalesce("top", F.lit(0.0)), F.when(n > 0, 0.7).otherwise(0.0)).alias("score"),
    )


def op6_license_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return label_texts(table(spark, sf_dir, "documents"))
