"""Workloads on the natural tables, which need no derived code."""

from __future__ import annotations

import functools
import itertools
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from fixtrace.functions.store import settle
from fixtrace.functions.text import alike, cosine, simhash64
from fixtrace.sources.tables import table
from fixtrace.streaming import feed


def following(rows: DataFrame, key: str, number: str, width: int = 1 << 16) -> DataFrame:
    """(key, number, after): the next greater number under the same key, null for the last one; null numbers are left out.

    Windows hold one range of ``width`` numbers of a key, and one row for each such range, so no key meets in one task.
    """
    marked = rows.select(key, number).where(F.col(number).isNotNull()).distinct().withColumn("__part", F.floor(F.col(number) / width))
    firsts = marked.groupBy(key, "__part").agg(F.min(number).alias("__first"))
    onward = firsts.select(F.col(key).alias("__key"), F.col("__part").alias("__at"), F.lead("__first").over(W.partitionBy(key).orderBy("__part")).alias("__next"))
    inside = F.lead(number).over(W.partitionBy(key, "__part").orderBy(number))
    met = marked.withColumn("__inside", inside).join(onward, F.col(key).eqNullSafe(F.col("__key")) & (F.col("__part") == F.col("__at")))
    return met.select(key, number, F.coalesce("__inside", "__next").alias("after"))


def line_pairs(docs: DataFrame) -> DataFrame:
    """(source, doc_a, doc_b, line_no, a, b): equal line numbers of neighbouring documents of one source.

    Neighbours come from ids alone, so texts are joined once, not carried through a window.
    """
    near = following(docs, "source", "doc_id").where("after is not null").withColumnRenamed("after", "doc_b")
    lines = docs.select("doc_id", F.posexplode(F.split("text", "\n")).alias("line_no", "x"))
    a = near.join(lines, "doc_id").select("source", F.col("doc_id").alias("doc_a"), "doc_b", "line_no", F.col("x").alias("a"))
    return a.join(lines.select(F.col("doc_id").alias("doc_b"), "line_no", F.col("x").alias("b")), ["doc_b", "line_no"])


def w11_edit(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = line_pairs(table(spark, sf_dir, "documents").select("doc_id", "source", "text"))
    return rows.groupBy("source").agg(F.count("*").alias("n_pairs"), F.count_if(alike(F.col("a"), F.col("b"), 800)).alias("n_similar"))


def w11_md5(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = line_pairs(table(spark, sf_dir, "documents").select("doc_id", "source", "text"))
    bare = lambda c: F.md5(F.trim(F.regexp_replace(c, " +", " ")).cast("binary"))
    return rows.groupBy("source").agg(F.count("*").alias("n_pairs"), F.count_if(bare("a") == bare("b")).alias("n_equal"))


def w11_cosine(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Precision and recall of cosine thresholds against equal labels; every hundredth vector asks all others."""
    v = table(spark, sf_dir, "embeddings")
    asked = v.where("vec_id % 100 = 0").select(F.col("vec_id").alias("qid"), F.col("embedding").alias("q"), F.col("label").alias("ql"))
    blocks = 64
    spread = asked.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    rows = v.withColumn("block", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int")).join(spread, "block").where("vec_id <> qid")
    c = rows.select((F.col("ql") == F.col("label")).alias("same"), cosine(F.col("q"), F.col("embedding")).alias("c"))
    levels = F.explode(F.array(*(F.lit(k / 10) for k in range(1, 6)))).alias("theta")
    return c.select("same", "c", levels).groupBy("theta").agg(F.count_if((F.col("c") >= F.col("theta")) & F.col("same")).alias("tp"), F.count_if((F.col("c") >= F.col("theta")) & ~F.col("same")).alias("fp"), F.count_if((F.col("c") < F.col("theta")) & F.col("same")).alias("fn"))


def _words(c):
    return F.filter(F.split(c, r"\s+"), lambda x: x != "")


def passages_held(docs: DataFrame, items: DataFrame, width: int = 4, block: int = 500) -> DataFrame:
    """(doc_id, item_id) of documents that hold a passage verbatim, at any place.

    The first and last word of a passage may be parts of a document's words, the words between are whole ones: a
    hash of the first ``width`` of them finds (of all, where there are fewer), containment confirms.  Only ids meet in
    the join; texts are read again for what it finds.  Passages of one or two words have no word between; they are
    held against every text in blocks of ``block`` passages.  A null text holds nothing, an empty passage is in every text.
    """
    items = items.select("item_id", F.col("text").alias("passage")).where("passage is not null").withColumn("w", _words(F.col("passage")))
    inner = F.slice("w", F.lit(2), F.least(F.size("w") - 2, F.lit(width)))
    keyed = items.where(F.size("w") > 2).withColumn("inner", inner).select("item_id", F.size("inner").alias("n"), F.xxhash64(F.array_join("inner", " ")).alias("key"))
    cut = docs.select("doc_id", _words(F.col("text")).alias("w"))

    def met_by(n: int) -> DataFrame:
        """Documents that have a key of ``n`` words."""
        hashes = F.transform(F.sequence(F.lit(1), F.size("w") - n + 1), lambda k: F.xxhash64(F.array_join(F.slice("w", k, n), " ")))
        found = cut.where(F.size("w") >= n).select("doc_id", F.explode(F.array_distinct(hashes)).alias("key"))
        return found.join(keyed.where(F.col("n") == n).drop("n"), "key").select("doc_id", "item_id")

    sizes = [r.n for r in keyed.select("n").distinct().orderBy("n").limit(width).collect()]
    met = functools.reduce(DataFrame.unionByName, (met_by(n) for n in sizes or [width])).distinct()
    texts = docs.select("doc_id", "text")
    held = met.join(items.select("item_id", "passage"), "item_id").join(texts, "doc_id").where(F.contains("text", "passage")).select("doc_id", "item_id")
    short = items.where(F.size("w") <= 2).select("item_id", "passage")
    many = short.count()
    if not many:
        return held.distinct()
    blocks = -(-many // block)
    for k in range(blocks):
        asked = short.where(F.pmod(F.xxhash64("item_id"), F.lit(blocks)) == k).agg(F.collect_list(F.struct("item_id", "passage")).alias("asked"))
        hits = texts.join(F.broadcast(asked)).select("doc_id", "text", F.explode("asked").alias("x")).where(F.contains("text", F.col("x.passage")))
        held = held.unionByName(hits.select("doc_id", "x.item_id"))
    return held.distinct()


def w17_signature_hits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark passage verbatim."""
    return passages_held(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def w18_digest_clones(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = table(spark, sf_dir, "documents").select("doc_id", F.md5(F.col("text").cast("binary")).alias("digest"))
    return d.groupBy("digest").agg(F.count("*").alias("n_docs"), F.min("doc_id").alias("first_doc")).where("n_docs > 1")


#: Six blocks of a 64-bit digest: first bit and width.
_BLOCKS = ((0, 11), (11, 11), (22, 11), (33, 11), (44, 10), (54, 10))


def near_digests(docs: DataFrame, limit: int = 3) -> DataFrame:
    """doc_id, class_doc and n_near: a document's class (equal digests, named by the least doc_id) and how many other
    classes lie within ``limit`` bits.

    Of six blocks, ``limit`` <= 3 differing bits leave three untouched, so classes meet under one of twenty keys of three
    blocks (some 32 bits: a key is hardly ever shared by chance).  Copies cost nothing and are never paired.
    """
    if not 0 <= limit <= 3:
        raise ValueError("three of six blocks are compared, so at most three bits may differ")
    words = docs.where("text is not null").select("doc_id", _words(F.col("text")).alias("w")).where(F.size("w") > 0)
    named = settle(words.select("doc_id", simhash64(F.col("w")).alias("h")))
    classes = settle(named.groupBy("h").agg(F.min("doc_id").alias("class_doc")))
    part = [F.shiftrightunsigned("h", at).bitwiseAND(F.lit((1 << width) - 1)) for at, width in _BLOCKS]
    keys = F.array(*(F.xxhash64(F.lit(k), *(part[i] for i in chosen)) for k, chosen in enumerate(itertools.combinations(range(6), 3))))
    dealt = classes.select("h", F.explode(keys).alias("key"))
    pairs = dealt.alias("a").join(dealt.alias("b"), "key").where(F.col("a.h") < F.col("b.h")).where(F.bit_count(F.col("a.h").bitwiseXOR(F.col("b.h"))) <= limit)
    linked = pairs.select(F.col("a.h").alias("x"), F.col("b.h").alias("y")).distinct()
    near = linked.select(F.explode(F.array("x", "y")).alias("h")).groupBy("h").agg(F.count("*").alias("n_near"))
    return named.join(classes, "h").join(near, "h", "left").select("doc_id", "class_doc", F.coalesce("n_near", F.lit(0)).alias("n_near"))


def w18_near_digests(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_digests(table(spark, sf_dir, "documents").select("doc_id", "text"))


def tag_code(tags):
    """One code point for each tag, fixed by its name alone; two names share one with odds of one in a million."""
    point = lambda t: F.lpad(F.hex(F.pmod(F.xxhash64(F.lower(t)), F.lit(0xFFFFE)) + 0x10000), 8, "0")
    return F.decode(F.unhex(F.array_join(F.transform(tags, point), "")), "UTF-32")


def w19_page_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tree similarity of neighbouring pages of a host: edit distance over in-order tag sequences."""
    tags = F.regexp_extract_all("html", F.lit(r"<(/?[a-zA-Z][a-zA-Z0-9]*)"), F.lit(1))
    p = table(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", r"://([^/?#]*)", 1).alias("host"), tag_code(tags).alias("code"))
    near = following(p, "host", "page_id").where("after is not null").select("host", F.col("page_id").alias("page_a"), F.col("after").alias("page_b"))
    one, two = (p.select(F.col("page_id").alias(f"page_{s}"), F.col("code").alias(s)) for s in "ab")
    longest = F.greatest(F.length("a"), F.length("b"))
    return near.join(one, "page_a").join(two, "page_b").select("host", "page_a", "page_b", F.round(F.when(longest == 0, 1.0).otherwise(1 - F.levenshtein("a", "b") / longest), 6).alias("similarity"))


def w20_label_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A plain rule against the quality labels: counts per source, for macro scores.

    The rule asks for at most one mark of ``#*$%&|<>!`` in 200 characters.
    """
    text = F.coalesce("text", F.lit(""))
    rule = F.char_length(F.regexp_replace(text, r"[^#*$%&|<>!]", "")) * 200 <= F.char_length(text)
    rows = table(spark, sf_dir, "documents").select("doc_id", "source", rule.alias("p")).join(table(spark, sf_dir, "labels").select("doc_id", (F.col("quality") == 1).alias("t")), "doc_id")
    return rows.groupBy("source").agg(F.count_if(F.col("p") & F.col("t")).alias("tp"), F.count_if(F.col("p") & ~F.col("t")).alias("fp"), F.count_if(~F.col("p") & F.col("t")).alias("fn"))


def w21_transcripts(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = F.array_sort(F.collect_list(F.struct("turn", "role", "text")))
    t = table(spark, sf_dir, "conversations").groupBy("conv_id").agg(turns.alias("t"))
    return t.select("conv_id", F.size("t").cast("long").alias("n_turns"), F.array_join(F.transform("t", lambda x: F.concat(x["role"], F.lit(": "), x["text"])), "\n").alias("prompt"))


def w22_stream_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    return feed.daily_windows(spark, sf_dir)


def w22_stream_votes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return feed.voted(spark, sf_dir)


def w22_stream_projects(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events of the stream by the project of their user: a stream-static join."""
    return feed.by_project(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    own = (w11_edit, w11_md5, w11_cosine, w17_signature_hits, w18_digest_clones, w18_near_digests, w19_page_trees, w20_label_scores, w21_transcripts, w22_stream_windows, w22_stream_votes, w22_stream_projects)
    return {f.__name__: f for f in own}
