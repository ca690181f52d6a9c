"""Text columns: squashing, bounded edit similarity, digests, version order."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def squash(text: Column) -> Column:
    """Comments removed, runs of white space made one space, trimmed."""
    bare = F.regexp_replace(text, r"(?s)/\*.*?\*/|//[^\n]*", " ")
    return F.trim(F.regexp_replace(bare, r"\s+", " "))


def edit_budget(a: Column, b: Column, permille: int) -> Column:
    """The most edits with which similarity is at least ``permille`` / 1000, by integers: 1 - 0.9 is not 0.1."""
    part = (1000 - permille) * F.greatest(F.char_length(a), F.char_length(b))
    return ((part - F.pmod(part, F.lit(1000))) / 1000).cast("int")


def line_similarity(a: Column, b: Column) -> Column:
    """1 - distance / longer length; two empty texts are alike."""
    longest = F.greatest(F.char_length(a), F.char_length(b))
    return F.when(a == b, 1.0).when(longest == 0, 1.0).otherwise(1 - F.levenshtein(a, b) / longest)


def alike(a: Column, b: Column, permille: int) -> Column:
    """Whether similarity reaches the threshold: equal texts and far lengths end early, then a bounded distance."""
    budget = edit_budget(a, b, permille)
    far = F.abs(F.char_length(a) - F.char_length(b)) > budget
    return F.when(a == b, True).when(far, False).otherwise(F.call_function("levenshtein", a, b, budget) >= 0)


def digest(*texts: str) -> Column:
    """Sixteen bytes that stand for texts where these would be shuffled."""
    ahead = [F.concat(F.char_length(t).cast("string"), F.lit(":")) for t in texts[:-1]]
    return F.unhex(F.md5(F.concat(*ahead, *map(F.col, texts)).cast("binary")))


def version_key(tag: Column) -> Column:
    """The numbers of a version tag in order, for comparing versions naturally."""
    return F.transform(F.regexp_extract_all(tag, F.lit(r"\d+"), F.lit(0)), lambda x: x.cast("bigint"))


def simhash64(tokens: Column) -> Column:
    """Locality-sensitive 64-bit digest of an array of tokens: the majority of each hash bit."""
    hashes = F.transform(tokens, lambda t: F.xxhash64(t))
    out = F.lit(0).cast("long")

    def set_at(k: int):
        return lambda h: F.bit_get(h, F.lit(k)) == 1

    for k in range(64):
        ones = F.size(F.filter(hashes, set_at(k)))
        out = out.bitwiseOR(F.when(ones * 2 > F.size(hashes), F.lit(1 << k if k < 63 else -(1 << 63)).cast("long")).otherwise(F.lit(0).cast("long")))
    return out


def cosine(a: Column, b: Column) -> Column:
    """Cosine of two arrays in double precision; null where either has no length."""
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)
    norm = F.sqrt(dot(a, a) * dot(b, b))
    return F.when(norm > 0, dot(a, b) / norm)
