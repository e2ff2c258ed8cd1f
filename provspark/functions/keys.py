"""Content keys, normalisation levels, outcome codes, similarity bands and the size law."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from provspark.config import POSSIBLE, SURE, ScaleLaw

LEVELS = ("raw", "space", "plain", "letters")


def normalized(text: Column, level: str) -> Column:
    """raw; single spaces; also lower case without punctuation; ASCII letters and digits alone."""
    if level == "raw":
        return text
    spaced = F.trim(F.regexp_replace(text, r"[ \t\r\n]+", " "))
    if level == "space":
        return spaced
    if level == "plain":
        return F.trim(F.regexp_replace(F.regexp_replace(F.lower(spaced), r"[!-/:-@\[-`{-~]+", ""), r" +", " "))
    if level == "letters":
        return F.regexp_replace(F.lower(text), r"[^a-z0-9]+", "")
    raise ValueError(level)


def content_key(text: Column, level: str = "raw") -> Column:
    """40 hexadecimal characters; null for null."""
    return F.sha1(normalized(text, level).cast("binary"))


def join_key(text: Column, level: str = "raw") -> Column:
    """The same key as 20 bytes, which halves what a shuffle moves."""
    return F.unhex(content_key(text, level))


def outcome_code(base_ok: Column, tuned_ok: Column) -> Column:
    """00 unsolved, 01 learnable, 10 degraded, 11 too easy; null where a side is missing."""
    return F.concat(base_ok.cast("int").cast("string"), tuned_ok.cast("int").cast("string"))


def band(similarity: Column, sure: float = SURE, possible: float = POSSIBLE) -> Column:
    return F.when(similarity >= sure, "high").when(similarity >= possible, "possible").otherwise("none")


def scale_law(law: ScaleLaw, size: Column) -> Column:
    return F.lit(law.a) + F.lit(law.b) * F.log10(size / F.lit(1e9))


def seeded(seed: str, *parts: Column) -> Column:
    """A reproducible order: SHA-1 of the seed and the parts."""
    return F.sha1(F.concat_ws(":", F.lit(seed), *[p.cast("string") for p in parts]).cast("binary"))
