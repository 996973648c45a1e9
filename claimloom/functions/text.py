"""Canonical keys, wiki markup, tokens and n-grams as column expressions."""

import unicodedata

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

TOKEN = r"[\p{L}\p{N}_]+"


def canonical(surface: str | None) -> str | None:
    """Compatibility form, case folded, letters, marks and digits only; null if nothing is left."""
    if surface is None:
        return None
    folded = unicodedata.normalize("NFKC", unicodedata.normalize("NFKC", surface).casefold())
    return "".join(c for c in folded if c.isalnum() or unicodedata.category(c)[0] == "M") or None


def _canonical_all(surface: pd.Series) -> pd.Series:
    return surface.map(canonical)


def canon_key(surface: Column) -> Column:
    """The key of a surface form; ASCII rows stay in the JVM."""
    plain = F.lower(F.regexp_replace(surface, "[^A-Za-z0-9]", ""))
    return F.when(surface.rlike(r"^[\x00-\x7F]*$"), F.nullif(plain, F.lit(""))).otherwise(F.pandas_udf(_canonical_all, "string")(surface))


def ascii_key(surface: Column) -> Column:
    """The key where compatibility forms do not matter: JVM only."""
    return F.nullif(F.lower(F.regexp_replace(surface, r"[^\p{L}\p{M}\p{N}]", "")), F.lit(""))


_LINK = r"\[\[([^\[\]]+)\]\]"
_SPACES = r"^(?i)\s*(category|file|image|template|help)\s*:"


def links(wikitext: Column) -> Column:
    """Array of (position, target, display, confidence) of the links; namespace links are no subjects."""
    inner = F.filter(F.regexp_extract_all(wikitext, F.lit(_LINK), F.lit(1)), lambda x: ~x.rlike(_SPACES))

    def one(x: Column, i: Column) -> Column:
        before, score = F.split(x, r"\|")[0], F.regexp_extract(F.split(x, r"\|")[0], r"\((0?\.\d+|1\.0+|0\.\d+)\)\s*$", 1)
        target = F.trim(F.when(score != "", F.regexp_replace(before, r"\s*\([^()]*\)\s*$", "")).otherwise(before))
        shown = F.when(F.instr(x, "|") > 0, F.trim(F.regexp_replace(x, r"^[^|]*\|", ""))).otherwise(target)
        return F.struct(i.alias("position"), target.alias("target"), shown.alias("display"), F.nullif(score, F.lit("")).cast("double").alias("confidence"))

    return F.transform(inner, one)


def headings(wikitext: Column) -> Column:
    return F.regexp_extract_all(wikitext, F.lit(r"(?m)^==+\s*([^=\n]+?)\s*==+\s*$"), F.lit(1))


def plain(wikitext: Column) -> Column:
    """Links unwrapped, templates (two levels), tags, headings' marks and quotes dropped, blanks squeezed."""
    x = F.regexp_replace(wikitext, r"\{\{[^{}]*\}\}", "")
    x = F.regexp_replace(x, r"\{\{[^{}]*\}\}", "")
    x = F.regexp_replace(x, r"(?i)\[\[\s*(category|file|image)\s*:[^\]]*\]\]", "")
    x = F.regexp_replace(x, r"\[\[(?:[^\[\]|]*\|)?([^\[\]]*)\]\]", "$1")
    x = F.regexp_replace(x, r"<[^>]*>|'{2,}|==+", " ")
    return F.trim(F.regexp_replace(x, r"\s+", " "))


def tokens(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit(f"({TOKEN})"), F.lit(1))


def ngrams(words: Column, n: int) -> Column:
    """Distinct n-grams joined by a blank; null for shorter texts."""
    at = F.sequence(F.lit(1), F.greatest(F.size(words) - (n - 1), F.lit(1)))
    return F.when(F.size(words) >= n, F.array_distinct(F.transform(at, lambda i: F.array_join(F.slice(words, i, n), " "))))


def jaccard(a: Column, b: Column) -> Column:
    return F.size(F.array_intersect(a, b)) / F.nullif(F.size(F.array_union(a, b)), F.lit(0))


def containment(a: Column, b: Column) -> Column:
    """Share of a's elements that b has."""
    return F.size(F.array_intersect(a, b)) / F.nullif(F.size(a), F.lit(0))


def cosine(a: Column, b: Column) -> Column:
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q), F.lit(0.0), lambda s, v: s + v)
    return dot(a, b) / F.nullif(F.sqrt(dot(a, a) * dot(b, b)), F.lit(0.0))
