"""Keyword queries as normalized text, tokens and phrases."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

TOKEN = r"[\p{L}\p{N}_#]+"
SEED, ENTITY = "<q>", "<e>"


def tokens(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit(TOKEN), F.lit(0))


def normalize(text: Column) -> Column:
    return F.array_join(tokens(text), " ")


def analyzed(text: Column) -> Column:
    """Tokens as the index sees them: normalized, a plural s dropped from words of four letters or more."""
    return F.transform(tokens(text), lambda t: F.when((F.length(t) > 3) & t.endswith("s") & ~t.endswith("ss"), F.substring(t, F.lit(1), F.length(t) - 1)).otherwise(t))


def padded(text: Column) -> Column:
    return F.concat(F.lit(" "), text, F.lit(" "))


def contains_words(text: Column, words: Column) -> Column:
    """Contiguous token containment."""
    return F.contains(padded(text), padded(words))


def phrases(text: Column) -> Column:
    """All contiguous token sub-phrases shorter than the text itself, distinct."""
    toks = F.split(text, " ")
    n = F.size(toks)
    starts = F.sequence(F.lit(1), n)
    made = F.flatten(F.transform(starts, lambda i: F.transform(F.sequence(F.lit(1), n - i + 1), lambda k: F.array_join(F.slice(toks, i, k), " "))))
    return F.array_distinct(F.filter(made, lambda p: p != text))


def residual(candidate: Column, query: Column, entity: Column | None = None) -> Column:
    """Facet key of a candidate, comparable across seeds: the seed, or else its entity, becomes a placeholder."""
    rest = F.trim(F.replace(padded(candidate), padded(query), F.lit(" ")))
    key = F.when(contains_words(candidate, query), F.concat(F.lit(SEED + " "), rest))
    if entity is not None:
        swapped = F.trim(F.replace(padded(candidate), padded(entity), F.lit(f" {ENTITY} ")))
        key = key.when(contains_words(candidate, entity), swapped)
    return key.otherwise(candidate)


def instantiate(facet: Column, query: Column, entity: Column | None = None) -> Column:
    """The query text that poses a facet key for a seed."""
    text = F.replace(facet, F.lit(SEED), query)
    return F.replace(text, F.lit(ENTITY), entity) if entity is not None else text


def label(facet: Column) -> Column:
    """A facet key as shown to users: without the seed's placeholder."""
    return F.trim(F.replace(facet, F.lit(SEED), F.lit("")))
