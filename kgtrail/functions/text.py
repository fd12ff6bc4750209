"""Tokens, token cosine and path texts as Column expressions (no UDF)."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def tokens(text: Column) -> Column:
    """Lower-cased runs of [a-z0-9]; empty for null."""
    plain = F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), "[^a-z0-9]+", " ")
    return F.filter(F.split(plain, " "), lambda t: t != "")


def relation_tokens(rels: Column) -> Column:
    return tokens(F.concat_ws(" ", rels))


def token_cosine(a: Column, b: Column) -> Column:
    """Term-frequency cosine of two token arrays, rounded to 6 digits; 0 if either is empty.
    With tf(x) the occurrences of x, a sum of tf over occurrences is a sum of squares."""

    def mass(of: Column, in_: Column) -> Column:
        return F.aggregate(of, F.lit(0), lambda acc, x: acc + F.size(F.filter(in_, lambda y: y == x)))

    norm = F.sqrt(mass(a, a).cast("double")) * F.sqrt(mass(b, b).cast("double"))
    return F.when(norm > 0, F.round(mass(b, a) / norm, 6)).otherwise(F.lit(0.0))


def etype_of(entity: Column) -> Column:
    """The part of an entity id before the colon; only for graphs whose ids carry their type."""
    return F.substring_index(entity, ":", 1)


def path_text(rels: Column, nodes: Column) -> Column:
    """topic -> relation -> node -> ..., with dots in relation names read as spaces."""
    hops = F.zip_with(rels, F.slice(nodes, F.lit(2), F.size(rels)), lambda r, n: F.concat_ws(" -> ", F.translate(r, ".", " "), n))
    return F.concat_ws(" -> ", F.element_at(nodes, 1), F.concat_ws(" -> ", hops))
