"""Arithmetic hashes that SQL engines can repeat exactly, and text, URL and time helpers."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: A prime below 2^31: hashes are products of numbers below it, so they never leave 64 bits.
PRIME = 2_147_483_647


def slot(node: Column, round_no: int, slots: int, seed: int | Column = 0) -> Column:
    """The sub-round in which a node moves; a new one each round. The square keeps any two nodes from always sharing one."""
    mixed = F.pmod(node % PRIME * 48271 + (seed * 69621 + round_no * 16807) % PRIME, F.lit(PRIME))
    return F.pmod(mixed * mixed % PRIME, F.lit(slots))


def label_hash(label: Column, seed: int | Column = 0) -> Column:
    """A seeded one-to-one image of labels below the prime (others wrap)."""
    return F.pmod((label % PRIME + seed) * 48271, F.lit(PRIME))


def tokens(text: Column) -> Column:
    return F.filter(F.split(F.lower(F.trim(text)), r"\s+"), lambda x: x != "")


def shingles(text: Column, n: int = 5, most_words: int | None = None) -> Column:
    """Distinct md5 fingerprints of runs of n words."""
    words = tokens(text) if most_words is None else F.slice(tokens(text), 1, most_words)
    return F.transform(F.array(words), lambda w: F.when(F.size(w) >= n, F.array_distinct(F.transform(F.sequence(F.lit(1), F.size(w) - (n - 1)), lambda i: F.md5(F.array_join(F.slice(w, i, n), " "))))).otherwise(F.array().cast("array<string>")))[0]


def hrefs(html: Column) -> Column:
    return F.regexp_extract_all(html, F.lit('href="([^"]*)"'), F.lit(1))


def host(url: Column) -> Column:
    return F.regexp_extract(url, "^[a-z]+://([^/?#]*)", 1)


def prop(props: Column, name: str) -> Column:
    return F.get_json_object(props, f"$.{name}")


def mul33(values: Column) -> Column:
    """The multiply-by-33 string hash over an array of numbers, modulo 2^32 at each step."""
    return F.aggregate(values, F.lit(5381).cast("long"), lambda h, x: F.pmod(h * 33 + x % 4294967296, F.lit(4294967296)))


def cosine(a: Column, b: Column) -> Column:
    dot = F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y), F.lit(0.0), lambda s, x: s + x)
    norm = lambda c: F.sqrt(F.aggregate(c, F.lit(0.0), lambda s, x: s + x.cast("double") * x))
    return dot / (norm(a) * norm(b))
