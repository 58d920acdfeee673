"""Text functions as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def normalize_answer(text: Column) -> Column:
    """Lower case, letters and digits only, single spaces."""
    return F.trim(F.regexp_replace(F.lower(text), r"[^\p{L}\p{N}]+", " "))


def word_list(text: Column) -> Column:
    return F.filter(F.split(normalize_answer(text), " "), lambda w: w != "")


def word_shingles(text: Column, n: int) -> Column:
    """Distinct runs of n words. The word list is bound once, so that it isn't worked out again for each run."""
    runs = lambda w: F.when(
        F.size(w) >= n, F.array_distinct(F.transform(F.sequence(F.lit(0), F.size(w) - n), lambda i: F.array_join(F.slice(w, i + 1, n), " ")))
    ).otherwise(F.array().cast("array<string>"))
    return F.element_at(F.transform(F.array(word_list(text)), runs), 1)


def token_f1(answer: Column, reference: Column) -> Column:
    """Harmonic mean of precision and recall over distinct words, 0 to 100."""
    a, b = F.array_distinct(word_list(answer)), F.array_distinct(word_list(reference))
    both = F.size(F.array_intersect(a, b)).cast("double")
    return F.when(F.size(a) + F.size(b) > 0, 200.0 * both / (F.size(a) + F.size(b))).otherwise(0.0)


def parse_choice(raw: Column) -> Column:
    """The option letter that an answer starts with or states in brackets."""
    return F.upper(F.regexp_extract(raw, r"^\s*\(?([A-Da-d])\)?(?:[\s.:)]|$)", 1))


def parse_yes_no(raw: Column) -> Column:
    return F.lower(F.regexp_extract(raw, r"(?i)\b(yes|no)\b", 1))


def cosine(a: Column, b: Column) -> Column:
    """Cosine in double precision."""
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)
    return dot(a, b) / (F.sqrt(dot(a, a)) * F.sqrt(dot(b, b)))


def boxes_overlap(ax: Column, ay: Column, aw: Column, ah: Column, bx: Column, by: Column, bw: Column, bh: Column) -> Column:
    """Strict: a shared edge isn't an overlap."""
    return (ax < bx + bw) & (bx < ax + aw) & (ay < by + bh) & (by < ay + ah)
