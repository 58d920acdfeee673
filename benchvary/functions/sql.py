"""SQL functions and table functions for use in spark.sql."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

_DOT = "aggregate(zip_with({0}, {1}, (p, q) -> cast(p as double) * cast(q as double)), 0D, (s, v) -> s + v)"
_PLAIN = r"trim(regexp_replace(lower(s), '[^\\p{L}\\p{N}]+', ' '))"
FUNCTIONS = {
    "box_overlap": ("a struct<x0:int,y0:int,w:int,h:int>, b struct<x0:int,y0:int,w:int,h:int>", "boolean", "a.x0 < b.x0 + b.w and b.x0 < a.x0 + a.w and a.y0 < b.y0 + b.h and b.y0 < a.y0 + a.h"),
    "cosine": ("a array<double>, b array<double>", "double", f"{_DOT.format('a', 'b')} / (sqrt({_DOT.format('a', 'a')}) * sqrt({_DOT.format('b', 'b')}))"),
    "plain_answer": ("s string", "string", _PLAIN),
}


@udtf(returnType="variant_id string, image string, question string, n_hard int")
class VariantSpecs:
    """variant_specs(max_image, max_text): every composition of at most so many edits on each side."""

    def eval(self, max_image: int, max_text: int):
        from benchvary.plans.compose import HARD, IMAGE, TEXT, all_compositions

        for spec in all_compositions(max_image, max_text):
            edits = [] if spec[0] == "vanilla" else spec[0].split("+")
            yield spec[0], "+".join(e for e in edits if e in IMAGE), "+".join(e for e in edits if e in TEXT), sum(e in HARD for e in edits)


@udtf(returnType="place int, shingle string")
class Shingles:
    """shingles(text, n): runs of n words of the plain text."""

    def eval(self, text: str, n: int):
        words = "".join(c if c.isalnum() else " " for c in (text or "").lower()).split()
        for k in range(len(words) - n + 1):
            yield k, " ".join(words[k : k + n])


def register(spark: SparkSession) -> None:
    """Make the functions known to spark.sql."""
    for name, (args, kind, body) in FUNCTIONS.items():
        spark.sql(f"create or replace temporary function {name}({args}) returns {kind} return {body}")
    spark.udtf.register("variant_specs", VariantSpecs)
    spark.udtf.register("shingles", Shingles)
