"""Varied samples themselves: scene and question after a stack of edits, applied one on another in the order given."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from benchvary.operators import edits as E
from benchvary.sources.carriers import CANVAS

IMAGE = ("V1", "V2", "V3")


def apply_spec(items: DataFrame, spec: tuple[str, ...], scenes: DataFrame | None = None, largest: int = 0, edition: int = 0, where: str = "before", keep: tuple[str, ...] = ()) -> DataFrame:
    """(item_id, task, scene, canvas, question, fallbacks) of every item under the edits.

    scene: array<struct<sn,name,x0,y0,w,h>> after the image edits, in order; an added object gets the serial 0. An edit
    without an accepted attempt leaves its input. Text edits shape one question: words, then the sentence, then its
    context. scenes(scene_id, objs) and largest serve L4. Items keep their number and ids. keep: the items' columns to pass on.
    """
    if unknown := set(spec) - {*IMAGE, "L1", "L2", "L3", "L4"}:
        raise ValueError(f"no such edits: {sorted(unknown)}")
    late = "V1" in spec and "V3" in spec and spec.index("V3") < spec.index("V1")
    side = round(CANVAS * E.RATIO)
    out = E.with_persona(E.swapped_name(E.remove_object(E.add_object(items, edition=edition, canvas=side if late else CANVAS))))
    plain = F.transform("objs", lambda o: F.struct(o["sn"].alias("sn"), o["name"].alias("name"), o["x0"].alias("x0"), o["y0"].alias("y0"), o["w"].alias("w"), o["h"].alias("h")))
    out = out.withColumns({"scene": plain, "canvas": F.lit(CANVAS), "fallbacks": F.lit(0)})
    for edit in (e for e in spec if e in IMAGE):
        if edit == "V1":
            new = F.array(F.struct(F.lit(0).alias("sn"), F.col("v1_name").alias("name"), F.col("v1_x").alias("x0"), F.col("v1_y").alias("y0"), F.lit(E.ADDED).alias("w"), F.lit(E.ADDED).alias("h")))
            out = out.withColumns({"scene": F.when(F.col("v1_fallback") == 0, F.concat("scene", new)).otherwise(F.col("scene")), "fallbacks": F.col("fallbacks") + F.col("v1_fallback")})
        elif edit == "V2":
            out = out.withColumns({"scene": F.filter("scene", lambda o: F.col("v2_sn").isNull() | (o["sn"] != F.col("v2_sn"))), "fallbacks": F.col("fallbacks") + F.col("v2_fallback")})
        else:
            shift = (side - CANVAS) // 2
            moved = F.transform("scene", lambda o: F.struct(o["sn"].alias("sn"), o["name"].alias("name"), (o["x0"] + shift).alias("x0"), (o["y0"] + shift).alias("y0"), o["w"].alias("w"), o["h"].alias("h")))
            out = out.withColumns({"scene": moved, "canvas": F.lit(side)})
    for edit, col in (("L1", "l1_fallback"), ("L2", "l2_fallback")):
        if edit in spec:
            out = out.withColumn("fallbacks", F.col("fallbacks") + F.col(col))
    out = E.question_text(out, "L1" in spec, "L2" in spec, "L3" in spec, None, where).select(*dict.fromkeys(("item_id", "scene_id", "task", "name", "scene", "canvas", "question", "fallbacks", *keep)))
    if "L4" in spec:
        out = E.with_noise(out, scenes, largest).withColumns({"question": E.in_context(F.col("question"), F.col("noise"), where), "fallbacks": F.col("fallbacks") + F.col("l4_fallback")})
    return out.select("item_id", "scene_id", "task", "scene", "canvas", "question", "fallbacks", *keep)
