"""The judge: one rule for each edit, attempts, composite verdicts, and generation with bounded regeneration.

A proposal is an edit of an item at an attempt; the judge knows which edit was made and says whether the item's answer
still holds. The scenes are exact, so the rules are exact too. An edit whose attempts all fail leaves the original.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from benchvary.functions.hashing import stable_buckets
from benchvary.functions.text import boxes_overlap
from benchvary.operators import edits as E
from benchvary.session import materialize
from benchvary.sources.carriers import CANVAS


def _boxes_stay() -> Column:
    """V3: on the larger canvas every box lies inside. All boxes move by the same, so the order of their middles stays."""
    side = E.canvas_side(E.RATIO)
    shift = F.floor((side - CANVAS) / 2)
    return F.forall("objs", lambda o: (o["x0"] + shift >= 0) & (o["y0"] + shift >= 0) & (o["x0"] + o["w"] + shift <= side) & (o["y0"] + o["h"] + shift <= side))


#: Edits whose proposals the scene and the question alone decide. L4's need the scene that it draws (edits.propose_noise).
ALONE = ("V1", "V2", "V3", "L1", "L2", "L3")


def verdicts(items: DataFrame, attempts: int = E.ATTEMPTS) -> DataFrame:
    """said: array<struct<strategy,k,ok>>, the proposals of each edit but L4 with the judge's verdict, in the item's row.

    V2 proposes the k-th largest object and L3 the k-th, as far as there are so many; V3 has one proposal.
    """
    one = lambda name, k, ok: F.struct(F.lit(name).alias("strategy"), k.cast("int").alias("k"), ok.alias("ok"))
    numbers = range(1, attempts + 1)
    out = E.propose_additions(items, attempts).withColumn("_luck", stable_buckets(F.col("item_id"), {"drift": E.DRIFT, "pronoun": E.PRONOUN}, attempts))
    luck = lambda part, k: F.get("_luck", F.lit(part * attempts + k - 1)) != 0
    rows = [
        F.array(*[one("V1", F.lit(k), F.element_at("tries", k)["ok"]) for k in numbers], one("V3", F.lit(1), _boxes_stay())),
        F.array(*[one("L1", F.lit(k), luck(0, k)) for k in numbers], *[one("L2", F.lit(k), luck(1, k)) for k in numbers]),
        F.transform(F.filter("objs", lambda o: o["rk"] <= attempts), lambda o: one("V2", o["rk"], E.may_go(o))),
        F.transform(F.slice("objs", 1, attempts), lambda o, i: one("L3", i + 1, E.tells_nothing(o))),
    ]
    return out.withColumn("said", F.concat(*rows)).drop("tries", "_luck")


def proposals(items: DataFrame, noise: DataFrame | None = None, attempts: int = E.ATTEMPTS) -> DataFrame:
    """(item_id, task, strategy, k, ok) of every proposal of every edit; noise: what edits.propose_noise gives for these items, for L4."""
    out = verdicts(items, attempts).select("item_id", "task", F.explode("said").alias("p")).select("item_id", "task", "p.*")
    if noise is not None:
        out = out.unionByName(noise.select("item_id", "task", F.lit("L4").alias("strategy"), "k", "ok"))
    return out


def first_accepted(items: DataFrame, scenes: DataFrame, largest: int, attempts: int = E.ATTEMPTS) -> DataFrame:
    """(item_id, task, strategy, attempt, fallback) for all seven edits: generate_with_judge without a shuffle of proposals.

    The first accepted attempt is found in the item's row, L4's by rounds over what is still open.
    """
    fits = lambda name: F.filter("said", lambda p: p["strategy"] == name)
    first = lambda name: F.array_min(F.transform(F.filter(fits(name), lambda p: p["ok"]), lambda p: p["k"]))
    one = lambda name: F.when(F.size(fits(name)) > 0, F.struct(F.lit(name).alias("strategy"), first(name).alias("first")))
    rows = verdicts(items, attempts).select("item_id", "task", F.explode(F.filter(F.array(*[one(n) for n in ALONE]), lambda x: x.isNotNull())).alias("p")).select("item_id", "task", "p.*")
    noise = E.accepted_noise(items.select("item_id", "task", "scene_id", "name"), scenes, largest, attempts, names=False)
    rows = rows.unionByName(noise.select("item_id", "task", F.lit("L4").alias("strategy"), F.when(F.col("_k") > 0, F.col("_k")).alias("first")))
    return rows.select("item_id", "task", "strategy", F.coalesce("first", F.lit(attempts)).alias("attempt"), F.col("first").isNull().cast("int").alias("fallback"))


def generate_with_judge(proposals: DataFrame, attempts: int = E.ATTEMPTS) -> DataFrame:
    """(item_id, task, strategy, attempt, fallback): the first accepted attempt of each edit, else the original after the last."""
    first = F.min(F.when(F.col("ok"), F.col("k")))
    return proposals.groupBy("item_id", "task", "strategy").agg(first.alias("first")).select("item_id", "task", "strategy", F.coalesce("first", F.lit(attempts)).alias("attempt"), F.col("first").isNull().cast("int").alias("fallback"))


def rounds(items: DataFrame, propose: Callable[[DataFrame, int], DataFrame], attempts: int = E.ATTEMPTS) -> DataFrame:
    """(item_id, attempt, fallback): regeneration for costly generators, one pass over what is still open in each round.

    propose(open items, k) gives the open items' rows with a column ok. Each round is written, so a generator is called
    once for each proposal, and what is still open is read from there.
    """
    left, done = items, None
    for k in range(1, attempts + 1):
        said = materialize(propose(left, k).select(*items.columns, "ok"), f"round-{k}")
        good = said.where("ok").select("item_id", F.lit(k).alias("attempt"), F.lit(0).alias("fallback"))
        done = good if done is None else done.unionByName(good)
        left = said.where("not ok").select(*items.columns)
    return done.unionByName(left.select("item_id", F.lit(attempts).alias("attempt"), F.lit(1).alias("fallback")))


def composite(items: DataFrame, scenes: DataFrame, largest: int, pairs: list[tuple[str, str]], attempts: int = E.ATTEMPTS) -> DataFrame:
    """(pair, mode, n, accepted, calls) of edits on both sides of a sample.

    joint: one check knows both edits, so an attempt counts only if both proposals hold (adversarial: a sample is broken
    unless it passes all rules). each: both sides are accepted on their own. Attempts that both edits propose count, and
    items with such ones. Verdicts are bits of a number for each edit, attempt k at bit k - 1. L4's are asked for by
    rounds, only for items where a further one can change a pair's result.
    """
    power = lambda k: F.call_function("shiftleft", F.lit(1), k - 1)
    bits = lambda name, good: F.aggregate(F.filter("said", lambda p: (p["strategy"] == name) & (p["ok"] if good else F.lit(True))), F.lit(0), lambda s, p: s.bitwiseOR(power(p["k"])))
    lowest = lambda x: F.when(x > 0, F.log2(x.bitwiseAND(-x)).cast("int") + 1)
    sides = sorted({e for p in pairs for e in p} - {"L4"})
    judged = verdicts(items, attempts).select("item_id", "scene_id", "name", *[bits(e, g).alias(f"{e}_{n}") for e in sides for n, g in (("may", False), ("ok", True))])

    def counted(df: DataFrame, some: list[tuple[str, str]]) -> DataFrame:
        rows = []
        for a, b in some:
            both = F.col(f"{a}_may").bitwiseAND(F.col(f"{b}_may"))
            ok = {e: F.col(f"{e}_ok").bitwiseAND(both) for e in (a, b)}
            fa, fb = lowest(ok[a]), lowest(ok[b])
            for mode, k in (("joint", lowest(ok[a].bitwiseAND(ok[b]))), ("each", F.when(fa.isNotNull() & fb.isNotNull(), F.greatest(fa, fb)))):
                rows.append(F.when(both > 0, F.struct(F.lit(f"{a}+{b}").alias("pair"), F.lit(mode).alias("mode"), k.alias("k"))))
        out = df.select(F.explode(F.filter(F.array(*rows), lambda x: x.isNotNull())).alias("m"))
        return out.groupBy("m.pair", "m.mode").agg(F.count("*").alias("n"), F.count("m.k").alias("accepted"), F.sum(F.coalesce("m.k", F.lit(attempts))).alias("calls"))

    plain, drawing = [p for p in pairs if "L4" not in p], [p for p in pairs if "L4" in p]
    if not drawing:
        return counted(judged, plain)
    partners = [e for p in drawing for e in p if e != "L4"]
    judged = materialize(judged, "judged")  # the counts of the other pairs and the rounds read it
    pool, left, done = E._pool(scenes), judged.select("item_id", "scene_id", "name", *[f"{e}_{n}" for e in partners for n in ("may", "ok")]), None
    columns = left.columns
    left = left.withColumn("L4_ok", F.lit(0))
    for k in range(1, attempts + 1):
        later = F.lit((1 << attempts) - (1 << k))
        lacks = lambda col: (F.col("L4_ok").bitwiseAND(F.col(col)) == 0) & (F.col(col).bitwiseAND(later) > 0)  # noqa: E731, B023
        unsure = F.lit(False)
        for e in partners:
            unsure = unsure | (F.col(f"{e}_ok") > 0) & (lacks(f"{e}_ok") | lacks(f"{e}_may"))
        said = E.draw_noise(left, pool, largest, k).withColumn("L4_ok", F.col("L4_ok").bitwiseOR(F.when(E.suits(), 1 << (k - 1)).otherwise(0)))
        said = materialize(said.select(*columns, "L4_ok", unsure.alias("open")), f"pairs-{k}")
        closed = said.where("not open").drop("open") if k < attempts else said.drop("open")
        done = closed if done is None else done.unionByName(closed)
        left = said.where("open").drop("open")
    out = counted(done.withColumn("L4_may", F.lit((1 << attempts) - 1)), drawing)
    return out.unionByName(counted(judged, plain)) if plain else out


def judged_stack(items: DataFrame, order: tuple[str, ...]) -> DataFrame:
    """An object added before or after the canvas grows: v1_attempt, v1_fallback and its place on the larger canvas (x, y)."""
    side = round(CANVAS * E.RATIO)
    late = order.index("V3") < order.index("V1")
    out = E.add_object(items, canvas=side if late else CANVAS)
    move = F.lit(0 if late else (side - CANVAS) // 2)
    return out.select("item_id", "task", "v1_attempt", "v1_fallback", (F.col("v1_x") + move).alias("x"), (F.col("v1_y") + move).alias("y"))


def covers_relevant(x: Column, y: Column) -> Column:
    """Whether an added box hides a relevant object."""
    side = F.lit(E.ADDED)
    return F.exists("objs", lambda o: F.array_contains("rel", o["sn"]) & boxes_overlap(o["x0"], o["y0"], o["w"], o["h"], x, y, side, side))
