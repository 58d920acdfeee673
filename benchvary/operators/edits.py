"""Image and question edits: pure functions of (item, attempt), so a repeated task gives the same sample.

V1 adds an object (hard), V2 removes one (easy), V3 expands the canvas (hard); L1 swaps words (hard), L2 rephrases for
a persona (hard), L3 adds relevant context (easy), L4 irrelevant context (hard). Each proposal of an edit passes the
judge's rule for it (judge.py) or the next attempt is made; after the last one the original stays.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from benchvary.functions.hashing import stable_bucket, stable_buckets
from benchvary.functions.text import boxes_overlap
from benchvary.session import materialize
from benchvary.sources.carriers import CANVAS

ATTEMPTS = 5
ADDED = 150
RATIO = 1.5
# The two synonyms of each word that object names consist of.
LEXICON = {
    "large": ("big", "huge"), "small": ("little", "tiny"), "red": ("crimson", "scarlet"), "blue": ("azure", "navy"),
    "hot": ("heated", "scorching"), "cold": ("chilly", "icy"), "old": ("aged", "worn"), "new": ("fresh", "recent"),
    "ring": ("hoop", "band"), "bolt": ("screw", "pin"), "plate": ("disc", "sheet"), "gear": ("cog", "sprocket"),
    "widget": ("gadget", "device"), "rod": ("bar", "pole"), "anvil": ("block", "stithy"), "gizmo": ("contraption", "thingamajig"),
}
PERSONAS = ("casual", "researcher", "child", "educated adult")
# Question forms by task.
QUESTIONS = {
    "presence": "Is there a {name} in the picture?", "count": "How many objects called {name} are there?", "attribute": "Which brand does the {name} have?",
    "spatial": "Where is the {name} relative to the next object?", "interaction": "Does the {name} touch the next object?", "text": "Which word is on the label of the {name}?",
}
REPHRASED = {
    "casual": "Hey, quick one about the {name}: ", "researcher": "With regard to the instance denoted {name}, determine: ", "child": "Can you tell me about the {name}, please: ", "educated adult": "Considering the {name} shown here: ",
}
STRATEGIES = (("V1", "image", "hard"), ("V2", "image", "easy"), ("V3", "image", "hard"), ("L1", "word", "hard"), ("L2", "sentence", "hard"), ("L3", "context", "easy"), ("L4", "context", "hard"))


def strategy_table(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(STRATEGIES), "strategy string, level string, difficulty string")


def _relevant(o: Column) -> Column:
    return F.array_contains("rel", o["sn"])


def propose_additions(items: DataFrame, attempts: int = ATTEMPTS, size: int = ADDED, edition: int = 0, canvas: int = CANVAS, first: int = 1) -> DataFrame:
    """tries: name (an adjective and a noun by hash) and box of each attempt, with the judge's verdict: not the asked name, and no relevant object covered.

    canvas: side of the scene, in the middle of which the original one stands; first: the attempt that tries begins with.
    """
    salt, words = f"v1e{edition}", list(LEXICON)
    half = len(words) // 2
    side, shift = F.lit(size), F.lit((canvas - CANVAS) // 2)
    given = F.array(*[F.lit(w) for w in words])
    parts = {f"{salt}|x": canvas - size, f"{salt}|y": canvas - size, f"{salt}|a": half, f"{salt}|n": half}
    drawn = lambda part, k: F.get("_drawn", F.lit(part * (attempts + 1 - first) + k - first)).cast("int")
    boxes = F.transform(F.filter("objs", _relevant), lambda o: F.struct((o["x0"] + shift).alias("x0"), (o["y0"] + shift).alias("y0"), o["w"].alias("w"), o["h"].alias("h")))

    def attempt(k: int) -> Column:
        x, y = drawn(0, k), drawn(1, k)
        name = F.concat_ws(" ", F.get(given, drawn(2, k)), F.get(given, half + drawn(3, k)))
        hidden = F.exists("_boxes", lambda o: boxes_overlap(o["x0"], o["y0"], o["w"], o["h"], x, y, side, side))
        return F.struct(F.lit(k).alias("k"), x.alias("x"), y.alias("y"), name.alias("name"), (~hidden & (name != F.col("name"))).alias("ok"))

    out = items.withColumns({"_drawn": stable_buckets(F.col("item_id"), parts, attempts, first), "_boxes": boxes})
    return out.withColumn("tries", F.array(*[attempt(k) for k in range(first, attempts + 1)])).drop("_drawn", "_boxes")


def add_object(items: DataFrame, attempts: int = ATTEMPTS, size: int = ADDED, edition: int = 0, canvas: int = CANVAS) -> DataFrame:
    """First accepted addition: v1_attempt, v1_x, v1_y, v1_name; v1_fallback where all attempts fail, and the original stays."""
    first = F.try_element_at(F.filter("tries", lambda t: t["ok"]), F.lit(1))
    return propose_additions(items, attempts, size, edition, canvas).withColumn("_f", first).withColumns(
        {"v1_attempt": F.coalesce(F.col("_f.k"), F.lit(attempts)), "v1_x": F.col("_f.x"), "v1_y": F.col("_f.y"), "v1_name": F.col("_f.name"), "v1_fallback": F.col("_f").isNull().cast("int")}
    ).drop("_f")


def may_go(o: Column) -> Column:
    """The judge's rule for a removal: neither relevant, nor named like the asked one, nor overlapping a relevant box."""
    return ~_relevant(o) & (o["name"] != F.col("name")) & ~F.exists("objs", lambda r: _relevant(r) & boxes_overlap(o["x0"], o["y0"], o["w"], o["h"], r["x0"], r["y0"], r["w"], r["h"]))


def removable(items: DataFrame) -> DataFrame:
    """can_go: objects that the judge lets go."""
    return items.withColumn("can_go", F.filter("objs", may_go))


def remove_object(items: DataFrame, attempts: int = ATTEMPTS) -> DataFrame:
    """Attempt k removes the k-th largest object; the first that may go is gone: v2_sn, v2_rank; v2_fallback where none is."""
    best = F.array_min(F.transform(F.filter("can_go", lambda o: o["rk"] <= attempts), lambda o: F.struct(o["rk"].alias("rk"), o["sn"].alias("sn"))))
    return removable(items).withColumn("_b", best).withColumns({"v2_sn": F.col("_b.sn"), "v2_rank": F.col("_b.rk"), "v2_fallback": F.col("_b").isNull().cast("int")}).drop("_b", "can_go")


def canvas_side(ratio: Column | float, ratio_on: str = "side") -> Column:
    """Side of the expanded canvas; ratio_on: the ratio is meant of the side or of the area."""
    r = F.lit(ratio) if isinstance(ratio, float) else ratio
    return F.round(CANVAS * (r if ratio_on == "side" else F.sqrt(r))).cast("int")


def expand_scene(objects: DataFrame, ratio: float = RATIO, ratio_on: str = "side") -> DataFrame:
    """Objects moved so that they keep the middle of the larger canvas; sizes and offsets stay."""
    side = canvas_side(ratio, ratio_on)
    shift = F.floor((side - CANVAS) / 2).cast("int")
    return objects.withColumns({"x0": F.col("x0") + shift, "y0": F.col("y0") + shift, "canvas": side})


def synonym(word: Column, salt: Column) -> Column:
    """A synonym of the word by hash, or the word."""
    table = F.create_map(*[x for w, s in LEXICON.items() for x in (F.lit(w), F.array(*[F.lit(v) for v in s]))])
    return F.coalesce(F.element_at(F.try_element_at(table, word), (1 + stable_bucket(2, "syn", salt, word)).cast("int")), word)


#: One in so many proposals of L1 takes a word of another meaning, and of L2 leaves the asked name out; the judge rejects both.
DRIFT, PRONOUN = 10, 8


def drifts(k: Column) -> Column:
    return stable_bucket(DRIFT, "drift", F.col("item_id"), k) == 0


def omits_name(k: Column) -> Column:
    return stable_bucket(PRONOUN, "pronoun", F.col("item_id"), k) == 0


def _all_fail(bad, attempts: int) -> Column:
    return F.forall(F.sequence(F.lit(1), F.lit(attempts)), bad).cast("int")


def swapped_name(items: DataFrame, attempts: int = ATTEMPTS) -> DataFrame:
    """swap1, swap2: what the two words of the asked name become under L1; the words themselves where every attempt fails (l1_fallback)."""
    out = items.withColumn("l1_fallback", _all_fail(drifts, attempts))
    word = lambda k: F.split_part("name", F.lit(" "), F.lit(k))
    return out.withColumns({f"swap{k}": F.when(F.col("l1_fallback") == 1, word(k)).otherwise(synonym(word(k), F.col("item_id"))) for k in (1, 2)})


def with_persona(items: DataFrame, attempts: int = ATTEMPTS) -> DataFrame:
    """persona, and l2_fallback where every attempt leaves the asked name out."""
    pick = F.element_at(F.array(*[F.lit(p) for p in PERSONAS]), (1 + stable_bucket(len(PERSONAS), "persona", F.col("item_id"))).cast("int"))
    return items.withColumns({"persona": pick, "l2_fallback": _all_fail(omits_name, attempts)})


def tells_nothing(o: Column) -> Column:
    """The judge's rule for a hint: about neither a relevant object nor one with the asked name."""
    return ~_relevant(o) & (o["name"] != F.col("name"))


def hints(items: DataFrame, most: int = 2, attempts: int = ATTEMPTS) -> Column:
    """Attempt k proposes the k-th object as a hint; the first accepted ones stay."""
    return F.slice(F.filter("objs", lambda o: (o["sn"] <= attempts) & tells_nothing(o)), 1, most)


def with_facts(items: DataFrame, most: int = 2) -> DataFrame:
    """facts: how many hints the question gets under L3."""
    return items.withColumn("facts", F.size(hints(items, most)))


def describe(objs: Column) -> Column:
    """A scene in words."""
    return F.concat(F.lit("The picture shows "), F.array_join(F.transform(objs, lambda o: F.concat(F.lit("a "), o["name"])), ", "), F.lit("."))


def in_context(question: Column, context: Column, where: str = "before") -> Column:
    """The question with a context before or after it; without a context, itself."""
    both = F.concat_ws(" ", context, question) if where == "before" else F.concat_ws(" ", question, context)
    return F.when(F.length(F.coalesce(context, F.lit(""))) > 0, both).otherwise(question)


def question_text(items: DataFrame, l1: bool = False, l2: bool = False, l3: bool = False, noise: str | None = None, where: str = "before") -> DataFrame:
    """question: the item's question under the edits; noise: a column with the context of L4."""
    name = F.concat_ws(" ", "swap1", "swap2") if l1 else F.col("name")
    forms = F.create_map(*[x for t, q in QUESTIONS.items() for x in (F.lit(t), F.lit(q))])
    text = F.replace(F.element_at(forms, F.col("task")), F.lit("{name}"), name)
    if l2:
        lead = F.create_map(*[x for p, q in REPHRASED.items() for x in (F.lit(p), F.lit(q))])
        text = F.when(F.col("l2_fallback") == 1, text).otherwise(F.concat(F.replace(F.element_at(lead, F.col("persona")), F.lit("{name}"), name), F.lower(text)))
    if l3:
        hint = hints(items)
        text = in_context(text, F.when(F.size(hint) > 0, describe(hint)), where)
    if noise:
        text = in_context(text, F.col(noise), where)
    return items.withColumn("question", text)


def with_noise(items: DataFrame, scenes: DataFrame, largest: int, attempts: int = ATTEMPTS) -> DataFrame:
    """noise: the description of another scene, for L4; null where every attempt fails (l4_fallback); l4_attempt.

    Attempt k draws a scene by hash from 1 to largest. The judge rejects one that doesn't exist, is the item's own, or
    names what is asked for. scenes: (scene_id, objs). The rows travel to the scenes as they are, so let them be narrow.
    """
    found = accepted_noise(items, scenes, largest, attempts)
    return found.select(*items.columns, describe(F.col("_others")).alias("noise"), F.when(F.col("_k") > 0, F.col("_k")).otherwise(attempts).alias("l4_attempt"), (F.col("_k") == 0).cast("int").alias("l4_fallback"))


def _pool(scenes: DataFrame) -> DataFrame:
    """Scenes as those who draw them need them: the names, in the objects' order."""
    names = F.transform(F.array_sort(F.transform("objs", lambda o: F.struct(o["sn"].alias("sn"), o["name"].alias("name")))), lambda o: F.struct(o["name"].alias("name")))
    return scenes.select(F.col("scene_id").alias("_other"), names.alias("_others"))


def suits() -> Column:
    """The judge's rule for a scene drawn as irrelevant context."""
    return F.col("_others").isNotNull() & (F.col("_other") != F.col("scene_id")) & ~F.coalesce(F.exists("_others", lambda o: o["name"] == F.col("name")), F.lit(True))


def draw_noise(items: DataFrame, pool: DataFrame, largest: int, k: int) -> DataFrame:
    """The items with the scene that attempt k draws: _other and its names, _others."""
    one = F.get(stable_buckets(F.col("item_id"), {"noise": max(largest, 1)}, k, k), F.lit(0))
    return items.withColumn("_other", 1 + one).join(pool, "_other", "left")


def accepted_noise(items: DataFrame, scenes: DataFrame, largest: int, attempts: int = ATTEMPTS, names: bool = True) -> DataFrame:
    """(the items' columns, _k, _others): the first accepted attempt of L4 and its scene's names; _k is 0 where every attempt fails.

    A round for each attempt over what is still open, as in judge.rounds; each is written to the session's shared folder.
    """
    pool, columns = _pool(scenes), items.columns
    kind = dict(pool.dtypes)["_others"]
    left, done = items, None
    for k in range(1, attempts + 1):
        shown = F.when(F.col("_ok"), F.col("_others")) if names else F.lit(None).cast(kind)
        said = materialize(draw_noise(left, pool, largest, k).withColumn("_ok", suits()).select(*columns, "_ok", shown.alias("_others")), f"noise-{k}")
        good = said.where("_ok").select(*columns, F.lit(k).alias("_k"), "_others")
        done = good if done is None else done.unionByName(good)
        left = said.where("not _ok").select(*columns)
    return done.unionByName(left.select(*columns, F.lit(0).alias("_k"), F.lit(None).cast(kind).alias("_others")))


def propose_noise(items: DataFrame, scenes: DataFrame, largest: int, attempts: int = ATTEMPTS) -> DataFrame:
    """(the items' columns, k, ok): the judge's verdict on the scene that each attempt draws."""
    drawn = items.withColumn("_drawn", stable_buckets(F.col("item_id"), {"noise": max(largest, 1)}, attempts))
    drawn = drawn.select(*items.columns, F.posexplode("_drawn").alias("k", "_other")).withColumns({"k": F.col("k") + 1, "_other": F.col("_other") + 1})
    return drawn.join(_pool(scenes), "_other", "left").select(*items.columns, "k", suits().alias("ok"))


def edited(items: DataFrame, edition: int = 0) -> DataFrame:
    """Items with all seven edits worked out once; compositions only combine the columns."""
    out = with_facts(with_persona(swapped_name(remove_object(add_object(items, edition=edition)))))
    return out.drop("objs", "tries", "rel")


def page_without_clutter(html: Column) -> Column:
    """A page without navigation and advertisement blocks (easy)."""
    return F.regexp_replace(F.regexp_replace(html, r"(?s)<nav>.*?</nav>", ""), r"(?s)<div class=\"ad\">.*?</div>", "")


def page_with_clutter(html: Column) -> Column:
    """A page with one more advertisement block in front of its body's end (hard)."""
    return F.replace(html, F.lit("</body>"), F.lit('<div class="ad">ad</div></body>'))
