"""How the given tables carry test samples: scenes, questions, dialogues, vectors and captions.

A scene (an "image") is an order; its objects are the order's lines with their part's name, on a 1000 x 1000 canvas.
Scenes without lines have no questions.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from benchvary.functions.hashing import first_free, stable_bucket, stable_hash
from benchvary.functions.text import boxes_overlap
from benchvary.sources.tables import read_table

CANVAS = 1000
#: Largest box: what a relevant object's area can't exceed; stands for "no object needed".
NO_AREA = 1_000_000


def scene_objects(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row for each object: scene_id, sn, name, brand, type, x0, y0, w, h."""
    line = read_table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_extendedprice", "l_quantity")
    part = read_table(spark, sf_dir, "part").select("p_partkey", "p_name", "p_brand", "p_type", "p_size")
    order = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_quantity")
    obj = line.join(part, F.col("l_partkey") == F.col("p_partkey")).withColumn("sn", F.row_number().over(order))
    w, h = (30 + 3 * F.col("p_size")).cast("int"), (30 + 3 * F.floor("l_quantity")).cast("int")
    obj = obj.select(F.col("l_orderkey").alias("scene_id"), "sn", F.col("p_name").alias("name"), F.col("p_brand").alias("brand"), F.col("p_type").alias("type"), w.alias("w"), h.alias("h"))
    place = lambda axis, size: stable_bucket(CANVAS - F.col(size), axis, F.col("scene_id"), F.col("sn")).cast("int")
    return obj.withColumns({"x0": place("x", "w"), "y0": place("y", "h")})


def object_names(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The distinct object names: a bounded vocabulary (adjective and noun), checked before it is broadcast."""
    return read_table(spark, sf_dir, "part").select(F.col("p_name").alias("name")).distinct()


def absent_names(objects: DataFrame, names: DataFrame, per_scene: int = 1) -> DataFrame:
    """(scene_id, pick, absent): names that a scene lacks, in the scene's own hash order."""
    held = objects.groupBy("scene_id").agg(F.collect_set("name").alias("held"))
    pool = names.agg(F.array_sort(F.collect_set("name")).alias("pool"))
    free = F.transform(F.array_except("pool", "held"), lambda n: F.struct(stable_hash("n", F.col("scene_id"), n).alias("h"), n.alias("n")))
    return held.crossJoin(F.broadcast(pool)).select("scene_id", F.posexplode(F.slice(F.array_sort(free), 1, per_scene)).alias("pick", "s")).select("scene_id", "pick", F.col("s.n").alias("absent"))


def items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Questions with what is needed to answer them.

    item_id, scene_id, task, benchmark, name (asked), answer (index of the right option), n_options, n (objects in the
    scene), rel (serials of the relevant objects), worst_rank and least_area of those, and objs, the scene's objects.
    One shuffle by scene serves ranks, packing and all six question families.
    """
    obj = scene_objects(spark, sf_dir).withColumn("area", F.col("w") * F.col("h"))
    rank = F.row_number().over(Window.partitionBy("scene_id").orderBy(F.desc("area"), "sn"))
    packed = obj.withColumn("rk", rank).groupBy("scene_id").agg(F.array_sort(F.collect_list(F.struct("sn", "name", "brand", "x0", "y0", "w", "h", "area", "rk"))).alias("objs"))
    pool = object_names(spark, sf_dir).agg(F.array_sort(F.collect_set("name")).alias("pool"))
    s = packed.crossJoin(F.broadcast(pool)).withColumn("n", F.size("objs"))
    s = s.withColumn("t", (1 + stable_bucket(F.col("n"), "t", F.col("scene_id"))).cast("int")).withColumn("t2", (1 + F.col("t") % F.col("n")).cast("int"))
    s = s.withColumns({"a": F.element_at("objs", F.col("t")), "b": F.element_at("objs", F.col("t2"))})
    there = F.col("there")
    s = s.withColumn("there", stable_bucket(2, "p", F.col("scene_id")) == 0).withColumn("absent", first_free(F.when(~there, F.col("scene_id")), F.transform("objs", lambda o: o["name"]), F.col("pool")))
    same = F.filter("objs", lambda o: o["name"] == F.col("a.name"))
    best = F.array_min(F.transform(same, lambda o: F.struct(o["rk"], o["sn"])))["sn"]
    one = F.size(same) == 1
    two = (F.col("n") >= 2) & (F.col("a.name") != F.col("b.name"))
    touch = boxes_overlap(*(F.col(f"{o}.{k}") for o in "ab" for k in ("x0", "y0", "w", "h")))
    left = 2 * F.col("a.x0") + F.col("a.w") < 2 * F.col("b.x0") + F.col("b.w")
    above = 2 * F.col("a.y0") + F.col("a.h") < 2 * F.col("b.y0") + F.col("b.h")
    ints = lambda *c: F.array(*c).cast("array<int>")
    empty = F.array().cast("array<int>")

    def q(task: str, bench: str, cond, name, answer, n_options: int, rel):
        return F.when(cond, F.struct(F.lit(task).alias("task"), F.lit(bench).alias("benchmark"), name.alias("name"), answer.cast("int").alias("answer"), F.lit(n_options).alias("n_options"), rel.alias("rel")))

    asked = F.array(
        q("presence", "YN", there | F.col("absent").isNotNull(), F.when(there, F.col("a.name")).otherwise(F.col("absent")), F.when(there, 0).otherwise(1), 2, F.when(there, ints(best)).otherwise(empty)),
        q("count", "MC-G", F.lit(True), F.col("a.name"), stable_bucket(4, "o", F.col("scene_id"), F.size(same)), 4, F.transform(same, lambda o: o["sn"])),
        q("attribute", "MC-G", one, F.col("a.name"), stable_bucket(4, "o", F.col("scene_id"), F.col("a.brand")), 4, ints(F.col("a.sn"))),
        q("spatial", "MC-T", two, F.col("a.name"), F.when(left, 0).otherwise(1) + F.when(above, 0).otherwise(2), 4, ints(F.col("a.sn"), F.col("b.sn"))),
        q("interaction", "MC-T", two, F.col("a.name"), F.when(touch, 0).otherwise(1), 2, ints(F.col("a.sn"), F.col("b.sn"))),
        q("text", "MC-T", one, F.col("a.name"), stable_bucket(4, "w", F.col("scene_id")), 4, ints(F.col("a.sn"))),
    )
    out = s.select("scene_id", "n", "objs", F.explode(F.filter(asked, lambda x: x.isNotNull())).alias("q")).select("scene_id", "n", "objs", "q.*")
    chosen = F.filter("objs", lambda o: F.array_contains("rel", o["sn"]))
    return out.withColumns(
        {
            "item_id": F.concat_ws("-", "task", F.col("scene_id").cast("string")),
            "worst_rank": F.coalesce(F.array_max(F.transform(chosen, lambda o: o["rk"])), F.lit(0)),
            "least_area": F.coalesce(F.array_min(F.transform(chosen, lambda o: o["area"])), F.lit(NO_AREA)),
        }
    )


#: Percent of each benchmark that single-edit experiments use.
SAMPLE = {"YN": 100, "MC-G": 30, "MC-T": 10}


def sampled(df: DataFrame, percent: dict[str, int] | None = None) -> DataFrame:
    """A hash sample of scenes, the same in every engine."""
    percent = percent or SAMPLE
    keep = F.lit(False)
    for bench, pct in percent.items():
        keep = keep | ((F.col("benchmark") == bench) & (stable_bucket(100, "s", F.col("scene_id")) < pct))
    return df.where(keep)


def dialogue_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User turns with the next assistant turn as reference; OE-1: even conversations, OE-2: odd."""
    c = read_table(spark, sf_dir, "conversations")
    w = Window.partitionBy("conv_id").orderBy("turn")
    c = c.withColumns({"next_role": F.lead("role").over(w), "reference": F.lead("text").over(w)})
    return c.where("role = 'user' and next_role = 'assistant'").select(
        "conv_id", "turn", F.when(F.col("conv_id") % 2 == 0, "OE-1").otherwise("OE-2").alias("benchmark"), F.col("text").alias("question"), "reference"
    )


ALPHAS = (0.0, 0.2, 0.4, 0.6, 0.9)
PLANT_PERCENT = 60


def eval_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = read_table(spark, sf_dir, "embeddings")
    return v.where("vec_id % 5 = 0").select(F.col("vec_id").alias("eval_id"), F.floor(F.col("vec_id") / 5).cast("long").alias("slot"), (F.floor(F.col("vec_id") / 5) % 3).cast("int").alias("eval_set"), F.col("embedding").cast("array<double>").alias("ev"))


def train_vectors(spark: SparkSession, sf_dir: str, shift: bool = False) -> DataFrame:
    """(train_id, tv, in_xl, in_m, in_cap, planted_from): the other vectors, and near copies of hash-chosen evaluation ones."""
    v = read_table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    rest = v.where("vec_id % 5 != 0").select(F.concat(F.lit("v"), F.col("vec_id").cast("string")).alias("train_id"), F.col("v").alias("tv"), F.lit(None).cast("long").alias("planted_from"))
    noise = v.select((F.col("vec_id") - 1).alias("vec_id"), F.col("v").alias("u"))
    alpha = F.element_at(F.array(*[F.lit(a) for a in ALPHAS]), (F.floor(F.col("vec_id") / 5) % 5 + 1).cast("int"))
    planted = (
        v.where("vec_id % 5 = 0").where(stable_bucket(100, "plant", F.col("vec_id")) < PLANT_PERCENT).join(noise, "vec_id")
        .select(F.concat(F.lit("p"), F.col("vec_id").cast("string")).alias("train_id"), F.zip_with("v", "u", lambda a, b: a + alpha * b).alias("tv"), F.col("vec_id").alias("planted_from"))
    )
    h = stable_bucket(100, "set", F.col("train_id"))
    return rest.unionByName(planted).withColumns({"in_xl": F.lit(1), "in_m": (h < 40).cast("int"), "in_cap": (h < 15).cast("int")})
