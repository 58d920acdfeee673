"""The registered queries: carriers, edits, judge, compositions, scores, contamination and the operators around them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from benchvary.functions.hashing import stable_bucket
from benchvary.functions.text import boxes_overlap, cosine, normalize_answer, parse_choice, parse_yes_no, token_f1
from benchvary.operators import answering as A
from benchvary.operators import contamination as C
from benchvary.operators import edits as E
from benchvary.operators import judge as J
from benchvary.operators import samples as V
from benchvary.plans import compose as P
from benchvary.sources import carriers as S
from benchvary.sources.tables import read_table

QUERIES: dict = {}
THRESHOLDS = (0.4, 0.5, 0.6, 0.7, 0.8, 0.9, 0.95, 0.99)


def query(f):
    QUERIES[f.__name__] = f
    return f


# --- carriers ---------------------------------------------------------------------------------------------------


@query
def scene_objects(spark: SparkSession, d: str) -> DataFrame:
    return S.scene_objects(spark, d)


@query
def scene_stats(spark, d):
    per = S.scene_objects(spark, d).groupBy("scene_id").agg(F.count("*").alias("objects"))
    return per.groupBy("objects").agg(F.count("*").alias("scenes"))


@query
def empty_scenes(spark, d):
    return read_table(spark, d, "orders").join(read_table(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select(F.col("o_orderkey").alias("scene_id"))


_ITEM = ("item_id", "scene_id", "task", "benchmark", "name", "answer", "n_options", "n", "worst_rank", "least_area")


def _task(task):
    def run(spark, d):
        return S.items(spark, d).where(F.col("task") == task).select(*_ITEM)

    QUERIES[f"items_{task}"] = run


for _t in ("presence", "count", "attribute", "spatial", "interaction", "text"):
    _task(_t)


@query
def sampled_benchmarks(spark, d):
    return S.sampled(S.items(spark, d)).groupBy("benchmark", "task").agg(F.count("*").alias("n"))


@query
def dialogue_items(spark, d):
    return S.dialogue_items(spark, d)


@query
def vector_split(spark, d):
    e = S.eval_vectors(spark, d)
    return e.groupBy("eval_set").agg(F.count("*").alias("n"))


@query
def planted_copies(spark, d):
    e, t = S.eval_vectors(spark, d), S.train_vectors(spark, d)
    return t.where("planted_from is not null").join(e, F.col("planted_from") == F.col("eval_id")).select("eval_id", "in_m", "in_cap", F.round(cosine(F.col("ev"), F.col("tv")), 6).alias("sim"))


def _captions(spark, d):
    """(train_id, caption): document t mod n for vector t, the first document with the item for a planted copy."""
    docs = read_table(spark, d, "documents").select("doc_id", "text")
    n_docs = docs.select("doc_id").distinct().count()
    items_ = read_table(spark, d, "benchmark").select("item_id", F.col("text").alias("item"))
    n_items = items_.count()
    holds = C.verbatim_overlap(docs, items_.withColumnRenamed("item", "text")).groupBy("item_id").agg(F.min("doc_id").alias("held_by"))
    t = S.train_vectors(spark, d).select("train_id", "planted_from", F.substring("train_id", 2, 20).cast("long").alias("vec"))
    t = t.withColumn("item_id", F.when(F.col("planted_from").isNotNull(), F.floor(F.col("planted_from") / 5) % n_items))
    t = t.join(F.broadcast(holds), "item_id", "left").withColumn("doc_id", F.coalesce("held_by", F.col("vec") % n_docs))
    return t.join(docs, "doc_id").select("train_id", "doc_id", F.col("text").alias("caption"))


@query
def caption_links(spark, d):
    return _captions(spark, d).select("train_id", "doc_id")


@query
def page_blocks(spark, d):
    html = F.coalesce(F.col("html"), F.lit(""))
    count = lambda x: ((F.length(html) - F.length(F.replace(html, F.lit(x), F.lit("")))) / len(x)).cast("long")
    return read_table(spark, d, "pages").select("page_id", count("<nav").alias("navs"), count("<p>").alias("paragraphs"), count('<div class="ad"').alias("ads"))


# --- contamination ----------------------------------------------------------------------------------------------


@query
def contam_image_raw_pairs(spark, d):
    v = read_table(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    pairs = C.similar_pairs(v.select(F.col("vec_id").alias("eval_id"), F.col("v").alias("ev")), v.select(F.col("vec_id").cast("string").alias("train_id"), F.col("v").alias("tv")), 0.4)
    return pairs.where("eval_id < cast(train_id as long)").select("eval_id", F.col("train_id").cast("long").alias("other_id"), F.round("sim", 6).alias("sim"))


@query
def contam_image_best_match(spark, d):
    return C.best_match(S.eval_vectors(spark, d), S.train_vectors(spark, d)).select("eval_id", F.round("sim", 6).alias("sim"))


@query
def contam_image_flags_semi(spark, d):
    return C.contaminated_ids(S.eval_vectors(spark, d), S.train_vectors(spark, d))


def _image_flags(spark, d):
    e, t = S.eval_vectors(spark, d), S.train_vectors(spark, d)
    return C.by_training_set(C.image_contamination(e, t), t, e)


@query
def contam_image_rate_grid(spark, d):
    return C.rate_grid(_image_flags(spark, d))


@query
def contam_threshold_sweep(spark, d):
    return C.threshold_sweep(C.best_match(S.eval_vectors(spark, d), S.train_vectors(spark, d)), THRESHOLDS)


def _text_flags(spark, d, how: str, evals: DataFrame | None = None):
    """Image-text flags: pairs whose caption settles the item's answer (the second half of the item's words)."""
    e, t = S.eval_vectors(spark, d) if evals is None else evals, S.train_vectors(spark, d)
    pairs = C.image_contamination(e, t)
    items_ = read_table(spark, d, "benchmark")
    n_items = items_.count()
    w = F.split("text", " ")
    answer = F.array_join(F.slice(w, F.floor(F.size(w) / 2).cast("int") + 1, F.size(w)), " ")
    items_ = items_.select("item_id", answer.alias("answer"))
    caps = _captions(spark, d)
    found = pairs.join(e.select("eval_id", (F.col("slot") % n_items).alias("item_id")), "eval_id").join(F.broadcast(items_), "item_id").join(caps, "train_id").where(C.decided_by(F.col("caption"), F.col("answer"), how))
    return C.by_training_set(found.select("eval_id", "train_id"), t, e)


def _text_rate(how):
    def run(spark, d):
        return C.rate_grid(_text_flags(spark, d, how))

    QUERIES[f"contam_text_rate_{how}"] = run


for _h in ("span", "recall", "shingle"):
    _text_rate(_h)


@query
def contam_text_two_denominators(spark, d):
    text, image = _text_flags(spark, d, "span"), _image_flags(spark, d)
    both = text.withColumnRenamed("hit", "text_hit").join(image.withColumnRenamed("hit", "image_hit"), ["eval_id", "eval_set", "train_set"])
    return both.groupBy("train_set").agg(
        F.round(F.sum("text_hit") / F.count("*"), 6).alias("of_all"), F.round(F.coalesce(F.sum("text_hit") / F.nullif(F.sum("image_hit"), F.lit(0)), F.lit(0.0)), 6).alias("of_contaminated")
    )


@query
def contam_grid_rollup(spark, d):
    flags = _image_flags(spark, d)
    return flags.rollup("eval_set", "train_set").agg(F.count("*").alias("n"), F.sum("hit").cast("long").alias("hits"), F.grouping_id().cast("long").alias("level"))


def _shifted(spark, d):
    """Evaluation vectors as the hardest variant has them: moved by the noise of another vector, alpha 0.6."""
    e = S.eval_vectors(spark, d)
    u = read_table(spark, d, "embeddings").select((F.col("vec_id") - 2).alias("eval_id"), F.col("embedding").cast("array<double>").alias("u"))
    return e.join(u, "eval_id", "left").withColumn("ev", F.when(F.col("u").isNotNull(), F.zip_with("ev", "u", lambda a, b: a + F.lit(0.6) * b)).otherwise(F.col("ev"))).drop("u")


@query
def shift_vector(spark, d):
    e = S.eval_vectors(spark, d).select("eval_id", F.col("ev").alias("v"))
    return _shifted(spark, d).join(e, "eval_id").select("eval_id", F.round(cosine(F.col("ev"), F.col("v")), 6).alias("kept"))


@query
def contam_reduction(spark, d):
    """Image-text rates of the static and of the hardest benchmark, whose pictures are re-encoded after the edit."""
    sides = [C.rate_grid(_text_flags(spark, d, "span", e)).select("eval_set", "train_set", F.col("rate").alias(n)) for n, e in (("static", S.eval_vectors(spark, d)), ("varied", _shifted(spark, d)))]
    both = sides[0].join(sides[1], ["eval_set", "train_set"], "full")
    zero = lambda c: F.coalesce(c, F.lit(0.0))
    less = zero("static") - zero("varied")
    return both.select("eval_set", "train_set", zero("static").alias("static"), zero("varied").alias("varied"), F.round(less, 6).alias("reduction"), F.when(zero("static") > 0, F.round(less / zero("static"), 6)).alias("relative"))


@query
def text_overlap_verbatim(spark, d):
    return C.verbatim_overlap(read_table(spark, d, "documents"), read_table(spark, d, "benchmark"))


@query
def text_overlap_shingle(spark, d):
    return C.shared_runs(read_table(spark, d, "documents"), read_table(spark, d, "benchmark"), 8)


@query
def contam_everywhere(spark, d):
    f = _image_flags(spark, d).where("hit = 1")
    one = lambda s: f.where(F.col("train_set") == s).select("eval_id")
    return one("in_xl").intersect(one("in_m")).intersect(one("in_cap"))


@query
def contam_nowhere(spark, d):
    return S.eval_vectors(spark, d).select("eval_id").exceptAll(_image_flags(spark, d).where("hit = 1").select("eval_id").distinct())


def _approximate(strategy):
    def run(spark, d):
        return C.image_contamination(S.eval_vectors(spark, d), S.train_vectors(spark, d), strategy=strategy).select("eval_id", "train_id", F.round("sim", 6).alias("sim"))

    QUERIES[f"contam_{strategy}"] = run


for _s in ("lsh", "cells"):
    _approximate(_s)


# --- image edits ------------------------------------------------------------------------------------------------


@query
def propose_additions(spark, d):
    tries = E.propose_additions(S.items(spark, d)).select("item_id", F.explode("tries").alias("t"))
    return tries.select("item_id", F.col("t.k").alias("attempt"), F.col("t.x").alias("x"), F.col("t.y").alias("y"), F.col("t.ok").cast("int").alias("ok"))


@query
def propose_removals(spark, d):
    return E.removable(S.items(spark, d)).select("item_id", F.size("can_go").cast("long").alias("removable"))


@query
def box_masks(spark, d):
    o = S.scene_objects(spark, d)
    return o.select("scene_id", "sn", "x0", "y0", F.least(F.col("x0") + F.col("w"), F.lit(S.CANVAS)).alias("x1"), F.least(F.col("y0") + F.col("h"), F.lit(S.CANVAS)).alias("y1"))


@query
def scene_add(spark, d):
    return E.add_object(S.items(spark, d)).select("item_id", "v1_attempt", "v1_x", "v1_y", "v1_name", "v1_fallback")


@query
def scene_remove(spark, d):
    return E.remove_object(S.items(spark, d)).select("item_id", "v2_sn", "v2_fallback")


@query
def scene_expand(spark, d):
    return E.expand_scene(S.scene_objects(spark, d)).select("scene_id", "sn", "x0", "y0", "w", "h", "canvas")


@query
def scene_expand_ratios(spark, d):
    o = S.scene_objects(spark, d)
    ratios = spark.createDataFrame([(r,) for r in (1.25, 1.5, 1.75, 2.0)], "ratio double")
    side = E.canvas_side(F.col("ratio"))
    return o.crossJoin(F.broadcast(ratios)).groupBy("ratio").agg(F.count("*").alias("n"), F.max(side).alias("canvas"), F.sum(F.col("x0") + F.floor((side - 1000) / 2)).cast("long").alias("sum_x"))


@query
def page_remove_clutter(spark, d):
    return read_table(spark, d, "pages").select("page_id", F.md5(E.page_without_clutter(F.coalesce("html", F.lit("")))).alias("digest"))


@query
def page_add_clutter(spark, d):
    return read_table(spark, d, "pages").select("page_id", F.md5(E.page_with_clutter(F.coalesce("html", F.lit("")))).alias("digest"))


# --- question edits ---------------------------------------------------------------------------------------------


@query
def word_swap(spark, d):
    q = E.question_text(E.swapped_name(S.items(spark, d)), l1=True)
    return q.select("item_id", "swap1", "swap2", "question")


@query
def persona_rephrase(spark, d):
    return E.question_text(E.with_persona(S.items(spark, d)), l2=True).select("item_id", "persona", "question")


@query
def hint_context(spark, d):
    return E.question_text(S.items(spark, d), l3=True).select("item_id", "question")


def _scenes(spark, d):
    """(scene_id, objs) of every scene, and the largest scene number, from which L4 draws."""
    o = S.scene_objects(spark, d).groupBy("scene_id").agg(F.array_sort(F.collect_list(F.struct("sn", "name"))).alias("objs"))
    return o, read_table(spark, d, "orders").agg(F.coalesce(F.max("o_orderkey"), F.lit(0))).first()[0]


@query
def noise_context(spark, d):
    """The description of another scene in front of the question."""
    i = E.question_text(S.items(spark, d)).select("item_id", "scene_id", "name", "question")
    return E.with_noise(i, *_scenes(spark, d)).select("item_id", "l4_attempt", E.in_context(F.col("question"), F.col("noise")).alias("question"))


@query
def context_after(spark, d):
    """Both contexts behind the question instead of in front of it."""
    i = E.question_text(S.items(spark, d), l3=True, where="after").select("item_id", "scene_id", "name", "question")
    return E.with_noise(i, *_scenes(spark, d)).select("item_id", E.in_context(F.col("question"), F.col("noise"), "after").alias("question"))


@query
def describe_scene(spark, d):
    o = S.scene_objects(spark, d).groupBy("scene_id").agg(F.array_sort(F.collect_list(F.struct("sn", "name"))).alias("objs"))
    return o.select("scene_id", E.describe(F.col("objs")).alias("description"))


@query
def dialogue_noise_context(spark, d):
    q = S.dialogue_items(spark, d)
    return q.select("conv_id", "turn", F.concat(F.lit("By the way, this is conversation "), F.col("conv_id").cast("string"), F.lit(". "), F.col("question")).alias("question"))


# --- judge ------------------------------------------------------------------------------------------------------


def _proposals(spark, d):
    i = S.items(spark, d)
    return J.proposals(i, E.propose_noise(i.select("item_id", "task", "scene_id", "name"), *_scenes(spark, d)))


@query
def judge_verdicts(spark, d):
    """Verdicts on the proposals of all seven edits, by edit and attempt."""
    return _proposals(spark, d).groupBy("strategy", F.col("k").alias("attempt")).agg(F.count("*").alias("n"), F.sum(F.col("ok").cast("long")).alias("yes"))


@query
def judge_attempts(spark, d):
    """Attempts until acceptance or fallback, by edit."""
    return J.first_accepted(S.items(spark, d), *_scenes(spark, d)).groupBy("strategy", "attempt", "fallback").agg(F.count("*").alias("n"))


@query
def judge_acceptance_cumulative(spark, d):
    per = judge_attempts(spark, d)
    total = per.groupBy("strategy").agg(F.sum("n").alias("total"))
    up = F.sum("n").over(Window.partitionBy("strategy").orderBy("attempt"))
    return per.where("fallback = 0").join(total, "strategy").select("strategy", "attempt", "n", F.round(up / F.col("total"), 6).alias("share"))


@query
def judge_composite(spark, d):
    """The twelve pairs: one check of both edits against a check of each."""
    return J.composite(S.items(spark, d), *_scenes(spark, d), [(v, t) for v in P.IMAGE for t in P.TEXT])


@query
def judge_rounds(spark, d):
    """V1 by rounds over what is still open; the same result as from all attempts at once."""
    i = S.items(spark, d).select("item_id", "name", "rel", F.filter("objs", lambda o: F.array_contains("rel", o["sn"])).alias("objs"))

    def propose(left, k):
        return E.propose_additions(left, k, first=k).withColumn("ok", F.element_at("tries", 1)["ok"])

    return J.rounds(i, propose).groupBy("attempt", "fallback").agg(F.count("*").alias("n"))


@query
def judge_confusion(spark, d):
    """A lossy judge that looks at the largest relevant object only, against the exact check of all."""
    i = E.propose_additions(S.items(spark, d))
    t = F.element_at("tries", 1)
    side = F.lit(E.ADDED)
    top = F.array_min(F.transform(F.filter("objs", lambda o: F.array_contains("rel", o["sn"])), lambda o: F.struct(o["rk"], o["x0"], o["y0"], o["w"], o["h"])))
    lossy = ~F.coalesce(boxes_overlap(top["x0"], top["y0"], top["w"], top["h"], t["x"], t["y"], side, side), F.lit(False))
    return A.agreement(i.select(lossy.alias("judged"), t["ok"].alias("truth")), "judged", "truth")


@query
def fallback_share(spark, d):
    return J.first_accepted(S.items(spark, d), *_scenes(spark, d)).groupBy("task", "strategy").agg(F.count("*").alias("n"), A.prob("fallback").alias("fallback"))


@query
def answer_preserved(spark, d):
    """Violations of the protocol: a removed object that was relevant, or an accepted box over a relevant one. Must be zero."""
    i = E.remove_object(E.add_object(S.items(spark, d)))
    hidden = F.exists("objs", lambda o: F.array_contains("rel", o["sn"]) & boxes_overlap(o["x0"], o["y0"], o["w"], o["h"], F.col("v1_x"), F.col("v1_y"), F.lit(E.ADDED), F.lit(E.ADDED)))
    gone = F.array_contains("rel", F.col("v2_sn"))
    return i.agg(F.count("*").alias("n"), F.coalesce(F.sum(F.coalesce(hidden, F.lit(False)).cast("long")), F.lit(0)).alias("hidden"), F.coalesce(F.sum(F.coalesce(gone, F.lit(False)).cast("long")), F.lit(0)).alias("removed"))


# --- scores -----------------------------------------------------------------------------------------------------


def _scores(spark, d, specs, full: bool = False, where: str = "true", models=A.MODELS, by=("model", "benchmark", "variant_id")):
    items_ = S.items(spark, d).where(where)
    return A.accuracy(A.answers(E.edited(items_ if full else S.sampled(items_)), A.spec_table(spark, specs), A.model_table(spark, models)), by)


@query
def single_image_scores(spark, d):
    return _scores(spark, d, P.SINGLE_IMAGE)


@query
def single_image_deltas(spark, d):
    return A.deltas(_scores(spark, d, P.SINGLE_IMAGE))


@query
def single_text_scores(spark, d):
    return _scores(spark, d, P.SINGLE_TEXT)


@query
def single_text_deltas(spark, d):
    return A.deltas(_scores(spark, d, P.SINGLE_TEXT))


def _dealt(spark, d, specs, salt):
    """Compositions with the number of scenes, of all orders, that a hash of the scene deals to each: place k goes to the k-th."""
    table = A.spec_table(spark, tuple((*s, k) for k, s in enumerate(specs)), "place int")
    scenes = read_table(spark, d, "orders").groupBy(stable_bucket(len(specs), salt, F.col("o_orderkey")).cast("int").alias("place")).agg(F.count("*").alias("scenes"))
    return F.broadcast(table).join(scenes, "place", "left").na.fill(0, ["scenes"]).drop("place")


@query
def paired_grid_variants(spark, d):
    """The twelve pairs, over which the scenes are dealt."""
    return _dealt(spark, d, P.GRID, "grid")


@query
def paired_grid_scores(spark, d):
    return _scores(spark, d, P.GRID, where="benchmark = 'MC-G'")


@query
def grid_axes(spark, d):
    """Both axes of the grid from easy to hard, by the mean accuracy of the single edits."""
    means = A.model_average(_scores(spark, d, (*P.SINGLE_IMAGE, *P.SINGLE_TEXT[1:]), where="benchmark = 'MC-G'"), ("variant_id",)).where("variant_id <> 'vanilla'")
    side = F.substring("variant_id", 1, 1)
    return means.withColumn("axis", side).withColumn("place", F.row_number().over(Window.partitionBy("axis").orderBy(F.desc("mean_accuracy"), "variant_id")))


@query
def grid_monotonicity(spark, d):
    """Neighbouring cells of the grid in the expected order."""
    axes = grid_axes(spark, d).select("variant_id", "place")
    cells = A.model_average(_scores(spark, d, P.GRID, where="benchmark = 'MC-G'"), ("variant_id",))
    v, t = axes.select(F.col("variant_id").alias("v"), F.col("place").alias("pv")), axes.select(F.col("variant_id").alias("l"), F.col("place").alias("pl"))
    g = cells.withColumns({"v": F.split_part("variant_id", F.lit("+"), F.lit(1)), "l": F.split_part("variant_id", F.lit("+"), F.lit(2))}).join(F.broadcast(v), "v").join(F.broadcast(t), "l")
    a, b = g.alias("a"), g.alias("b")
    step = ((F.col("b.pv") == F.col("a.pv") + 1) & (F.col("b.pl") == F.col("a.pl"))) | ((F.col("b.pl") == F.col("a.pl") + 1) & (F.col("b.pv") == F.col("a.pv")))
    return a.join(F.broadcast(b), step).agg(F.count("*").alias("neighbours"), F.sum((F.col("b.mean_accuracy") <= F.col("a.mean_accuracy")).cast("long")).alias("in_order"))


@query
def hard_ladder_scores(spark, d):
    s = _scores(spark, d, P.LADDER, where="benchmark = 'MC-T'", models=A.MODELS[6:], by=("model", "benchmark", "variant_id", "n_hard"))
    return s


@query
def ladder_steps(spark, d):
    s = _scores(spark, d, P.LADDER[:4], where="benchmark = 'MC-T'", by=("model", "benchmark", "variant_id", "n_hard"))
    return A.steps(A.model_average(s, ("n_hard",)), "n_hard")


@query
def extreme_scores_closed(spark, d):
    return _scores(spark, d, P.EXTREMES, full=True, where="benchmark = 'MC-G'", models=(*A.MODELS, A.EXTRA_MODEL))


def _open_scores(spark, d, specs, by=("model", "benchmark", "variant_id"), models=(*A.MODELS, A.EXTRA_MODEL)):
    """Graded answers to dialogues: the answerer repeats as many words of the reference as its capacity allows.

    An added object and a larger canvas each cost a word, a removed object gives one; contexts act as on closed questions.
    """
    q = S.dialogue_items(spark, d)
    m = A.model_table(spark, models)
    v = A.spec_table(spark, specs)
    image = F.col("v2") - F.col("v1") - (F.col("ratio") > 1).cast("int")
    cap = F.greatest(F.lit(0), 4 * F.col("cap") + image - F.col("l4") * 2 * F.col("noise_cost") + F.col("l3") * 2 * F.col("hint_gain"))
    w = F.split("reference", " ")
    r = q.crossJoin(F.broadcast(m)).crossJoin(F.broadcast(v)).withColumn("given", F.array_join(F.slice(w, F.lit(1), cap), " "))
    return r.groupBy(*by).agg(F.count("*").alias("n"), F.round(F.avg(token_f1(F.col("given"), F.col("reference"))), 4).alias("accuracy"))


@query
def extreme_scores_open(spark, d):
    return _open_scores(spark, d, P.EXTREMES)


@query
def ladder_scores_open(spark, d):
    """The ladder on the first open-ended set, for the three strongest models."""
    return _open_scores(spark, d, P.LADDER, ("model", "benchmark", "variant_id", "n_hard"), A.MODELS[6:]).where("benchmark = 'OE-1'")


@query
def score_bounds(spark, d):
    return A.bounds(_scores(spark, d, P.EXTREMES, full=True, where="benchmark = 'MC-G'"))


def _editions(spark, d):
    """Items with the added box of each of three editions, in one pass: editions, array<struct<edition,v1_x,v1_y>>."""
    i = S.items(spark, d).select("item_id", "name", "rel", "objs")
    for k in range(3):
        i = E.add_object(i, edition=k).withColumn(f"e{k}", F.struct(F.lit(k).alias("edition"), "v1_x", "v1_y")).drop("tries", "v1_attempt", "v1_x", "v1_y", "v1_name", "v1_fallback")
    return i.select("item_id", F.array("e0", "e1", "e2").alias("editions"))


@query
def edition_refresh(spark, d):
    return _editions(spark, d).select("item_id", F.explode("editions").alias("e")).select("item_id", "e.*")


@query
def variant_examples(spark, d):
    """Each item beside its hardest form: the scene in words, the canvas and the question, before and after."""
    i = S.items(spark, d).withColumn("before", E.describe(F.col("objs")))
    hard = V.apply_spec(i, ("V1", "V3"), keep=("name", "before"))  # these leave the question as it was; L4 follows in the same row
    hard = hard.select("item_id", "scene_id", "name", F.col("before").alias("scene"), "question", E.describe(F.col("scene")).alias("scene_after"), "canvas", "fallbacks")
    out = E.with_noise(hard, *_scenes(spark, d))
    return out.select("item_id", "scene", "question", "scene_after", "canvas", E.in_context(F.col("question"), F.col("noise")).alias("question_after"), (F.col("fallbacks") + F.col("l4_fallback")).alias("fallbacks"))


@query
def stack_order_effect(spark, d):
    """Adding and then expanding against expanding and then adding: attempts, fallbacks, and added boxes in the old scene's frame."""
    i = S.items(spark, d)
    out = None
    for order in (("V1", "V3"), ("V3", "V1")):
        s = J.judged_stack(i, order).withColumn("order", F.lit(">".join(order)))
        out = s if out is None else out.unionByName(s)
    inside = (F.col("x") + E.ADDED > 250) & (F.col("x") < 1250) & (F.col("y") + E.ADDED > 250) & (F.col("y") < 1250)
    return out.groupBy("order").agg(F.count("*").alias("n"), F.sum("v1_attempt").alias("calls"), F.sum("v1_fallback").cast("long").alias("fallbacks"), F.sum(F.coalesce(inside, F.lit(False)).cast("long")).alias("inside"))


@query
def edition_diversity(spark, d):
    boxes = F.filter("editions", lambda e: e["v1_x"].isNotNull())
    e = _editions(spark, d).select(boxes.alias("b")).where(F.size("b") > 0)
    per = e.select((F.size(F.array_distinct(F.transform("b", lambda e: F.struct(e["v1_x"], e["v1_y"])))) / F.size("b")).alias("share"))  # an item is one row
    return per.agg(F.count("*").alias("n"), F.round(F.avg("share"), 6).alias("diversity"))


@query
def direction_check(spark, d):
    s = _scores(spark, d, (*P.SINGLE_IMAGE, *P.SINGLE_TEXT[1:]))
    return A.direction(A.deltas(s), E.strategy_table(spark))


@query
def model_average(spark, d):
    return A.model_average(_scores(spark, d, (*P.SINGLE_IMAGE, *P.SINGLE_TEXT[1:])))


@query
def ratio_ablation(spark, d):
    return A.model_average(_scores(spark, d, P.RATIOS), ("variant_id",))


@query
def ratio_steps(spark, d):
    return A.steps(A.model_average(_scores(spark, d, P.RATIOS), ("variant_id",)), "variant_id")


def _tasks(spark, d):
    s = _scores(spark, d, P.EXTREMES, full=True, by=("model", "task", "variant_id"))
    return A.model_average(s, ("task", "variant_id"))


@query
def task_breakdown(spark, d):
    return _tasks(spark, d)


@query
def task_sensitivity(spark, d):
    wide = _tasks(spark, d).groupBy("task").pivot("variant_id", ["V1+L4", "vanilla", "V2+L3"]).agg(F.first("mean_accuracy"))
    change = F.round(F.abs(F.col("`V1+L4`") - F.col("vanilla")) + F.abs(F.col("`V2+L3`") - F.col("vanilla")), 4)
    out = wide.select("task", change.alias("change"))
    return out.withColumn("place", F.rank().over(Window.orderBy(F.desc("change"))))


@query
def fluctuation_by_level(spark, d):
    dl = A.deltas(_scores(spark, d, P.SINGLE_TEXT))
    r = E.strategy_table(spark)
    j = dl.join(F.broadcast(r), F.col("variant_id") == F.col("strategy"))
    return j.groupBy("strategy", "level").agg(F.round(F.avg(F.abs("delta")), 4).alias("mean_abs"), F.round(F.percentile(F.abs("delta"), F.lit(0.5)), 4).alias("median_abs"))


@query
def leaderboard(spark, d):
    return A.leaderboard(_scores(spark, d, P.SINGLE_IMAGE)).select("model", "benchmark", "variant_id", "accuracy", "place")


@query
def rank_shift(spark, d):
    b = A.leaderboard(_scores(spark, d, P.EXTREMES, full=True, where="benchmark = 'MC-G'"))
    base = b.where("variant_id = 'vanilla'").select("model", F.col("place").alias("vanilla_place"))
    return b.where("variant_id <> 'vanilla'").join(F.broadcast(base), "model").select("model", "variant_id", (F.col("place") - F.col("vanilla_place")).alias("shift"))


@query
def rank_correlation(spark, d):
    """Rank correlation of the leaderboard on each extreme variant with the static one."""
    b = A.leaderboard(_scores(spark, d, P.EXTREMES, full=True, where="benchmark = 'MC-G'"))
    base = b.where("variant_id = 'vanilla'").select("model", F.col("place").alias("vanilla_place"))
    both = b.where("variant_id <> 'vanilla'").join(F.broadcast(base), "model")
    return both.groupBy("variant_id").agg(F.round(F.corr(F.col("place").cast("double"), F.col("vanilla_place").cast("double")), 4).alias("correlation"))


@query
def guesser_scores(spark, d):
    """Chance: an answerer that sees nothing."""
    i = S.items(spark, d).withColumn("right", (stable_bucket(F.col("n_options"), "g", F.lit("chance"), F.col("item_id")) == F.col("answer")).cast("int"))
    return i.groupBy("benchmark").agg(F.count("*").alias("n"), F.round(100.0 * F.sum("right") / F.count("*"), 4).alias("accuracy"))


@query
def parsed_answers(spark, d):
    """Raw answers as a model would give them (an option's letter, or yes and no in a sentence), parsed and scored."""
    i = S.items(spark, d).where("n_options = 4 or task = 'presence'")
    letter = F.substring(F.lit("ABCD"), F.col("answer") + 1, F.lit(1))
    raw = F.when(F.col("task") == "presence", F.when(F.col("answer") == 0, "Yes, there is one.").otherwise("I think no.")).otherwise(F.concat(F.lit("("), letter, F.lit(") is right")))
    i = i.withColumn("raw", raw)
    got = F.when(F.col("task") == "presence", F.when(parse_yes_no(F.col("raw")) == "yes", 0).otherwise(1)).otherwise(F.instr(F.lit("ABCD"), parse_choice(F.col("raw"))) - 1)
    return i.groupBy("task").agg(F.count("*").alias("n"), F.sum((got == F.col("answer")).cast("long")).alias("right"))


@query
def memorisation_gap(spark, d):
    """An answerer that has the contaminated static items by heart: right there on vanilla, ordinary on the varied form.

    An item's picture is the evaluation vector that its hash picks; it is contaminated where that vector is, in the largest set.
    """
    a = A.answers(E.edited(S.items(spark, d)), A.spec_table(spark, P.EXTREMES[:2]), A.model_table(spark))
    e = S.eval_vectors(spark, d)
    n = e.count()
    known = C.image_contamination(e, S.train_vectors(spark, d)).join(e, "eval_id").select("slot").distinct().withColumn("known", F.lit(True))
    a = a.withColumn("slot", stable_bucket(max(n, 1), "picture", F.col("item_id"))).join(known, "slot", "left")
    seen = F.coalesce("known", F.lit(False)) & (F.col("variant_id") == "vanilla")
    return a.withColumn("by_heart", F.when(seen, 1).otherwise(F.col("correct"))).groupBy("variant_id").agg(A.prob("correct").alias("honest"), A.prob("by_heart").alias("memorising"))


@query
def length_effect(spark, d):
    """Measured growth of each item's question under each text edit, against the loss of accuracy over all models."""
    i = E.with_noise(S.sampled(S.items(spark, d)), *_scenes(spark, d))
    q = E.question_text(E.with_persona(E.swapped_name(i))).withColumn("plain", F.length("question"))
    for t in P.TEXT:
        q = E.question_text(q, t == "L1", t == "L2", t == "L3", "noise" if t == "L4" else None).withColumn(f"chars_{t}", F.length("question") - F.col("plain"))
    a = A.answers(E.edited(S.sampled(S.items(spark, d))), A.spec_table(spark, P.SINGLE_TEXT), A.model_table(spark))
    right = a.groupBy("item_id").agg(*[F.avg(F.when(F.col("variant_id") == v, F.col("correct"))).alias(v) for v in ("vanilla", *P.TEXT)])
    both = right.join(q.select("item_id", *[f"chars_{t}" for t in P.TEXT]), "item_id")  # one row an item on either side
    rows = F.array(*[F.struct(F.lit(t).alias("variant_id"), F.col(f"chars_{t}").alias("chars"), (F.col("vanilla") - F.col(t)).alias("loss")) for t in P.TEXT])
    met = both.select(F.explode(rows).alias("m")).select("m.*")
    by = met.rollup("variant_id").agg(F.count("*").alias("n"), F.round(F.avg("chars"), 4).alias("chars"), F.round(F.avg("loss"), 4).alias("loss"), F.round(F.corr(F.col("chars").cast("double"), "loss"), 4).alias("c"))
    whole = F.max(F.when(F.col("variant_id").isNull(), F.col("c"))).over(Window.partitionBy(F.lit(1)))  # of five rows
    return by.withColumn("correlation", whole).where("variant_id is not null").drop("c")


@query
def variant_distance(spark, d):
    i = E.swapped_name(S.items(spark, d))
    a = E.question_text(i).select("item_id", F.split("question", " ").alias("a"))
    b = E.question_text(i, l1=True).select("item_id", F.split("question", " ").alias("b"))
    j = a.join(b, "item_id").withColumn("dist", 1 - F.size(F.array_intersect("a", "b")) / F.size(F.array_union("a", "b")))
    return j.agg(F.count("*").alias("n"), F.round(F.avg("dist"), 6).alias("distance"))


@query
def score_cube(spark, d):
    a = A.answers(E.edited(S.items(spark, d)), A.spec_table(spark, P.EXTREMES), A.model_table(spark))
    return a.cube("model", "benchmark", "variant_id").agg(F.count("*").alias("n"), F.sum("correct").cast("long").alias("right"))


@query
def scores_wide(spark, d):
    s = _scores(spark, d, P.SINGLE_IMAGE)
    return s.groupBy("model", "benchmark").pivot("variant_id", ["vanilla", "V1", "V2", "V3"]).agg(F.first("accuracy"))


@query
def score_ci(spark, d):
    return A.with_interval(_scores(spark, d, P.SINGLE_IMAGE))


@query
def cost_report(spark, d):
    """Generator and judge calls of one V1 pass, and model calls of the single-edit experiments."""
    e = E.add_object(S.sampled(S.items(spark, d)))
    return e.agg(F.count("*").alias("items"), F.sum("v1_attempt").alias("calls"), F.sum("v1_fallback").cast("long").alias("fallbacks")).withColumn("model_calls", F.col("items") * len(A.MODELS) * 8)


# --- operators around -------------------------------------------------------------------------------------------


@query
def op_asof_answers(spark, d):
    """The last earlier answer of the same user: an as-of join as one ordered window."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = read_table(spark, d, "events")
    return e.select("event_id", F.lag("event_id").over(w).alias("before_id"), F.round(F.lag("value").over(w), 6).alias("before_value"))


@query
def op_interval_verdicts(spark, d):
    """Answers of one user within an hour after another: an interval join on hour blocks."""
    e = read_table(spark, d, "events").select("event_id", "user_id", F.unix_seconds(F.col("ts").cast("timestamp")).alias("s"))
    a = e.select(F.col("event_id").alias("a_id"), F.col("user_id").alias("u"), F.col("s").alias("a_s"), F.explode(F.array(F.floor(F.col("s") / 3600), F.floor(F.col("s") / 3600) + 1)).alias("block"))
    b = e.select(F.col("event_id").alias("b_id"), F.col("user_id").alias("u"), F.col("s").alias("b_s"), F.floor(F.col("s") / 3600).alias("block"))
    return a.join(b, ["u", "block"]).where("b_s > a_s and b_s <= a_s + 3600").select("a_id", "b_id")


@query
def op_anti_missing_answers(spark, d):
    c, o = read_table(spark, d, "customer"), read_table(spark, d, "orders")
    return c.join(o, F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@query
def op_full_outer_rates(spark, d):
    n, s = read_table(spark, d, "customer"), read_table(spark, d, "supplier")
    a = n.groupBy(F.col("c_nationkey").alias("nation")).agg(F.count("*").alias("customers"))
    b = s.groupBy(F.col("s_nationkey").alias("nation")).agg(F.count("*").alias("suppliers"))
    return a.join(b, "nation", "full").na.fill(0)


@query
def op_grouping_sets(spark, d):
    read_table(spark, d, "events").createOrReplaceTempView("answer_log")
    return spark.sql("select event_type, user_id % 9 as model, count(*) as n from answer_log group by grouping sets ((event_type, user_id % 9), (event_type), ())")


@query
def op_percentiles(spark, d):
    return read_table(spark, d, "events").groupBy("event_type").agg(*[F.round(F.percentile("value", F.lit(p)), 6).alias(f"p{int(p * 100)}") for p in (0.25, 0.5, 0.9)])


@query
def op_ntile_models(spark, d):
    w = Window.partitionBy("event_type").orderBy(F.desc("value"), "event_id")
    return read_table(spark, d, "events").withColumn("quarter", F.ntile(4).over(w)).groupBy("event_type", "quarter").agg(F.count("*").alias("n"), F.round(F.avg("value"), 6).alias("mean"))


@query
def op_moving_accuracy(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-4, 0)
    return read_table(spark, d, "events").select("event_id", F.round(F.avg("value").over(w), 6).alias("moving"))


@query
def op_topk_pairs(spark, d):
    return contam_image_raw_pairs(spark, d).orderBy(F.desc("sim"), "eval_id", "other_id").limit(10)


@query
def op_union_variants(spark, d):
    o = S.scene_objects(spark, d).select("scene_id", "sn", "w")
    return o.withColumn("variant", F.lit("vanilla")).unionByName(o.where("w >= 60").withColumn("variant", F.lit("large"))).groupBy("variant").agg(F.count("*").alias("n"), F.sum("w").cast("long").alias("w"))


@query
def op_except_all(spark, d):
    line = read_table(spark, d, "lineitem").select("l_orderkey")
    return line.exceptAll(line.distinct()).groupBy("l_orderkey").agg(F.count("*").alias("n"))


@query
def op_unpivot_scores(spark, d):
    b = read_table(spark, d, "events").groupBy("event_type").agg(F.round(F.min("value"), 6).alias("low"), F.round(F.max("value"), 6).alias("high"))
    return b.unpivot(["event_type"], ["low", "high"], "bound", "value")


@query
def op_json_props(spark, d):
    k = F.get_json_object("props", "$.k").cast("int")
    return read_table(spark, d, "events").groupBy((k % 5 + 1).alias("attempt")).agg(F.count("*").alias("n"))


@query
def op_string_parse(spark, d):
    return read_table(spark, d, "benchmark").select("item_id", normalize_answer(F.col("text")).alias("plain"), F.size(F.split("text", " ")).cast("long").alias("words"))


@query
def op_date_buckets(spark, d):
    return read_table(spark, d, "orders").groupBy(F.date_format("o_orderdate", "yyyy-MM").alias("month")).agg(F.count("*").alias("n"))


@query
def op_box_overlap_join(spark, d):
    """Pairs of overlapping objects: equal scene, then the box condition."""
    o = S.scene_objects(spark, d)
    a, b = o.alias("a"), o.alias("b")
    hit = boxes_overlap(*(F.col(f"{x}.{k}") for x in "ab" for k in ("x0", "y0", "w", "h")))
    return a.join(b, (F.col("a.scene_id") == F.col("b.scene_id")) & (F.col("a.sn") < F.col("b.sn")) & hit).groupBy(F.col("a.scene_id").alias("scene_id")).agg(F.count("*").alias("pairs"))


@query
def op_specs(spark, d):
    """Every composition of at most two edits on each side, over which the scenes are dealt."""
    return _dealt(spark, d, P.all_compositions(), "spec")


@query
def op_udtf_specs(spark, d):
    """The compositions from a table function, with the number of scenes that allow each: a hash gives a scene its most edits on either side."""
    from benchvary.functions import sql

    sql.register(spark)
    most = lambda side: stable_bucket(3, side, F.col("o_orderkey")).cast("int")
    allowed = read_table(spark, d, "orders").groupBy(most("image").alias("images"), most("text").alias("texts")).agg(F.count("*").alias("scenes"))  # at most nine rows
    allowed.createOrReplaceTempView("_allowed")
    return spark.sql("select v.variant_id, v.n_hard, sum(a.scenes) as scenes from _allowed a, lateral variant_specs(a.images, a.texts) v group by 1, 2")


@query
def op_sql_functions(spark, d):
    """The SQL functions, over evaluation vectors and benchmark texts."""
    from benchvary.functions import sql

    sql.register(spark)
    S.eval_vectors(spark, d).createOrReplaceTempView("_evals")
    read_table(spark, d, "benchmark").createOrReplaceTempView("_benchmark")
    return spark.sql("select 'cosine' as f, count(*) as n, round(sum(cosine(ev, ev)), 4) as total from _evals union all select 'plain_answer', count(*), cast(sum(length(plain_answer(text))) as double) from _benchmark")


@query
def op_cube(spark, d):
    e = read_table(spark, d, "events").withColumn("model", F.col("user_id") % 9)
    return e.cube("event_type", "model").agg(F.count("*").alias("n"), F.grouping_id().cast("long").alias("level"))


@query
def op_map_scores(spark, d):
    """Scores of each model as a map from event type to its count, queried by key."""
    per = read_table(spark, d, "events").groupBy((F.col("user_id") % 9).alias("model"), "event_type").agg(F.count("*").alias("n"))
    m = per.groupBy("model").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("event_type", "n")))).alias("m"))
    best = F.array_max(F.map_values("m"))
    return m.select("model", F.size("m").cast("long").alias("kinds"), best.alias("most"), F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x).alias("n"))


@query
def op_lateral_candidates(spark, d):
    """A lateral join: the two largest objects of each scene, chosen row by row."""
    o = S.scene_objects(spark, d).groupBy("scene_id").agg(F.collect_list(F.struct((-F.col("w") * F.col("h")).alias("key"), "sn")).alias("objs"))
    o.createOrReplaceTempView("_scenes")
    return spark.sql("select scene_id, c.sn from _scenes, lateral (select x.sn as sn from (select explode(slice(array_sort(objs), 1, 2)) as x)) as c")


@query
def op_salted_join(spark, d):
    """A join whose left side is dealt over salts and whose right side is copied to each, so that a hot key is many tasks."""
    salts = 8
    line = read_table(spark, d, "lineitem").select("l_partkey", "l_orderkey", "l_linenumber").withColumn("salt", F.pmod(F.xxhash64("l_orderkey", "l_linenumber"), F.lit(salts)))
    part = read_table(spark, d, "part").select(F.col("p_partkey").alias("l_partkey"), "p_brand").withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    # by a merge of both sides: the copies count nowhere in the estimated size of the right side, which would be broadcast
    return line.join(part.hint("merge"), ["l_partkey", "salt"]).groupBy("p_brand").agg(F.count("*").alias("n"))


@query
def op_asof_join(spark, d):
    """Each answer with the latest earlier event of another kind of the same user, of two sides in one ordered window."""
    e = read_table(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    kinds = e.agg(F.min("event_type").alias("kind"))
    e = e.crossJoin(F.broadcast(kinds)).withColumn("version", F.when(F.col("event_type") == F.col("kind"), F.col("event_id")))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return e.withColumn("version_id", F.last("version", True).over(w)).where("version is null").select("event_id", "version_id")


@query
def op_rankings(spark, d):
    """All ranking functions over the number of answers of each user."""
    n = read_table(spark, d, "events").groupBy("user_id").agg(F.count("*").alias("n"))
    w = Window.partitionBy((F.col("user_id") % 9)).orderBy("n")
    return n.select("user_id", F.rank().over(w).alias("place"), F.dense_rank().over(w).alias("dense"), F.round(F.percent_rank().over(w), 6).alias("percent"), F.round(F.cume_dist().over(w), 6).alias("share"))


@query
def op_range_frame(spark, d):
    """Answers of a user within the day before each, by a range of seconds."""
    e = read_table(spark, d, "events").select("event_id", "user_id", F.unix_seconds(F.col("ts").cast("timestamp")).alias("s"))
    w = Window.partitionBy("user_id").orderBy("s").rangeBetween(-86_400, 0)
    return e.select("event_id", F.count("*").over(w).alias("within_day"))


@query
def op_approximate(spark, d):
    """Approximate distinct counts, percentiles and set sketches lie within their bounds of the exact values."""
    e = read_table(spark, d, "events")
    near = lambda a, b, share: F.abs(a - b) <= share * F.abs(b)
    return e.groupBy("event_type").agg(
        near(F.approx_count_distinct("user_id", 0.02), F.count_distinct("user_id"), 0.1).alias("distinct_ok"),
        near(F.hll_sketch_estimate(F.hll_sketch_agg("user_id")), F.count_distinct("user_id"), 0.1).alias("sketch_ok"),
        near(F.percentile_approx("value", 0.5, 10000), F.percentile("value", F.lit(0.5)), 0.05).alias("median_ok"),
    )


@query
def op_set_sketches(spark, d):
    """Overlaps of the training sets from theta sketches, against the exact sizes."""
    t = S.train_vectors(spark, d)
    sk = t.agg(*[F.theta_sketch_agg(F.when(F.col(c) == 1, F.col("train_id"))).alias(c) for c in ("in_xl", "in_m", "in_cap")], F.sum((F.col("in_m") * F.col("in_cap")).cast("long")).alias("m_cap"), F.sum(F.col("in_m").cast("long")).alias("m"))
    both = F.theta_sketch_estimate(F.theta_intersection("in_m", "in_cap"))
    return sk.select("m_cap", "m", (F.abs(both - F.col("m_cap")) <= F.greatest(F.lit(2.0), 0.1 * F.col("m_cap"))).alias("overlap_ok"), (F.abs(F.theta_sketch_estimate("in_m") - F.col("m")) <= 0.05 * F.col("m")).alias("size_ok"))


@query
def op_provider_inferrer(spark, d):
    """Pairs whose caption settles the answer, by the default provider over Arrow batches."""
    from benchvary.operators import providers

    docs, items_ = read_table(spark, d, "documents"), read_table(spark, d, "benchmark")
    n = items_.count()
    pairs = C.verbatim_overlap(docs, items_).unionByName(docs.select((F.col("doc_id") % max(n, 1)).alias("item_id"), "doc_id")).distinct()
    w = F.split("text", " ")
    half = F.floor(F.size(w) / 2).cast("int")
    items_ = items_.select("item_id", F.array_join(F.slice(w, 1, half), " ").alias("question"), F.array_join(F.slice(w, half + 1, F.size(w)), " ").alias("answer"))
    pairs = pairs.join(items_, "item_id").join(docs.select("doc_id", F.col("text").alias("caption")), "doc_id")
    return providers.caption_settles(pairs, providers.span_provider).select("item_id", "doc_id")


# --- streams ----------------------------------------------------------------------------------------------------


def _stream(name):
    def run(spark, d):
        from benchvary.streaming import answer_log

        return getattr(answer_log, name)(spark, d)

    QUERIES[f"log_{name}"] = run


for _n in ("tumbling", "sliding", "session", "dedup", "late_rows", "running_contamination", "with_registry", "regenerate_state", "interval_join"):
    _stream(_n)
