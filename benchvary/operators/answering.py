"""Deterministic answerers and scoring.

An answerer sees the largest objects of a scene, up to its capacity and down to a share of the canvas. It answers
right what it sees and understands, and otherwise guesses by a hash of model and item, the same in every variant.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from benchvary.functions.hashing import stable_bucket
from benchvary.operators.edits import ADDED, LEXICON, PERSONAS, QUESTIONS, canvas_side
from benchvary.sources.carriers import NO_AREA

# Model, capacity, least share of the canvas in millionths, percent of words, percent of personas, cost of a sentence, gain of a fact.
MODELS = (
    ("M1", 3, 6000, 70, 70, 2, 1), ("M2", 3, 5000, 75, 75, 1, 1), ("M3", 4, 6000, 70, 80, 2, 2), ("M4", 4, 5000, 80, 75, 1, 1), ("M5", 4, 4000, 60, 60, 2, 0),
    ("M6", 5, 5000, 85, 85, 1, 1), ("M7", 5, 4000, 80, 80, 2, 2), ("M8", 6, 4000, 90, 90, 1, 1), ("M9", 7, 3000, 95, 90, 1, 1),
)
#: The closed model that only the last table has: like M9, but each irrelevant sentence costs it three objects.
EXTRA_MODEL = ("M10", 7, 3000, 95, 90, 3, 1)
SENTENCES = 2


#: Every word that names and their synonyms are made of.
VOCABULARY = tuple(sorted({w for word, others in LEXICON.items() for w in (word, *others)}))


def _knows_word(word: Column) -> Column:
    return stable_bucket(100, "w", F.col("model"), word) < F.col("vocab")


def _knows_persona(persona: Column, task: Column) -> Column:
    return stable_bucket(100, "p", F.col("model"), persona, task) < F.col("personas")


def model_table(spark: SparkSession, models: tuple = MODELS) -> DataFrame:
    """Models with what each one knows (words; personas by task): worked out here once, not again for every item."""
    df = spark.createDataFrame(list(models), "model string, cap int, floor_ppm int, vocab int, personas int, noise_cost int, hint_gain int")
    words = F.array(*[F.lit(w) for w in VOCABULARY])
    forms = F.array(*[F.struct(F.lit(p).alias("p"), F.lit(t).alias("t")) for p in PERSONAS for t in QUESTIONS])
    rows = df.withColumns({"words": F.filter(words, _knows_word), "forms": F.transform(F.filter(forms, lambda x: _knows_persona(x["p"], x["t"])), lambda x: F.concat_ws("|", x["p"], x["t"]))}).collect()  # one row a model
    return spark.createDataFrame(rows, "model string, cap int, floor_ppm int, vocab int, personas int, noise_cost int, hint_gain int, words array<string>, forms array<string>")


def spec_table(spark: SparkSession, specs: tuple, more: str = "") -> DataFrame:
    """Variants: id, edits on the image (added, removed, ratio), edits on the question (l1 to l4), number of hard edits; more: further columns of specs."""
    return spark.createDataFrame(list(specs), "variant_id string, v1 int, v2 int, ratio double, l1 int, l2 int, l3 int, l4 int, n_hard int" + (more and ", " + more))


def answers(edited: DataFrame, specs: DataFrame, models: DataFrame) -> DataFrame:
    """(model, variant_id, item_id, benchmark, task, sees, correct): items times two small tables, with no shuffle."""
    listed = lambda w: w.isin(*VOCABULARY)
    known = lambda col: F.when(listed(F.col(col)), F.array_contains("words", F.col(col))).otherwise(_knows_word(F.col(col)))
    form = F.concat_ws("|", "persona", "task")
    rows = edited.crossJoin(F.broadcast(models)).withColumns(
        {
            "knows_words": known("swap1") & known("swap2"),
            "knows_persona": F.when(F.col("persona").isin(*PERSONAS) & F.col("task").isin(*QUESTIONS), F.array_contains("forms", form)).otherwise(_knows_persona(F.col("persona"), F.col("task"))),
            "guess": (stable_bucket(F.col("n_options"), "g", F.col("model"), F.col("item_id")) == F.col("answer")).cast("int"),
        }
    ).drop("words", "forms")
    rows = rows.crossJoin(F.broadcast(specs))
    added = (F.col("v1") == 1) & (F.col("v1_fallback") == 0) & (F.lit(ADDED * ADDED) > F.col("least_area"))
    removed = (F.col("v2") == 1) & (F.col("v2_fallback") == 0) & (F.col("v2_rank") < F.col("worst_rank"))
    rank = F.col("worst_rank") + F.when(added, 1).otherwise(0) - F.when(removed, 1).otherwise(0)
    cap = F.greatest(F.lit(0), F.col("cap") - F.col("l4") * SENTENCES * F.col("noise_cost") + F.col("l3") * F.col("facts") * F.col("hint_gain"))
    side = canvas_side(F.col("ratio")).cast("long")
    big = (F.col("least_area") == NO_AREA) | (F.col("least_area").cast("long") * 1_000_000 >= F.col("floor_ppm") * side * side)
    understood = ((F.col("l1") == 0) | F.col("knows_words")) & ((F.col("l2") == 0) | (F.col("l2_fallback") == 1) | F.col("knows_persona"))
    sees = (rank <= cap) & big & understood
    return rows.select("model", "variant_id", "n_hard", "item_id", "benchmark", "task", sees.cast("int").alias("sees"), F.when(sees, 1).otherwise(F.col("guess")).alias("correct"))


def accuracy(answers: DataFrame, by: tuple[str, ...] = ("model", "benchmark", "variant_id")) -> DataFrame:
    """Percent of right answers; an unanswered item is wrong and stays in the denominator."""
    return answers.groupBy(*by).agg(F.count("*").alias("n"), F.round(100.0 * F.sum(F.coalesce("correct", F.lit(0))) / F.count("*"), 4).alias("accuracy"))


def deltas(scores: DataFrame) -> DataFrame:
    """Difference of each score to the same model's and benchmark's vanilla score."""
    base = scores.where("variant_id = 'vanilla'").select("model", "benchmark", F.col("accuracy").alias("vanilla"))
    return scores.where("variant_id <> 'vanilla'").join(F.broadcast(base), ["model", "benchmark"]).withColumn("delta", F.round(F.col("accuracy") - F.col("vanilla"), 4))


def model_average(scores: DataFrame, by: tuple[str, ...] = ("benchmark", "variant_id")) -> DataFrame:
    """Mean over models of their accuracies, not pooled over items."""
    return scores.groupBy(*by).agg(F.round(F.avg("accuracy"), 4).alias("mean_accuracy"))


def steps(means: DataFrame, order: str, by: str | None = None) -> DataFrame:
    """First and second differences along order: is the decrease getting steeper?"""
    w = Window.partitionBy(*([by] if by else [F.lit(1)])).orderBy(order)
    first = F.col("mean_accuracy") - F.lag("mean_accuracy").over(w)
    out = means.withColumn("step", F.round(first, 4))
    return out.withColumn("bend", F.round(F.col("step") - F.lag("step").over(w), 4))


def direction(deltas: DataFrame, registry: DataFrame) -> DataFrame:
    """Per strategy: cells whose sign agrees with the declared difficulty, or that are zero, among all."""
    d = deltas.join(F.broadcast(registry), deltas["variant_id"] == registry["strategy"])
    ok = F.when(F.col("difficulty") == "hard", F.col("delta") <= 0).otherwise(F.col("delta") >= 0)
    return d.groupBy("strategy", "difficulty").agg(F.count("*").alias("cells"), F.sum(ok.cast("long")).alias("agree"))


def bounds(scores: DataFrame) -> DataFrame:
    """Lowest and highest score of each model and benchmark over the variants, and their spread."""
    return scores.groupBy("model", "benchmark").agg(F.min("accuracy").alias("lowest"), F.max("accuracy").alias("highest"), F.round(F.max("accuracy") - F.min("accuracy"), 4).alias("spread"))


def leaderboard(scores: DataFrame) -> DataFrame:
    """Rank of each model within benchmark and variant."""
    w = Window.partitionBy("benchmark", "variant_id").orderBy(F.desc("accuracy"))
    return scores.withColumn("place", F.rank().over(w))


def agreement(verdicts: DataFrame, judged: str, truth: str) -> DataFrame:
    """Confusion counts, raw agreement and kappa of a judge against the truth."""
    j, t = F.col(judged).cast("int"), F.col(truth).cast("int")
    c = verdicts.agg(*[F.sum(((j == a) & (t == b)).cast("long")).alias(f"n{a}{b}") for a in (0, 1) for b in (0, 1)])
    n = F.col("n00") + F.col("n01") + F.col("n10") + F.col("n11")
    po = (F.col("n00") + F.col("n11")) / n
    pe = ((F.col("n00") + F.col("n01")) * (F.col("n00") + F.col("n10")) + (F.col("n10") + F.col("n11")) * (F.col("n01") + F.col("n11"))) / (n * n)
    return c.withColumns({"agreement": F.round(po, 6), "kappa": F.round(F.when(pe < 1, (po - pe) / (1 - pe)).otherwise(1.0), 6)})


def with_interval(scores: DataFrame) -> DataFrame:
    """Half width of the 95 % binomial interval."""
    p = F.col("accuracy") / 100
    return scores.withColumn("half_width", F.round(196.0 * F.sqrt(p * (1 - p) / F.col("n")), 4))


def prob(col: str) -> Column:
    return F.round(F.avg(F.col(col).cast("double")), 6)
