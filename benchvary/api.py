"""The library in a few calls.

    bench = Benchmark.from_scenes(spark, folder)
    run = evaluate(bench.vary(("V1", "L4")))
    report(run).deltas(); report(run).by_task(); report(run).bounds()
    contamination_report(evaluation_vectors, training_vectors)

Tables are registered as the views items, variants, answers, scores and rates.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from benchvary.operators import answering, contamination, edits, samples
from benchvary.plans import compose
from benchvary.session import materialize
from benchvary.sources import carriers
from benchvary.sources.tables import read_table

HARDEST, EASIEST, VANILLA = ("V1", "L4"), ("V2", "L3"), ()


@dataclass
class Benchmark:
    """Items of a static benchmark and the variants drawn from it; edited items and samples are made once (store)."""

    spark: SparkSession
    items: DataFrame
    scenes: DataFrame
    largest: int
    specs: list[tuple[str, ...]] = field(default_factory=lambda: [VANILLA])
    edition: int = 0
    store: dict = field(default_factory=dict)

    @classmethod
    def from_scenes(cls, spark: SparkSession, folder: str) -> Benchmark:
        scenes = carriers.scene_objects(spark, folder).groupBy("scene_id").agg(F.array_sort(F.collect_list(F.struct("sn", "name"))).alias("objs"))
        largest = read_table(spark, folder, "orders").agg(F.coalesce(F.max("o_orderkey"), F.lit(0))).first()[0]
        items = materialize(carriers.items(spark, folder), "items")
        items.createOrReplaceTempView("items")
        return cls(spark, items, scenes, largest)

    def sampled(self, percent: dict[str, int] | None = None) -> Benchmark:
        return Benchmark(self.spark, carriers.sampled(self.items, percent), self.scenes, self.largest, list(self.specs), self.edition)

    def refresh(self, edition: int) -> Benchmark:
        """Another edition: the same items, drawn anew."""
        return Benchmark(self.spark, self.items, self.scenes, self.largest, list(self.specs), edition)

    def vary(self, *specs: tuple[str, ...]) -> Benchmark:
        """With these compositions beside the static form."""
        return Benchmark(self.spark, self.items, self.scenes, self.largest, [VANILLA, *(s for s in specs if s)], self.edition, self.store)

    def edited(self) -> DataFrame:
        if ("edited", self.edition) not in self.store:
            self.store["edited", self.edition] = materialize(edits.edited(self.items, self.edition), "edited")
        return self.store["edited", self.edition]

    def samples(self, spec: tuple[str, ...]) -> DataFrame:
        """The varied samples themselves: scene, canvas and question of every item."""
        if (spec, self.edition) not in self.store:
            made = samples.apply_spec(self.items, spec, self.scenes, self.largest, self.edition).withColumn("variant_id", F.lit("+".join(spec) or "vanilla"))
            self.store[spec, self.edition] = materialize(made, "samples")
        out = self.store[spec, self.edition]
        out.createOrReplaceTempView("variants")
        return out


def evaluate(bench: Benchmark, models: tuple = answering.MODELS) -> DataFrame:
    """Answers of every model to every variant."""
    specs = tuple(compose.spec(s) for s in bench.specs)
    out = materialize(answering.answers(bench.edited(), answering.spec_table(bench.spark, specs), answering.model_table(bench.spark, models)), "answers")
    out.createOrReplaceTempView("answers")
    return out


@dataclass
class Report:
    answers: DataFrame

    def scores(self) -> DataFrame:
        out = answering.accuracy(self.answers)
        out.createOrReplaceTempView("scores")
        return out

    def deltas(self) -> DataFrame:
        return answering.deltas(self.scores())

    def by_task(self) -> DataFrame:
        return answering.model_average(answering.accuracy(self.answers, ("model", "task", "variant_id")), ("task", "variant_id"))

    def bounds(self) -> DataFrame:
        return answering.bounds(self.scores())

    def intervals(self) -> DataFrame:
        return answering.with_interval(self.scores())

    def leaderboard(self) -> DataFrame:
        return answering.leaderboard(self.scores())


def report(answers: DataFrame) -> Report:
    return Report(answers)


def contamination_report(evals: DataFrame, trains: DataFrame, threshold: float = contamination.THRESHOLD) -> DataFrame:
    """Rates of each evaluation set against each training set, by images."""
    out = contamination.rate_grid(contamination.by_training_set(contamination.image_contamination(evals, trains, threshold), trains, evals))
    out.createOrReplaceTempView("rates")
    return out
