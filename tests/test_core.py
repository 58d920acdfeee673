"""Core queries against DuckDB, and the protocol's invariants."""

import pytest
from pyspark.sql import functions as F

from benchvary import api
from benchvary.functions import hashing
from benchvary.functions.text import parse_choice, parse_yes_no, token_f1
from benchvary.operators import answering, contamination, edits, judge, providers
from benchvary.plans import compose, oracle, queries
from benchvary.sources import carriers
from tests.compare import connect, mismatch

#: Twins that take long at this scale: scores of many compositions. tests/compare.py runs them all.
SLOW = {
    "items_presence", "items_attribute", "items_interaction", "items_text", "contam_text_rate_shingle", "judge_attempts", "judge_acceptance_cumulative", "fallback_share", "grid_axes", "grid_monotonicity",
    "edition_diversity", "task_sensitivity", "rank_shift", "memorisation_gap", "length_effect", "variant_examples", "single_image_deltas", "single_text_scores", "paired_grid_scores", "hard_ladder_scores",
    "contam_text_two_denominators", "contam_reduction", "judge_composite", "judge_verdicts", "judge_rounds", "edition_refresh", "stack_order_effect", "ladder_steps", "direction_check", "score_bounds",
    "noise_context", "context_after", "hint_context", "variant_distance", "cost_report", "answer_preserved", "single_image_scores",
    "extreme_scores_closed", "model_average", "fluctuation_by_level", "leaderboard", "score_cube", "scores_wide", "score_ci", "ratio_ablation", "ratio_steps", "task_breakdown",
}
FAST = sorted({*oracle.ORACLE} - SLOW | {"judge_verdicts", "noise_context", "direction_check", "contam_reduction"})


@pytest.mark.parametrize("name", FAST)
def test_against_duckdb(spark, sf, name):
    assert mismatch(spark, connect(sf), sf, queries.QUERIES[name], oracle.ORACLE[name]) == ""


def test_no_answer_breaks(spark, sf):
    row = queries.QUERIES["answer_preserved"](spark, sf).first()
    assert row["n"] > 0 and row["hidden"] == 0 and row["removed"] == 0


def test_declared_directions_hold(spark, sf):
    for row in queries.QUERIES["direction_check"](spark, sf).collect():
        assert row["agree"] == row["cells"], row


def test_editions_and_memorisation_take_all_items(spark, sf):
    i = carriers.items(spark, sf)
    n = i.count()
    assert carriers.sampled(i).count() < n
    assert queries.QUERIES["edition_refresh"](spark, sf).count() == 3 * n
    full = answering.answers(edits.edited(i), answering.spec_table(spark, compose.EXTREMES[:2]), answering.model_table(spark)).groupBy("variant_id").agg(answering.prob("correct").alias("p"))
    assert {r["variant_id"]: r["honest"] for r in queries.QUERIES["memorisation_gap"](spark, sf).collect()} == {r["variant_id"]: r["p"] for r in full.collect()}


def test_seeing_is_monotone(spark, sf):
    specs = (compose.VANILLA, *(compose.spec((e,)) for e in ("V1", "V2", "V3")))
    i = carriers.sampled(carriers.items(spark, sf))
    a = answering.answers(edits.edited(i), answering.spec_table(spark, specs), answering.model_table(spark)).groupBy("model", "item_id").pivot("variant_id", ["vanilla", "V1", "V2", "V3"]).max("sees")
    assert a.where("V1 > vanilla or V3 > vanilla or V2 < vanilla").isEmpty()


def test_ladder_and_ratio_decline(spark, sf):
    steps = [r["mean_accuracy"] for r in queries.QUERIES["ladder_steps"](spark, sf).orderBy("n_hard").collect()]
    assert steps == sorted(steps, reverse=True)
    ratio = [r["mean_accuracy"] for r in queries.QUERIES["ratio_ablation"](spark, sf).where("variant_id <> 'vanilla'").orderBy("variant_id").collect()]
    assert ratio == sorted(ratio, reverse=True)


def test_candidates_find_all_planted(spark, sf):
    e, t = carriers.eval_vectors(spark, sf), carriers.train_vectors(spark, sf)
    exact = {(r[0], r[1]) for r in contamination.image_contamination(e, t).select("eval_id", "train_id").collect()}
    for how in ("lsh", "cells"):
        found = {(r[0], r[1]) for r in contamination.image_contamination(e, t, strategy=how).select("eval_id", "train_id").collect()}
        assert found <= exact and len(found) >= 0.9 * len(exact)


def test_contamination_falls(spark, sf):
    rows = queries.QUERIES["contam_reduction"](spark, sf).collect()
    assert all(r["varied"] <= r["static"] for r in rows) and any(r["reduction"] > 0 for r in rows)


def test_judge_rounds_equal_attempts_at_once(spark, sf):
    one = {(r["attempt"], r["fallback"]): r["n"] for r in queries.QUERIES["judge_attempts"](spark, sf).where("strategy = 'V1'").collect()}
    assert {(r["attempt"], r["fallback"]): r["n"] for r in queries.QUERIES["judge_rounds"](spark, sf).collect()} == one


def test_samples_and_order(spark, sf):
    bench = api.Benchmark.from_scenes(spark, sf)
    n = bench.items.count()
    first, second = (bench.samples(s) for s in (("V1", "V3", "L1", "L4"), ("V3", "V1")))
    assert first.count() == n == second.count() and set(first.select("canvas").distinct().collect()[0]) == {1500}
    box = lambda df: df.selectExpr("item_id", "get(filter(scene, o -> o.sn = 0), 0) as b").where("b is not null")
    assert box(first).where("b.x0 < 250 or b.x0 > 1250").isEmpty() and not box(second).where("b.x0 < 250").isEmpty()
    plain = bench.samples(())
    moved = first.join(plain.selectExpr("item_id", "scene as old", "question as asked"), "item_id")
    assert moved.where("size(scene) - size(old) not in (0, 1) or fallbacks < 0 or question = asked").isEmpty()
    scores = api.report(api.evaluate(bench.sampled().vary(api.HARDEST, api.EASIEST)))
    assert scores.deltas().where("variant_id = 'V1+L4' and delta > 0").isEmpty() and not spark.table("scores").isEmpty()
    again = bench.refresh(1).samples(("V1",)).join(bench.samples(("V1",)).selectExpr("item_id", "scene as other"), "item_id")
    assert again.where("scene = other").count() < 0.2 * n


def test_providers_ask_each_prompt_once(spark):
    def shout(batch):
        return batch["q"].str.upper()

    df = spark.createDataFrame([(1, "a"), (2, "a"), (3, "b")], "k int, q string")
    out, store = providers.cached(df, shout, ("q",), "raw")
    assert {(r["k"], r["raw"]) for r in out.collect()} == {(1, "A"), (2, "A"), (3, "B")} and store.count() == 2
    out, store = providers.cached(df.union(spark.createDataFrame([(4, "c")], "k int, q string")), shout, ("q",), "raw", store)
    assert store.count() == 3 and providers.scored(out.withColumnRenamed("q", "reference")).agg({"correct": "sum"}).first()[0] == 4


def test_expansion_by_area(spark):
    df = spark.range(1)
    assert df.select(edits.canvas_side(2.25, "area")).first()[0] == 1500 == df.select(edits.canvas_side(1.5)).first()[0]


def test_files_round_trip(spark, tmp_path):
    from benchvary.sources.tables import read_answers, register_views, write_variants

    rows = spark.createDataFrame([("M1", "vanilla", "i1", "(A)"), ("M1", "V1", "i1", "B")], "model string, variant_id string, item_id string, raw string")
    for fmt in ("parquet", "orc", "json", "csv"):
        rows.write.format(fmt).option("header", True).save(f"{tmp_path}/{fmt}")
        assert read_answers(spark, f"{tmp_path}/{fmt}", fmt).exceptAll(rows).isEmpty()
    write_variants(rows, f"{tmp_path}/v")
    write_variants(rows.where("variant_id = 'V1'").withColumn("raw", F.lit("C")), f"{tmp_path}/v")
    assert {r["raw"] for r in spark.read.parquet(f"{tmp_path}/v").collect()} == {"(A)", "C"}
    register_views(spark, "/root/testdata/sf0.001")
    assert spark.sql("select count(*) from region").first()[0] > 0


def test_parsing(spark):
    df = spark.createDataFrame([("(B) it is", "Yes, there is", "a b c", "a b")], "c string, y string, p string, q string")
    row = df.select(parse_choice(df.c), parse_yes_no(df.y), token_f1(df.p, df.q)).first()
    assert row[0] == "B" and row[1] == "yes" and abs(row[2] - 80.0) < 1e-9


def test_grid_has_twelve_cells():
    assert len({s[0] for s in compose.GRID}) == 12 and compose.HARDEST[0] == "V1+L4"


def test_sliding_windows_take_the_nearest_second(spark, tmp_path):
    import duckdb

    sql = "SELECT k AS event_id, ts, k AS user_id, 'click' AS event_type, 10.0 * k AS value, '{}' AS props FROM (VALUES (1, TIMESTAMP '2024-01-08 17:59:59.7'), (2, TIMESTAMP '2024-01-08 17:59:59.5'), (3, TIMESTAMP '2024-01-08 17:59:58.5'), (4, TIMESTAMP '2024-01-08 18:00:00.2')) AS t(k, ts)"
    duckdb.sql(f"COPY ({sql}) TO '{tmp_path}/events.parquet'")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{tmp_path}/events.parquet'")
    assert mismatch(spark, con, str(tmp_path), queries.QUERIES["log_sliding"], oracle.ORACLE["log_sliding"]) == ""


def _plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_salted_join_is_not_broadcast(spark, sf):
    assert "BroadcastHashJoin" not in _plan(queries.QUERIES["op_salted_join"](spark, sf))


@pytest.mark.parametrize("name", ["op_specs", "op_udtf_specs", "paired_grid_variants"])
def test_compositions_are_dealt_over_orders(spark, sf, name):
    df = queries.QUERIES[name](spark, sf)
    assert "orders.parquet" in _plan(df) and "scenes" in df.columns


def test_md5_of_many_keys(spark):
    keys = [f"presence-{k}" for k in range(300)] + ["", "\u00e9", "x" * 47, "x" * 48, "y" * 200]
    df = spark.createDataFrame([(k,) for k in keys], "key string")
    many = df.select("key", hashing.stable_buckets(F.col("key"), {"a|x": 850, "b": 7}, 3, 2).alias("m"))
    one = F.array(*[hashing.stable_bucket(n, *salts, F.col("key"), F.lit(k)) for salts, n in ((("a", "x"), 850), (("b",), 7)) for k in (2, 3)])
    assert many.count() == len(keys) and many.where(F.col("m") != one).isEmpty()


def test_first_free_name(spark):
    df = spark.createDataFrame([(k, ["c", f"{k % 5}"] if k else list("0123abc")) for k in range(50)] + [(None, [])], "key long, held array<string>").withColumn("pool", F.array(*map(F.lit, "0123abc")))
    free = F.transform(F.array_except("pool", "held"), lambda x: F.struct(hashing.stable_hash("n", F.col("key"), x), x.alias("x")))
    rows = df.select("key", hashing.first_free(F.col("key"), F.col("held"), F.col("pool")).alias("got"), F.array_min(free)["x"].alias("want")).collect()
    assert len(rows) == 51 and all(r["got"] == (None if r["key"] is None else r["want"]) for r in rows)


def test_additions_hash_in_batches(spark, sf):
    assert _plan(edits.propose_additions(carriers.items(spark, sf)).select("tries")).count("ArrowEvalPython") == 2  # absent names, attempts


@pytest.mark.parametrize("name", ["edition_refresh", "edition_diversity"])
def test_editions_make_items_once(spark, sf, name):
    assert _plan(queries.QUERIES[name](spark, sf)).count("lineitem.parquet") == 1


def test_judge_in_rows_equals_the_general_one(spark, sf):
    i, scenes = carriers.items(spark, sf).limit(400).cache(), queries._scenes(spark, sf)
    slow = judge.generate_with_judge(judge.proposals(i, edits.propose_noise(i.select("item_id", "task", "scene_id", "name"), *scenes)))
    fast = judge.first_accepted(i, *scenes)
    assert fast.exceptAll(slow).isEmpty() and slow.exceptAll(fast).isEmpty() and fast.count() > 2000
    i.unpersist()


def test_judge_rounds_read_what_is_open(spark, sf):
    assert "lineitem.parquet" not in _plan(queries.QUERIES["judge_rounds"](spark, sf))


@pytest.mark.parametrize("name", ["context_after", "variant_examples"])
def test_context_comes_without_a_join_of_items(spark, sf, name):
    assert "Join" not in _plan(queries.QUERIES[name](spark, sf))


def test_composite_counts_bits_of_both_sides(spark, sf):
    pairs = [("V1", "L1"), ("V2", "L4"), ("V3", "L4")]
    i, (scenes, largest) = carriers.items(spark, sf).limit(400).cache(), queries._scenes(spark, sf)
    said = {}
    for r in judge.proposals(i, edits.propose_noise(i.select("item_id", "task", "scene_id", "name"), scenes, largest)).collect():
        said.setdefault((r["item_id"], r["strategy"]), {})[r["k"]] = r["ok"]
    want = {}
    for a, b in pairs:
        for x in {k for k, _ in said}:
            p, q = said.get((x, a), {}), said.get((x, b), {})
            both = sorted(p.keys() & q.keys())
            if both:
                least = lambda ok: min((k for k in both if ok(k)), default=None)  # noqa: E731, B023
                fa, fb = least(lambda k: p[k]), least(lambda k: q[k])  # noqa: B023
                for mode, k in (("joint", least(lambda k: p[k] and q[k])), ("each", None if None in (fa, fb) else max(fa, fb))):  # noqa: B023
                    n, ok, calls = want.get((f"{a}+{b}", mode), (0, 0, 0))
                    want[f"{a}+{b}", mode] = (n + 1, ok + (k is not None), calls + (k or 5))
    assert {(r["pair"], r["mode"]): (r["n"], r["accepted"], r["calls"]) for r in judge.composite(i, scenes, largest, pairs).collect()} == want
    i.unpersist()


def test_length_effect_answers_once(spark, sf):
    assert _plan(queries.QUERIES["length_effect"](spark, sf)).count("lineitem.parquet") == 1
