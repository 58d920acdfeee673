"""Overlap between evaluation and training data, by images and by images with text."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from benchvary.functions.text import cosine, normalize_answer, word_list, word_shingles

THRESHOLD = 0.9
#: Bytes up to which the evaluation side is sent to all workers; larger ones go block by block.
BROADCAST_BYTES = 64 << 20
SETS = ("in_xl", "in_m", "in_cap")


def _units(x: np.ndarray) -> np.ndarray:
    """Rows at length one; zero rows become not-a-number, which is like nothing."""
    with np.errstate(invalid="ignore", divide="ignore"):
        return x / np.linalg.norm(x, axis=1, keepdims=True)


def similar_pairs(evals: DataFrame, trains: DataFrame, threshold: float, best_too: bool = False) -> DataFrame:
    """(eval_id, train_id, sim, is_best) of every pair above threshold, exact, in one scan of the training side.

    The evaluation side is the query set: its size is checked, and beyond the bound it is sent in blocks. With
    best_too each partition adds the best pair of each evaluation vector, whatever its similarity. Vectors that are null
    or of another length than the evaluation side's are like nothing, and so are zero vectors.
    """
    spark = evals.sparkSession
    size = evals.agg(F.max(F.size("ev")).alias("dims")).first()["dims"] or 0
    evals = evals.where((F.size("ev") == size) & ~F.exists("ev", lambda v: v.isNull()))
    trains = trains.where((F.size("tv") == size) & ~F.exists("tv", lambda v: v.isNull()))
    n = evals.count()
    width = max(8, 8 * size)
    blocks = max(1, -(-n * width // BROADCAST_BYTES))
    schema = "eval_id long, train_id string, sim double, is_best boolean"
    out = None
    for b in range(blocks):
        rows = evals.where(F.pmod(F.col("eval_id"), F.lit(blocks)) == b).orderBy("eval_id").select("eval_id", "ev").collect() if blocks > 1 else evals.orderBy("eval_id").select("eval_id", "ev").collect()
        if not rows:
            continue
        x = np.array([r["ev"] for r in rows])
        sent = spark.sparkContext.broadcast((np.array([r["eval_id"] for r in rows]), _units(x)))

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            ids, x = sent.value
            best, who = np.full(len(ids), -2.0), np.full(len(ids), None, dtype=object)
            step = max(1, (64 << 20) // (8 * max(1, len(ids))))
            for batch in batches:
                for i in range(0, batch.num_rows, step):
                    part = batch.slice(i, step)
                    y = np.array(part.column(1).to_pylist(), dtype=np.float64)
                    sim = np.nan_to_num(x @ _units(y).T, nan=-2.0)
                    names = np.array(part.column(0).to_pylist(), dtype=object)
                    e, t = np.nonzero(sim > threshold)
                    yield pa.RecordBatch.from_arrays([pa.array(ids[e]), pa.array(names[t].tolist(), pa.string()), pa.array(sim[e, t]), pa.array(np.zeros(len(e), dtype=bool))], names=["eval_id", "train_id", "sim", "is_best"])
                    top = sim.argmax(axis=1)
                    value = sim[np.arange(len(ids)), top]
                    better = value > best
                    best, who = np.where(better, value, best), np.where(better, names[top], who)
            if best_too and (best > -2).any():
                ok = best > -2
                yield pa.RecordBatch.from_arrays([pa.array(ids[ok]), pa.array(who[ok].tolist(), pa.string()), pa.array(best[ok]), pa.array(np.ones(ok.sum(), dtype=bool))], names=["eval_id", "train_id", "sim", "is_best"])

        found = trains.select("train_id", "tv").mapInArrow(run, schema)
        out = found if out is None else out.unionByName(found)
    return out if out is not None else spark.createDataFrame([], schema)


def best_match(evals: DataFrame, trains: DataFrame) -> DataFrame:
    """(eval_id, sim): similarity to the nearest training vector; maxima are taken before the shuffle."""
    return similar_pairs(evals, trains, 2.0, True).groupBy("eval_id").agg(F.max("sim").alias("sim"))


def contaminated_ids(evals: DataFrame, trains: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """Semi-join form: evaluation ids alone."""
    hits = similar_pairs(evals, trains, threshold).select("eval_id").distinct()
    return evals.select("eval_id").join(hits, "eval_id", "left_semi")


def image_contamination(evals: DataFrame, trains: DataFrame, threshold: float = THRESHOLD, strategy: str = "exact") -> DataFrame:
    """(eval_id, train_id, sim) above threshold: exact scan, or candidates by hyperplane bands or coarse cells, then exact."""
    if strategy == "exact":
        return similar_pairs(evals, trains, threshold).select("eval_id", "train_id", "sim")
    if strategy == "lsh":
        bits = band_bits(trains.count())
        e, t = hyperplane_bands(evals, "eval_id", "ev", bits), hyperplane_bands(trains, "train_id", "tv", bits)
    else:
        centres = train_centroids(trains)
        if not len(centres):
            return similar_pairs(evals, trains, threshold).select("eval_id", "train_id", "sim")
        e, t = coarse_cells(evals, "eval_id", "ev", centres, PROBES), coarse_cells(trains, "train_id", "tv", centres, 1)
    cand = e.join(t, "band").select("eval_id", "train_id").distinct()
    both = cand.join(evals.select("eval_id", "ev"), "eval_id").join(trains.select("train_id", "tv"), "train_id")
    return both.withColumn("sim", cosine(F.col("ev"), F.col("tv"))).where(F.col("sim") > threshold).select("eval_id", "train_id", "sim")


#: Cells that an evaluation vector probes.
PROBES = 8
#: Least recall that the bands are laid out for, at the threshold.
BAND_RECALL = 0.99


def band_bits(n: int) -> int:
    """Signs in a band: buckets grow with the training side, so that one holds some tens of vectors on average."""
    return int(min(24, max(8, np.ceil(np.log2(max(n, 1) / 32)))))


def band_count(bits: int, threshold: float = THRESHOLD) -> int:
    """Bands until a pair at the threshold agrees in one of them with probability BAND_RECALL."""
    agree = (1 - np.arccos(threshold) / np.pi) ** bits
    return int(np.ceil(np.log(1 - BAND_RECALL) / np.log(1 - agree)))


def hyperplane_bands(df: DataFrame, id_col: str, vec_col: str, bits: int, seed: int = 7) -> DataFrame:
    """(id, band): signs of random projections, cut into bands."""
    bands = band_count(bits)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = np.array(batch.column(1).to_pylist(), dtype=np.float64)
            planes = np.random.default_rng(seed).standard_normal((x.shape[1], bits * bands))
            sign = (x @ planes > 0).reshape(len(x), bands, bits)
            key = (sign * (1 << np.arange(bits))).sum(axis=2) + (np.arange(bands) << bits)
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(np.repeat(np.arange(len(x)), bands))), pa.array(key.ravel())], names=[id_col, "band"])

    kind = df.schema[id_col].dataType.simpleString()
    return df.select(id_col, vec_col).mapInArrow(run, f"{id_col} {kind}, band long")


#: Vectors that centroids are trained on, at most about; cells for each so many training vectors, at least and at most.
CENTROID_SAMPLE, CELL_ROWS, LEAST_CELLS, MOST_CELLS = 20_000, 200, 16, 4096


def train_centroids(trains: DataFrame, id_col: str = "train_id", vec_col: str = "tv", rounds: int = 8) -> np.ndarray:
    """Unit centroids by k-means on the sphere, over a bounded hash sample; their number grows with the table's rows."""
    n = trains.count()
    cells = int(min(MOST_CELLS, max(LEAST_CELLS, n // CELL_ROWS)))
    share = min(1.0, CENTROID_SAMPLE / max(n, 1))
    rows = trains.where(F.pmod(F.xxhash64(id_col), F.lit(1 << 20)) < int(share * (1 << 20)) + 1).select(F.xxhash64(id_col).alias("h"), vec_col).where(F.col(vec_col).isNotNull()).toPandas().sort_values("h")
    x = np.array([v for v in rows[vec_col] if len(v)], dtype=np.float64)
    if not len(x):
        return np.zeros((0, 0))
    x = x[np.isfinite(x).all(axis=1) & (np.linalg.norm(x, axis=1) > 0)]
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    c = x[: min(cells, len(x))].copy()
    for _ in range(rounds):
        own = (x @ c.T).argmax(axis=1)
        sums = np.zeros_like(c)
        np.add.at(sums, own, x)
        size = np.linalg.norm(sums, axis=1, keepdims=True)
        c = np.where(size > 0, sums / np.maximum(size, 1e-300), c)
    return c


def coarse_cells(df: DataFrame, id_col: str, vec_col: str, centres: np.ndarray, probes: int) -> DataFrame:
    """(id, band): the nearest centroids of each vector; training vectors go to one, evaluation vectors probe several."""
    sent = df.sparkSession.sparkContext.broadcast(centres)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = sent.value
        for batch in batches:
            x = np.array(batch.column(1).to_pylist(), dtype=np.float64)
            n = min(probes, len(c))
            near = np.argsort(-(x @ c.T), axis=1)[:, :n]
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(np.repeat(np.arange(len(x)), n))), pa.array(near.ravel())], names=[id_col, "band"])

    kind = df.schema[id_col].dataType.simpleString()
    return df.select(id_col, vec_col).mapInArrow(run, f"{id_col} {kind}, band long")


def by_training_set(pairs: DataFrame, trains: DataFrame, evals: DataFrame) -> DataFrame:
    """(eval_id, eval_set, train_set, hit): one row for each evaluation image and training set."""
    flags = pairs.join(trains.select("train_id", *SETS), "train_id").groupBy("eval_id").agg(*[F.max(s).alias(s) for s in SETS])
    wide = evals.select("eval_id", "eval_set").join(flags, "eval_id", "left")
    return wide.unpivot(["eval_id", "eval_set"], [*SETS], "train_set", "hit").withColumn("hit", F.coalesce("hit", F.lit(0)))


def rate_grid(flags: DataFrame) -> DataFrame:
    """Rate of each evaluation set against each training set, over distinct images."""
    return flags.groupBy("eval_set", "train_set").agg(F.count_distinct("eval_id").alias("n"), F.sum("hit").cast("long").alias("hits")).withColumn("rate", F.round(F.col("hits") / F.col("n"), 6))


def threshold_sweep(best: DataFrame, thresholds: tuple[float, ...]) -> DataFrame:
    """Share of evaluation images above each threshold, in one pass."""
    rows = best.select(F.explode(F.array(*[F.struct(F.lit(t).alias("threshold"), (F.col("sim") > t).cast("int").alias("hit")) for t in thresholds])).alias("x"))
    return rows.groupBy("x.threshold").agg(F.count("*").alias("n"), F.sum("x.hit").cast("long").alias("hits")).withColumn("rate", F.round(F.col("hits") / F.col("n"), 6))


def decided_by(caption: Column, answer: Column, how: str, least: float = 0.8, n: int = 8) -> Column:
    """Does the caption settle the answer? span: holds it; recall: most of its words; shingle: a run of n words."""
    if how == "span":
        return F.contains(normalize_answer(caption), normalize_answer(answer)) & (F.length(normalize_answer(answer)) > 0)
    if how == "recall":
        words = F.array_distinct(word_list(answer))
        return (F.size(words) > 0) & (F.size(F.array_intersect(words, word_list(caption))) >= least * F.size(words))
    return F.arrays_overlap(word_shingles(caption, n), word_shingles(answer, n))


#: Bytes of items that are sent to every worker at once.
ITEM_BYTES = 16 << 20


def verbatim_overlap(docs: DataFrame, items: DataFrame) -> DataFrame:
    """(item_id, doc_id) of every document that holds an item's whole text, by one automaton over all items.

    Items are the query set: they are dealt into parts by a hash so that each part has about ITEM_BYTES at most, and each
    part is one scan of the documents, whose texts are never shuffled. Null texts hold nothing; empty items are in all.
    """
    import ahocorasick

    spark = docs.sparkSession
    total = items.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    parts = max(1, -(-total // ITEM_BYTES))
    out = docs.where("text is not null").select("doc_id").crossJoin(items.where("text = ''").select("item_id")).select("item_id", "doc_id")
    id_kinds = [df.schema[c].dataType.simpleString() for df, c in ((items, "item_id"), (docs, "doc_id"))]
    for part in range(parts):
        rows = items.where(F.length("text") > 0).where(F.pmod(F.xxhash64("item_id"), F.lit(parts)) == part).select("item_id", "text").collect()  # about ITEM_BYTES
        by_text: dict[str, list] = {}
        for r in rows:
            by_text.setdefault(r["text"], []).append(r["item_id"])
        sent = spark.sparkContext.broadcast(by_text)

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            machine = ahocorasick.Automaton()
            for text, ids in sent.value.items():
                machine.add_word(text, ids)
            if sent.value:
                machine.make_automaton()
            for batch in batches:
                found, held = [], []
                for doc, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                    hits = {i for _, ids in machine.iter(text.as_py()) for i in ids} if sent.value else ()
                    found += hits
                    held += [doc] * len(hits)
                yield pa.RecordBatch.from_arrays([pa.array(found, batch_kinds[0]), pa.array(held, batch_kinds[1])], names=["item_id", "doc_id"])

        batch_kinds = [pa.int64() if k == "bigint" else pa.int32() if k == "int" else pa.string() for k in id_kinds]
        out = out.unionByName(docs.where("text is not null").select("doc_id", "text").mapInArrow(run, f"item_id {id_kinds[0]}, doc_id {id_kinds[1]}"))
    return out


def shared_runs(docs: DataFrame, items: DataFrame, n: int) -> DataFrame:
    """(item_id, doc_id, shared): how many different runs of n words of an item's plain text a document has.

    The items' runs are the query set, dealt into parts of about ITEM_BYTES by a hash; each part is one scan of the
    documents, from which only runs that some item has leave a worker.
    """
    from benchvary.session import materialize

    spark = docs.sparkSession
    runs = materialize(items.select("item_id", F.explode(word_shingles(F.col("text"), n)).alias("s")), "runs")
    total = runs.agg(F.coalesce(F.sum(F.octet_length("s")), F.lit(0))).first()[0]
    parts = max(1, -(-total // ITEM_BYTES))
    plain = docs.select("doc_id", F.coalesce(normalize_answer(F.col("text")), F.lit("")).alias("plain"))
    kind = docs.schema["doc_id"].dataType.simpleString()
    found = None
    for part in range(parts):
        sent = spark.sparkContext.broadcast({r["s"] for r in runs.where(F.pmod(F.xxhash64("s"), F.lit(parts)) == part).select("s").distinct().collect()})  # about ITEM_BYTES

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            wanted = sent.value
            firsts = {s.split(" ", 1)[0] for s in wanted}
            for batch in batches:
                held, said = [], []
                for k, text in enumerate(batch.column(1)):
                    w = text.as_py().split(" ")
                    own = {s for i in range(len(w) - n + 1) if w[i] in firsts and (s := " ".join(w[i : i + n])) in wanted}
                    said += own
                    held += [k] * len(own)
                yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(held, pa.int64())), pa.array(said, pa.string())], names=["doc_id", "s"])

        own = plain.mapInArrow(run, f"doc_id {kind}, s string")
        found = own if found is None else found.unionByName(own)
    return found.join(runs, "s").groupBy("item_id", "doc_id").agg(F.count_distinct("s").alias("shared"))
