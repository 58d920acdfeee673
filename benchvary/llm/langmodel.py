"""Hashed maximum-entropy language model with a class-factored softmax.

P(word | history) = P(class | history) * P(group | class, history) * P(word | group). The class part is a log-linear
model over hashed features of the history's classes: the previous word's class (n-gram), the one before it (skip), and a
hash of both. The frequent words are classes of their own; all others fall into classes by a hash of their ending.
Inside a class the words form groups by their hash; the group part is a softmax over hashed features of the words
themselves: the previous word with the class (n-gram) and the word before it with the class (skip). The word part is
the word's share of its group, with one unseen word in each group.

All counts cover every training text. The class part's gradient steps run distributed over the table of (history,
class) counts, whose size is bounded by the number of classes; the group part's run over the texts, each of which is in
one of several steps. Only sums of gradients, bounded too, reach the driver. Scoring looks the frequent words up in
numpy batches; the rest of each text's words meet their counts in a shuffle join, so a vocabulary of any size works.

Defined results: null and empty texts consist of the end token alone; white space is ASCII white space; repeated rows
are scored and learnt from once each; extra columns are ignored; an empty table gives an empty result, and without
training texts all words are unseen.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from benchvary.llm import _text
from benchvary.session import materialize

ADD = 0.1
#: Frequent words that are classes of their own, classes of endings, buckets of hashed history pairs.
TOP, ENDINGS, PAIRS = 47, 64, 4096
CLASSES = TOP + ENDINGS + 1
END = CLASSES - 1
END_HASH = np.uint64(0x0123456789ABCDEF)
#: Frequent words that every worker looks up directly: 16 bytes each.
HEAD_WORDS = 1 << 20
#: Bytes of text handled at once where every token has a row of weights.
SLICE = 512 << 10
STEPS = 6
#: Groups of a class, a power of two; hashed word features; steps, between which the training texts are dealt.
GROUPS, FEATURES, WORD_STEPS = 8, 1 << 16, 8
_GROUP_SHIFT = np.uint64(65 - GROUPS.bit_length())


def _tokens(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes and ending classes of all words with an end token after each text, and tokens per text."""
    hashes, per_row, starts, ends = _text.words(data, offsets)
    low = _text._LOWER[data]
    last = low[ends - 1].astype(np.uint64) if len(ends) else np.zeros(0, np.uint64)
    before = np.where(ends - starts > 1, low[np.maximum(ends - 2, 0)], 0).astype(np.uint64) if len(ends) else last
    ending = TOP + (_text.mix(last * np.uint64(257) + before) % np.uint64(ENDINGS)).astype(np.int64)
    at = np.cumsum(per_row)
    return np.insert(hashes, at, END_HASH), np.insert(ending, at, END), per_row + 1


def _classes(hashes: np.ndarray, ending: np.ndarray, top: np.ndarray, rank: np.ndarray) -> np.ndarray:
    """The class of each token; top: sorted hashes of the words that are classes of their own."""
    if not len(top):
        return ending
    at = np.minimum(np.searchsorted(top, hashes), len(top) - 1)
    return np.where(top[at] == hashes, rank[at], ending)


def _history(cls: np.ndarray, per_row: np.ndarray) -> np.ndarray:
    """previous class * CLASSES + the one before it; before a text stands END."""
    one, two = np.full(len(cls), END), np.full(len(cls), END)
    one[1:], two[2:] = cls[:-1], cls[:-2]
    first = np.cumsum(per_row) - per_row
    one[first] = two[first] = END
    second = first[per_row > 1] + 1
    two[second] = END
    return one * CLASSES + two


def _word_features(hashes: np.ndarray, cls: np.ndarray, per_row: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows of the group part's weights for each token: the previous word and the one before it, each with the token's class."""
    one, two = np.full(len(hashes), END_HASH), np.full(len(hashes), END_HASH)
    one[1:], two[2:] = hashes[:-1], hashes[:-2]
    first = np.cumsum(per_row) - per_row
    one[first] = two[first] = END_HASH
    two[first[per_row > 1] + 1] = END_HASH
    c = cls.astype(np.uint64)
    return tuple((_text.mix(w * np.uint64(2 * k + 3) + c * np.uint64(0x9E3779B97F4A7C15) + np.uint64(k)) % np.uint64(FEATURES)).astype(np.int64) for k, w in enumerate((one, two)))


def _log_groups(weights: np.ndarray, bias: np.ndarray, cls: np.ndarray, features: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """(tokens, GROUPS): log P(group | class, history) of tokens whose class (from 0 on) has groups."""
    z = bias[cls] + weights[features[0]] + weights[features[1]]
    z -= z.max(axis=1, keepdims=True)
    return z - np.log(np.exp(z).sum(axis=1, keepdims=True))


def _group(hashes: np.ndarray) -> np.ndarray:
    return (hashes >> _GROUP_SHIFT).astype(np.int64)


def word_counts(texts: DataFrame) -> DataFrame:
    """(word, ending, c) over all rows of texts(text): hash, ending class and count of each token."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        size = 0

        def flush() -> pa.RecordBatch:
            word, ending, n = (np.concatenate(x) for x in zip(*held, strict=True))
            order = np.argsort(word, kind="stable")
            word, ending, n = word[order], ending[order], n[order]
            head = np.flatnonzero(np.concatenate([[True], word[1:] != word[:-1]]))
            return pa.RecordBatch.from_arrays([pa.array(word[head].view(np.int64)), pa.array(ending[head].astype(np.int32)), pa.array(np.add.reduceat(n, head))], names=["word", "ending", "c"])

        for batch in batches:
            for _, _, data, offsets in _text.slices(batch.column(0)):
                hashes, ending, _ = _tokens(data, offsets)
                word, at, n = np.unique(hashes, return_index=True, return_counts=True)
                held.append((word, ending[at], n))
                size += len(word)
                if size > 3_000_000:
                    yield flush()
                    held, size = [], 0
        if held:
            yield flush()

    return texts.mapInArrow(_text.released(run), "word long, ending int, c long").groupBy("word").agg(F.first("ending").alias("ending"), F.sum("c").alias("c"))


def history_counts(texts: DataFrame, top: np.ndarray, rank: np.ndarray) -> DataFrame:
    """(history, cls, n) over all rows of texts(text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells = np.zeros(CLASSES**3, dtype=np.int64)
        for batch in batches:
            for _, _, data, offsets in _text.slices(batch.column(0)):
                hashes, ending, per_row = _tokens(data, offsets)
                cls = _classes(hashes, ending, top, rank)
                key, n = np.unique(_history(cls, per_row) * CLASSES + cls, return_counts=True)
                cells[key] += n
        found = np.flatnonzero(cells)
        for i in range(0, len(found), 100_000):
            at = found[i : i + 100_000]
            yield pa.RecordBatch.from_arrays([pa.array((at // CLASSES).astype(np.int32)), pa.array((at % CLASSES).astype(np.int32)), pa.array(cells[at])], names=["history", "cls", "n"])

    return texts.mapInArrow(_text.released(run), "history int, cls int, n long").groupBy("history", "cls").agg(F.sum("n").alias("n"))


def _features(history: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows of the weight matrix: n-gram, skip, hashed pair."""
    pair = (_text.mix(history.astype(np.uint64) + np.uint64(7)) % np.uint64(PAIRS)).astype(np.int64)
    return history // CLASSES, CLASSES + history % CLASSES, 2 * CLASSES + pair


def _log_softmax(weights: np.ndarray, bias: np.ndarray, history: np.ndarray) -> np.ndarray:
    a, b, c = _features(history)
    z = weights[a] + weights[b] + weights[c] + bias
    z -= z.max(axis=1, keepdims=True)
    return z - np.log(np.exp(z).sum(axis=1, keepdims=True))


def _sparse_rows(grad: np.ndarray, mass: np.ndarray) -> Iterator[pa.RecordBatch]:
    """(f, g, m) of the features with mass, a few hundred to a batch."""
    found = np.flatnonzero(mass)
    for at in (found[i : i + 512] for i in range(0, len(found), 512)):
        rows = [g.tobytes() for g in grad[at].astype(np.float32)]
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(rows, pa.binary()), pa.array(mass[at])], names=["f", "g", "m"])


def train_classes(counts: DataFrame, steps: int = STEPS) -> tuple[np.ndarray, np.ndarray]:
    """Weights and bias of the class part, by distributed gradient steps over (history, cls, n)."""
    spark = counts.sparkSession
    rows = materialize(counts.groupBy("history").agg(F.collect_list("cls").alias("cls"), F.collect_list("n").alias("n")), "histories")
    size = (2 * CLASSES + PAIRS, CLASSES)
    totals = np.zeros(CLASSES)
    first = np.zeros((CLASSES, CLASSES))
    for r in counts.groupBy((F.col("history") / CLASSES).cast("int").alias("h"), "cls").agg(F.sum("n").alias("n")).toLocalIterator():  # at most CLASSES ** 2 rows
        first[r["h"], r["cls"]] += r["n"]
        totals[r["cls"]] += r["n"]
    bias = np.log((totals + 0.5) / (totals.sum() + 0.5 * CLASSES))
    weights = np.zeros(size)
    prior = np.exp(bias)
    weights[:CLASSES] = np.log((first + 8 * prior) / (first.sum(axis=1, keepdims=True) + 8)) - bias
    scale = np.zeros(size)
    for step in range(steps):
        sent = spark.sparkContext.broadcast((weights.astype(np.float32), bias.astype(np.float32)))

        def gradient(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            w, b = sent.value
            grad, mass = np.zeros(size), np.zeros(size[0])
            for batch in batches:
                history = batch.column(0).to_numpy().astype(np.int64)
                n = np.zeros((len(history), CLASSES))
                for i, (cls, c) in enumerate(zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True)):
                    n[i, cls] = c
                all_ = n.sum(axis=1, keepdims=True)
                g = n - np.exp(_log_softmax(w, b, history)) * all_
                for f in _features(history):
                    np.add.at(grad, f, g)
                    np.add.at(mass, f, all_[:, 0])
            yield from _sparse_rows(grad, mass)

        def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            grad, mass = np.zeros(size), np.zeros(size[0])
            for batch in batches:
                for f, g, m in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True):
                    grad[f] += np.frombuffer(g, dtype=np.float32)
                    mass[f] += m
            yield from _sparse_rows(grad, mass)

        out = "f long, g binary, m double"
        grad, mass = np.zeros(size), np.ones(size[0])
        for r in rows.mapInArrow(_text.released(gradient), out).repartition(8, "f").mapInArrow(add, out).collect():  # at most one row for each feature
            grad[r["f"]] = np.frombuffer(r["g"], dtype=np.float32)
            mass[r["f"]] = r["m"]
        expected = mass[:, None] * prior + 50.0
        move = grad / expected  # a step in the scale of each cell's expected count
        scale = 0.5 * scale + move
        weights = weights + np.clip(0.25 * scale, -1.0, 1.0)
        sent.unpersist()
    return weights, bias


def train_groups(texts: DataFrame, top: np.ndarray, rank: np.ndarray, bias: np.ndarray, steps: int = WORD_STEPS) -> np.ndarray:
    """Weights of the group part: each step takes the gradient over its share of the texts, all of which have their turn."""
    spark = texts.sparkSession
    weights = np.zeros((FEATURES, GROUPS), dtype=np.float32)
    dealt = texts.withColumn("turn", F.pmod(F.monotonically_increasing_id(), F.lit(steps)))
    for step in range(steps):
        sent = spark.sparkContext.broadcast((weights, bias.astype(np.float32)))

        def gradient(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            w, b = sent.value
            grad, mass = np.zeros((FEATURES, GROUPS), dtype=np.float32), np.zeros(FEATURES)
            for batch in batches:
                for _, _, data, offsets in _text.slices(batch.column(0), SLICE):
                    hashes, ending, per_row = _tokens(data, offsets)
                    cls = _classes(hashes, ending, top, rank)
                    features = _word_features(hashes, cls, per_row)
                    own = np.flatnonzero((cls >= TOP) & (cls < END))
                    if not len(own):
                        continue
                    features = tuple(f[own] for f in features)
                    g = -np.exp(_log_groups(w, b, cls[own] - TOP, features))
                    g[np.arange(len(own)), _group(hashes[own])] += 1
                    for f in features:
                        order = np.argsort(f, kind="stable")
                        head = np.flatnonzero(np.concatenate([[True], f[order][1:] != f[order][:-1]]))
                        grad[f[order][head]] += np.add.reduceat(g[order], head, axis=0)
                        mass += np.bincount(f, minlength=FEATURES)
            yield from _sparse_rows(grad, mass)

        def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            grad, mass = np.zeros((FEATURES, GROUPS), dtype=np.float32), np.zeros(FEATURES)
            for batch in batches:
                f = batch.column(0).to_numpy()
                np.add.at(grad, f, np.array([np.frombuffer(g, dtype=np.float32) for g in batch.column(1).to_pylist()]).reshape(len(f), GROUPS))
                np.add.at(mass, f, batch.column(2).to_numpy())
            yield from _sparse_rows(grad, mass)

        out = "f long, g binary, m double"
        grad, mass = np.zeros((FEATURES, GROUPS), dtype=np.float32), np.zeros(FEATURES)
        found = dealt.where(F.col("turn") == step).select("text").mapInArrow(_text.released(gradient), out).repartition(8, "f").mapInArrow(add, out).toArrow()  # at most one row for each feature
        if found.num_rows:
            at = found["f"].to_numpy()
            grad[at] = np.frombuffer(b"".join(found["g"].to_pylist()), dtype=np.float32).reshape(-1, GROUPS)
            mass[at] = found["m"].to_numpy()
        # a step in the scale of each cell's expected count, small for features that few texts have
        weights = np.clip(weights + np.clip(0.5 * grad / (mass[:, None] / GROUPS + 10.0), -0.5, 0.5), -4, 4).astype(np.float32)
        sent.unpersist()
    return weights


@dataclass
class HashedModel:
    """What scoring needs: all of it bounded but counts, which stays a table."""

    counts: DataFrame  # (word, ending, c)
    n: int
    v: int
    floor: int  # words with at least this count are in the head
    head: np.ndarray
    head_c: np.ndarray
    top: np.ndarray
    rank: np.ndarray
    log_class: np.ndarray  # log10 P(class | history), less log10 of the class's mass where it has no groups
    group_bias: np.ndarray
    group_weights: np.ndarray
    group_mass: np.ndarray  # log10 of the mass of (class, group)

    def tables(self) -> tuple:
        """What factors() needs."""
        return self.top, self.rank, self.log_class, self.group_bias.astype(np.float32), self.group_weights, self.group_mass


def factors(tables: tuple, hashes: np.ndarray, ending: np.ndarray, per_row: np.ndarray) -> np.ndarray:
    """log10 P(token | history) - log10(c + ADD) of each token."""
    top, rank, log_class, bias, weights, mass = tables
    cls = _classes(hashes, ending, top, rank)
    out = log_class[_history(cls, per_row), cls].astype(np.float64)
    own = np.flatnonzero((cls >= TOP) & (cls < END))
    if len(own):
        group = _group(hashes[own])
        features = tuple(f[own] for f in _word_features(hashes, cls, per_row))
        out[own] += _log_groups(weights, bias, cls[own] - TOP, features)[np.arange(len(own)), group] / np.log(10) - mass[cls[own] - TOP, group]
    return out


def fit(texts: DataFrame, head_words: int = HEAD_WORDS, steps: int = STEPS) -> HashedModel:
    """texts(text): all training texts."""
    counts = materialize(word_counts(texts), "word-counts")
    total = counts.agg(F.sum("c").alias("n"), F.count("*").alias("v")).first()
    n, v = int(total["n"] or 0), int(total["v"])
    end = np.int64(END_HASH.astype(np.int64))
    best = counts.where(F.col("word") != F.lit(int(end))).orderBy(F.desc("c"), "word").limit(TOP).select("word").collect()
    hashes = np.array([r["word"] for r in best], dtype=np.int64).view(np.uint64)
    order = np.argsort(hashes)
    top, rank = hashes[order], order.astype(np.int64)
    sizes = {r["b"]: r["n"] for r in counts.groupBy(F.floor(F.log2(F.col("c"))).alias("b")).agg(F.count("*").alias("n")).collect()}
    floor, held = 1 << 62, 0
    for b in sorted(sizes, reverse=True):
        if held + sizes[b] > head_words:
            break
        held, floor = held + sizes[b], 1 << b
    rows = counts.where(F.col("c") >= floor).select("word", "c").toArrow()  # at most head_words rows of 16 bytes
    word = rows["word"].to_numpy().view(np.uint64)
    order = np.argsort(word)
    # Mass of each class and group: its counts, ADD for each of its words, and ADD for one unseen word.
    is_top = F.col("word").isin([int(x) for x in hashes.view(np.int64)]) if len(hashes) else F.lit(False)
    mass = np.full(CLASSES, ADD)
    parts = np.full((ENDINGS, GROUPS), ADD)
    group = F.shiftrightunsigned("word", int(_GROUP_SHIFT)).cast("int")
    for r in counts.where(~is_top).groupBy("ending", group.alias("g")).agg(F.sum(F.col("c") + ADD).alias("m")).collect():  # at most CLASSES * GROUPS rows
        if r["ending"] == END:
            mass[END] += r["m"]
        else:
            parts[r["ending"] - TOP, r["g"]] += r["m"]
    if len(hashes):
        own = {r["word"]: r["c"] for r in counts.where(is_top).select("word", "c").collect()}
        for k, h in enumerate(hashes.view(np.int64)):
            mass[k] = own[int(h)] + ADD
    mass[TOP:END] = 1.0  # the groups carry it
    weights, bias = train_classes(history_counts(texts, top, rank), steps)
    group_bias = np.log(parts / parts.sum(axis=1, keepdims=True))
    group_weights = train_groups(texts, top, rank, group_bias)
    table = np.empty((CLASSES * CLASSES, CLASSES), dtype=np.float32)
    for i in range(0, len(table), 4096):
        at = np.arange(i, min(i + 4096, len(table)))
        table[at] = _log_softmax(weights, bias, at) / np.log(10) - np.log10(mass)
    return HashedModel(counts, n, v, floor, word[order], rows["c"].to_numpy()[order], top, rank, table, group_bias, group_weights, np.log10(parts))


def score(model: HashedModel, docs: DataFrame, keep: tuple[str, ...], text_col: str = "text") -> DataFrame:
    """The columns of keep with (n_tokens, n_known, train_tokens, base_score, score) for every row of docs."""
    sent = docs.sparkSession.sparkContext.broadcast((model.head, np.log10(model.head_c + ADD), model.tables()))
    key, body = "row_key", "body"
    while key in keep or body in keep:
        key, body = key + "_", body + "_"
    slim = docs.select(F.monotonically_increasing_id().alias(key), *keep, F.col(text_col).alias(body))
    schema = slim.drop(body).schema
    unseen = float(np.log10(ADD))
    width = len(keep) + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        head, logs, tables = sent.value
        for batch in batches:
            for i, j, data, offsets in _text.slices(batch.column(width), SLICE):
                hashes, ending, per_row = _tokens(data, offsets)
                row = np.repeat(np.arange(j - i), per_row)
                factor = np.bincount(row, factors(tables, hashes, ending, per_row), j - i)
                word, back = np.unique(hashes, return_inverse=True)
                if len(head):
                    at = np.minimum(np.searchsorted(head, word), len(head) - 1)
                    known = head[at] == word
                    value = np.where(known, logs[at], 0.0)
                else:
                    known, value = np.zeros(len(word), dtype=bool), np.zeros(len(word))
                sums = np.bincount(row, value[back], j - i)
                n_head = np.bincount(row, known[back], j - i).astype(np.int64)
                rest = np.flatnonzero(~known[back])
                tail_n = np.bincount(row[rest], minlength=j - i)
                ends = np.concatenate([[0], np.cumsum(tail_n)]).astype(np.int32)
                tail = pa.ListArray.from_arrays(pa.array(ends), pa.array(hashes[rest].view(np.int64)))
                yield pa.RecordBatch.from_arrays(
                    [*(batch.column(k).slice(i, j - i) for k in range(width)), pa.array(per_row.astype(np.int64)), pa.array(n_head), pa.array(sums), pa.array(factor), tail],
                    names=[key, *keep, "n_tokens", "n_head", "sums", "factor", "tail"],
                )

    out = schema
    for name, kind in (("n_tokens", "long"), ("n_head", "long"), ("sums", "double"), ("factor", "double"), ("tail", T.ArrayType(T.LongType()))):
        out = out.add(name, kind)
    parts = materialize(slim.mapInArrow(_text.released(run), out), "scores")
    # Words outside the head: each text's own, counted per text first, meet their counts.
    tail = parts.select(key, F.explode("tail").alias("word")).groupBy(key, "word").agg(F.count("*").alias("tf"))
    rare = model.counts.where(F.col("c") < model.floor).select("word", "c")
    met = tail.join(rare, "word", "left").groupBy(key).agg(
        F.sum(F.when(F.col("c").isNotNull(), F.col("tf")).otherwise(0)).alias("tail_known"),
        F.sum(F.col("tf") * F.coalesce(F.log10(F.col("c") + ADD), F.lit(unseen))).alias("tail_sums"),
    )
    whole = F.col("sums") + F.coalesce("tail_sums", F.lit(0.0))
    base = float(np.log10(model.n + ADD * (model.v + 1)))
    return parts.join(met, key, "left").select(
        *keep,
        "n_tokens",
        (F.col("n_head") + F.coalesce("tail_known", F.lit(0))).alias("n_known"),
        F.lit(model.n).cast("long").alias("train_tokens"),
        (whole - F.col("n_tokens") * F.lit(base)).alias("base_score"),
        (whole + F.col("factor")).alias("score"),
    )


def held_out(id_col: str = "doc_id", parts: int = 10, which: int = 0) -> Column:
    """True where crc32 of the id as text leaves the remainder which."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % parts == which, F.lit(False))
