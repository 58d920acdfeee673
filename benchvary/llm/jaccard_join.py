"""Set similarity join on word n-grams by token-combination prefixes.

Every document is the set of its distinct n-word shingles, as 64-bit hashes. A first scan counts all shingles of all
documents in hashed cells; the cell's count, in powers of two over the mean, is a shingle's class. Sets are ordered by
class, so frequent shingles come last and seldom stand in a prefix. Two sets with a Jaccard similarity of at least t
share a shingle within their prefixes (the first |S| - ceil(t|S|) + 1 ones), and share k of them within prefixes that
are k - 1 longer. Shingles that few prefixes hold are indexed alone; those that stay frequent there are indexed in
combinations of two, then three.
Every set also has a sketch: the parity of its members in each of 512 bins. Bins in which two sketches differ hold a
member of one set that the other lacks, so their number bounds the difference from below, and joins drop pairs that
differ too much while they make them. Candidates then meet their wide sketches, of at least as many bins as members;
what these leave is verified on whole sets. Neither bound can drop a similar pair.

Groups of copies never become all pairs: documents with equal sets are one node from the start; then every document
is verified against a few chosen members of each key it shares (stars), and only keys that still join different
components give further pairs, between those outside a key's main component and the rest. Keys that stay large at
the longest combination are dealt in blocks, so no task gets a whole key and the result is exact at any skew.

Defined results: null and empty texts, and texts without words, have an empty set and link with nothing; a text with
fewer words than n is one shingle; rows are told apart, so repeated rows are copies of each other, and rows that share
an id but not a text are two documents; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from benchvary.llm import _text
from benchvary.llm._graph import components
from benchvary.session import forget, materialize, modest_batches

#: Most documents of a key whose pairs are listed directly; beyond it the key is combined with others.
RARE = 4096
#: Longest combination; larger keys are then dealt block by block.
LONGEST = 3
#: Chosen members that every document of a key is compared with first.
STARS = 4
#: Documents of a block.
BLOCK = 4096
#: 64-bit words of a sketch.
SKETCH = tuple(f"s{i}" for i in range(8))
#: Cells in which shingles are counted, and cells that travel together.
CELLS, TOGETHER = 1 << 18, 1 << 12
#: Most nodes whose ids are sent to every worker (8 bytes each); more are joined.
SENT_NODES = 1 << 20
#: Bytes of text hashed at once.
SLICE = 512 << 10


def _least(n: np.ndarray, num: int, den: int) -> np.ndarray:
    """ceil(t * n) in whole numbers: the least overlap of a set of n with any that is similar to it."""
    return -(-n * num // den)


def _cell(tokens: np.ndarray) -> np.ndarray:
    return (tokens >> np.uint64(64 - CELLS.bit_length() + 1)).astype(np.int64)


def _sets(data: np.ndarray, offsets: np.ndarray, n_words: int, classes: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    hashes, per_row, _, _ = _text.words(data, offsets)
    tokens, count = _text.shingles(hashes, per_row, n_words)
    return _text.distinct(tokens, count, None if classes is None else classes[_cell(tokens)])


def shingle_classes(texts: DataFrame, n_words: int) -> np.ndarray:
    """The class (0 to 15) of each cell of shingles, from the counts of all shingles of texts(text).

    Every task sends its counts, of a fixed size, in parts; parts are summed where they meet, and the driver gets one
    row for each part.
    """

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells = None
        for batch in batches:
            for _, _, data, offsets in _text.slices(batch.column(0), SLICE):
                hashes, per_row, _, _ = _text.words(data, offsets)
                found = np.bincount(_cell(_text.shingles(hashes, per_row, n_words)[0]), minlength=CELLS)
                cells = found if cells is None else cells + found
        if cells is not None:
            parts = [x.astype("<i8").tobytes() for x in cells.reshape(-1, TOGETHER)]
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(parts))), pa.array(parts, pa.binary())], names=["part", "n"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for part, n in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                own = np.frombuffer(n.as_buffer(), dtype="<i8")
                sums[part] = own + sums[part] if part in sums else own
        if sums:
            yield pa.RecordBatch.from_arrays([pa.array(list(sums)), pa.array([x.tobytes() for x in sums.values()], pa.binary())], names=["part", "n"])

    out = "part long, n binary"
    cells = np.zeros((CELLS // TOGETHER, TOGETHER), dtype=np.int64)
    for r in texts.mapInArrow(_text.released(count), out).repartition(8, "part").mapInArrow(add, out).collect():  # CELLS / TOGETHER rows
        cells[r["part"]] = np.frombuffer(r["n"], dtype="<i8")
    over = cells.ravel() / max(cells.mean(), 1)
    return np.clip(np.log2(np.maximum(over, 1)), 0, 15).astype(np.uint8)


def _parities(tokens: np.ndarray, per_row: np.ndarray) -> np.ndarray:
    """(rows, words) sketches: bit b is set where an odd number of a row's members fall into bin b."""
    bins = 64 * len(SKETCH)
    cell = np.repeat(np.arange(len(per_row)), per_row) * bins + (_text.mix(tokens + np.uint64(3)) % np.uint64(bins)).astype(np.int64)
    odd = (np.bincount(cell, minlength=len(per_row) * bins) & 1).astype(np.uint8)
    return np.packbits(odd).view(np.int64).reshape(len(per_row), len(SKETCH))


def _wide(tokens: np.ndarray, per_row: np.ndarray) -> pa.Array:
    """Sketches with at least as many bins as a row has members, a power of two, so that longer ones fold onto shorter ones."""
    words = 1 << np.ceil(np.log2(np.maximum(per_row, 64) / 64)).astype(np.int64)
    first = np.cumsum(words) - words
    at = _text.mix(tokens + np.uint64(5)) & np.repeat(64 * words - 1, per_row).astype(np.uint64)
    odd = (np.bincount(at.astype(np.int64) + np.repeat(64 * first, per_row), minlength=64 * int(words.sum())) & 1).astype(np.uint8)
    return _text.binary(np.packbits(odd).view(np.uint64), words)


def _lists(values: np.ndarray, per_row: np.ndarray) -> pa.Array:
    ends = np.concatenate([[0], np.cumsum(per_row)]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(values.view(np.int64)))


def shingle_sets(docs: DataFrame, n_words: int, num: int, den: int, classes: Broadcast, extra: int = 0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text_key, n_shingles, k1, k2, head, wide, s0, ...): a hash of the text, the set's size, a 128-bit key of the whole set, its prefix with extra more, its sketches."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, data, offsets in _text.slices(batch.column(1), SLICE):
                own, n = _sets(data, offsets, n_words, classes.value)
                first = np.concatenate([[0], np.cumsum(n)])
                sums = [np.concatenate([np.zeros(1, np.uint64), np.cumsum(_text.mix(own + np.uint64(salt)), dtype=np.uint64)]) for salt in (1, 0x5851F42D4C957F2D)]
                k1, k2 = (_text.mix(s[first[1:]] - s[first[:-1]] + n.astype(np.uint64)).view(np.int64) for s in sums)
                length = np.minimum(n, n - _least(n, num, den) + 1 + extra)
                at = np.repeat(first[:-1] - np.concatenate([[0], np.cumsum(length)])[:-1], length) + np.arange(length.sum())
                sketch = np.ascontiguousarray(_parities(own, n).T)
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(i, j - i), batch.column(2).slice(i, j - i), pa.array(n.astype(np.int64)), pa.array(k1), pa.array(k2), _lists(own[at], length), _wide(own, n), *map(pa.array, sketch)],
                    names=["doc_id", "text_key", "n_shingles", "k1", "k2", "head", "wide", *SKETCH],
                )

    out = "doc_id long, text_key long, n_shingles long, k1 long, k2 long, head array<long>, wide binary, " + ", ".join(f"{c} long" for c in SKETCH)
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"), F.xxhash64(text_col).alias("text_key")).mapInArrow(_text.released(run), out)


def _with_nodes(docs: DataFrame, rows: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(node, text) of the rows(doc_id, k1, node) that stand for a set: their ids, to be told from repeated ids by k1."""
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return slim.join(F.broadcast(rows) if rows.count() <= SENT_NODES else rows, "doc_id")


def _whole_sets(docs: DataFrame, wanted: DataFrame, n_words: int, id_col: str, text_col: str) -> DataFrame:
    """(node, tokens) for the wanted(doc_id, node, k1): their whole sets, from their texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, data, offsets in _text.slices(batch.column(2), SLICE):
                own, n = _sets(data, offsets, n_words)
                first = np.concatenate([[0], np.cumsum(n)])
                sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(_text.mix(own + np.uint64(1)), dtype=np.uint64)])
                k1 = _text.mix(sums[first[1:]] - sums[first[:-1]] + n.astype(np.uint64)).view(np.int64)
                right = pa.array(k1 == batch.column(1).slice(i, j - i).to_numpy())  # another row with this id has another set
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), _lists(own, n)], names=["node", "tokens"]).filter(right)

    texts = _with_nodes(docs, wanted, id_col, text_col).select("node", "k1", "text")
    return texts.mapInArrow(_text.released(run), "node long, tokens array<long>").dropDuplicates(["node"])


def _similar(pairs: DataFrame, sets: DataFrame, num: int, den: int) -> DataFrame:
    """(a, b) of the pairs whose whole sets are similar; a popular end is split by the skew join."""
    left = sets.select(F.col("node").alias("a"), F.col("tokens").alias("ta"))
    right = sets.select(F.col("node").alias("b"), F.col("tokens").alias("tb"))
    common = F.size(F.array_intersect("ta", "tb")).cast("long")
    return pairs.join(left, "a").join(right, "b").where(den * common >= num * (F.size("ta") + F.size("tb") - common)).select("a", "b")


def _plausible(pairs: DataFrame, heads: DataFrame, num: int, den: int) -> DataFrame:
    """Pairs whose wide sketches, the longer one folded to the length of the shorter, don't differ too much."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.column(2).to_numpy() + batch.column(3).to_numpy()
            differ = np.zeros(batch.num_rows, dtype=np.int64)
            for k, (x, y) in enumerate(zip(batch.column(4), batch.column(5), strict=True)):
                a, b = np.frombuffer(x.as_buffer(), dtype=np.uint64), np.frombuffer(y.as_buffer(), dtype=np.uint64)
                m = min(len(a), len(b))
                differ[k] = np.bitwise_count(np.bitwise_xor.reduce(a.reshape(-1, m)) ^ np.bitwise_xor.reduce(b.reshape(-1, m))).sum()
            yield batch.select([0, 1]).filter(pa.array((den + num) * differ <= (den - num) * n))

    left = heads.select(F.col("node").alias("a"), F.col("size").alias("na"), F.col("wide").alias("wa"))
    right = heads.select(F.col("node").alias("b"), F.col("size").alias("nb"), F.col("wide").alias("wb"))
    return pairs.join(left, "a").join(right, "b").select("a", "b", "na", "nb", "wa", "wb").mapInArrow(_text.released(run), "a long, b long")


def _fits(num: int, den: int, room: Column | None = None) -> Column:
    """Sizes of a pair that can be similar at all, room enough for what they must share, and sketches that don't differ too much."""
    x, y = F.col("x.size"), F.col("y.size")
    room = F.least(x, y) if room is None else room
    differ = sum((F.bit_count(F.col(f"x.{c}").bitwiseXOR(F.col(f"y.{c}"))) for c in SKETCH), F.lit(0))
    return (den * x >= num * y) & (den * y >= num * x) & (den * room >= num * (x + y - room)) & ((den + num) * differ <= (den - num) * (x + y))


def _unordered(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.least("x.node", "y.node").alias("a"), F.greatest("x.node", "y.node").alias("b")).distinct()


def _hubs(keys: DataFrame, heads: DataFrame) -> DataFrame:
    """(key, node, size, s0, ...): the members of each key that come first in each of a few fixed orders.

    An order is the node's hash with some bits turned, so the least value gives the hash back.
    """
    turned = [F.lit(0x1234567890ABCDEF * (2 * i + 1) & (1 << 63) - 1) for i in range(STARS)]
    least = [F.min(F.xxhash64("node").bitwiseXOR(t)).alias(f"h{i}") for i, t in enumerate(turned)]
    first = keys.groupBy("key").agg(*least)
    first = first.select("key", F.explode(F.array_distinct(F.array(*[F.col(f"h{i}").bitwiseXOR(t) for i, t in enumerate(turned)]))).alias("h"))
    return first.join(heads.select(F.xxhash64("node").alias("h"), "node", "size", *SKETCH), "h").drop("h")


def _combined(heads: DataFrame, frequent: DataFrame, k: int, num: int, den: int) -> DataFrame:
    """(key, node, pos): each frequent key of a node combined with every later shingle of its prefix of length k."""
    own = frequent.groupBy("node").agg(F.collect_list(F.struct("key", "pos")).alias("hot"))  # at most the combinations of one prefix

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for node, size, head, hot in zip(*(batch.column(c).to_pylist() for c in range(4)), strict=True):
                length = size - int(_least(np.array([size]), num, den)[0]) + k
                tokens = _text.mix(np.array(head[:length], dtype=np.int64).view(np.uint64)) * np.uint64(0x9FB21C651E98DF25)
                places = [np.arange(x["pos"] + 1, len(tokens)) for x in hot]
                n = np.array([len(p) for p in places])
                at = np.concatenate(places)
                key = np.repeat(_text.mix(np.array([x["key"] for x in hot], dtype=np.int64).view(np.uint64)), n)
                both = _text.mix(tokens[at] + key)
                yield pa.RecordBatch.from_arrays([pa.array(both.view(np.int64)), pa.array(np.full(len(at), node)), pa.array(at.astype(np.int32))], names=["key", "node", "pos"])

    rows = heads.join(own, "node")
    return rows.select("node", "size", "head", "hot").mapInArrow(_text.released(run), "key long, node long, pos int").join(heads.select("node", "size", *SKETCH), "node")


def _open_keys(keys: DataFrame, comp: DataFrame) -> DataFrame:
    """Rows of keys that join more than one component: with their component, the key's main one (main), its rows (n)."""
    own = keys.join(comp, "node", "left").withColumn("comp", F.coalesce("comp", "node"))
    wide = own.groupBy("key").agg(F.min("comp").alias("main"), F.max("comp").alias("hi"), F.count("*").alias("n")).where("main < hi").select(F.bitwise_not("key").alias("w"), "main", "n")
    return own.withColumn("w", F.bitwise_not("key")).join(wide, "w").drop("w")


def _pairs(level: DataFrame, num: int, den: int, k: int) -> DataFrame:
    """Distinct pairs (a < b) of nodes of different components that share a key and can be similar.

    Rows outside a key's main component meet all its rows. Both sides are dealt into blocks of a key, and each goes to
    all blocks of the other; a key of one block is not copied.
    """
    blocks = level.withColumn("blocks", F.ceil(F.col("n") / BLOCK).cast("int")).withColumn("own", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    x = blocks.where("comp != main").withColumns({"p": F.col("own"), "q": F.col("other")}).alias("x")
    y = blocks.withColumns({"p": F.col("other"), "q": F.col("own")}).alias("y")
    room = F.lit(k - 1) + F.least(F.col("x.size") - F.col("x.pos"), F.col("y.size") - F.col("y.pos"))
    meet = (F.col("x.key") == F.col("y.key")) & (F.col("x.p") == F.col("y.p")) & (F.col("x.q") == F.col("y.q")) & (F.col("x.comp") != F.col("y.comp"))
    once = (F.col("y.comp") == F.col("y.main")) | (F.col("x.node") < F.col("y.node"))
    return _unordered(x.join(y, meet & once & _fits(num, den, room)))


def similar_groups(docs: DataFrame, n_words: int = 5, threshold: tuple[int, int] = (80, 100), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_shingles, component_id, text_key): documents joined by similar sets; component_id is the smallest id of the group.

    text_key: xxhash64 of the text, which tells rows that share an id apart.
    threshold: similarity as a fraction (numerator, denominator), compared in whole numbers.
    """
    modest_batches(docs.sparkSession)
    num, den = threshold
    longest = LONGEST if num >= den else min(LONGEST, max(1, -(-num // (den - num))))  # different similar sets share as many at least
    classes = docs.sparkSession.sparkContext.broadcast(shingle_classes(docs.select(F.col(text_col).alias("text")), n_words))
    rows = materialize(shingle_sets(docs, n_words, num, den, classes, longest - 1, id_col, text_col).withColumn("row_key", F.monotonically_increasing_id()), "sets")
    # Rows with equal sets are one node, named by one of them.
    some = rows.where("n_shingles > 0")
    same = some.groupBy("k1", "k2", "n_shingles").agg(F.min("row_key").alias("node"), F.min("doc_id").alias("least")).withColumn("w", F.bitwise_not("k1")).drop("k1")
    named = materialize(some.withColumn("w", F.bitwise_not("k1")).join(same, ["w", "k2", "n_shingles"]).drop("w").withColumns({c: F.when(F.col("row_key") == F.col("node"), F.col(c)) for c in ("head", "wide")}), "named")
    empty = materialize(rows.where("n_shingles = 0").select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"), "text_key"), "empty")
    forget(rows)
    heads = named.where("row_key = node").withColumn("size", F.col("n_shingles"))
    short = F.col("size") - F.ceil(F.col("size") * num / den) + 1  # the prefix without what combinations add
    single = heads.select("node", "size", F.posexplode(F.slice("head", F.lit(1), F.greatest(short, F.lit(1)).cast("int"))).alias("pos", "key"))
    shared = single.groupBy("key").agg(F.count("*").alias("n")).where("n > 1").select("key")
    keys = materialize(single.join(shared, "key").join(heads.select("node", *SKETCH), "node"), "keys")
    x, y = keys.alias("x"), _hubs(keys, heads).alias("y")
    star = x.join(y, (F.col("x.key") == F.col("y.key")) & (F.col("x.node") != F.col("y.node")) & _fits(num, den))
    sets: list[DataFrame] = []

    def checked(pairs: DataFrame) -> DataFrame:
        """Links among the pairs; whole sets are made from the texts of their ends, once each."""
        left = materialize(_plausible(pairs, heads, num, den), "plausible")
        ends = left.select(F.col("a").alias("node")).unionByName(left.select(F.col("b").alias("node"))).distinct()
        for done in sets:
            ends = ends.join(done.select("node"), "node", "left_anti")
        wanted = materialize(heads.select("node", "doc_id", "k1").join(ends, "node"), "wanted")
        sets.append(materialize(_whole_sets(docs, wanted, n_words, id_col, text_col), "whole"))
        found = materialize(_similar(left, reduce(DataFrame.unionByName, sets), num, den), "links")
        forget(left)
        forget(wanted)
        return found

    links = checked(_unordered(star))
    comp = materialize(components(links, 2, whole=False).select("node", F.col("component").alias("comp")), "comp")
    level = materialize(_open_keys(keys, comp), "open")
    forget(keys)
    for k in range(1, longest + 1):
        hot = level.where(F.col("n") > RARE)
        last = k == longest or hot.isEmpty()
        links = links.unionByName(checked(_pairs(level if last else level.where(F.col("n") <= RARE), num, den, k)))
        if last:
            break
        done, level = level, materialize(_open_keys(_combined(heads, hot, k + 1, num, den), comp), "open")
        forget(done)
    forget(level)
    for done in sets:
        forget(done)
    comp = components(links)
    # The component's smallest id, over its nodes; nodes without a link keep their own.
    group = comp.join(heads.select("node", "least"), "node").groupBy("component").agg(F.min("least").alias("lowest"))
    lowest = comp.withColumn("w", F.bitwise_not("component")).join(group.select(F.bitwise_not("component").alias("w"), "lowest"), "w").select("node", "lowest")
    out = named.select("doc_id", "n_shingles", "node", "least", "text_key").join(lowest, "node", "left").select("doc_id", "n_shingles", F.coalesce("lowest", "least").alias("component_id"), "text_key")
    return out.unionByName(empty)
