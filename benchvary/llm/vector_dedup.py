"""Near-copies among vectors by cross-polytope hashing.

Vectors are turned by three rounds of random signs and a fast Hadamard transform; the largest coordinate with its sign
is a hash value. Several values make a bucket key, several keys a set of tables, and each table is also probed with
the second largest coordinate of each value in turn. Larger inputs take more values; tables are added until the share
of pairs at the bound that meet, measured on random pairs of the same width, is RECALL at every size. Vectors that share a bucket (and a label) are candidates, and
every reported link is verified by its cosine in double precision.

Vectors with equal components and label are one node with a multiplicity. Small buckets give candidate pairs of ids,
which meet their vectors by joins. A bucket with many nodes is dealt into blocks, and blocks meet in pairs inside
workers, which return only link counts and a spanning forest; so a large group of near-copies never becomes a table of
all its pairs. A pair that shares large buckets is counted in the first of them and left out elsewhere.

Defined results: vectors that are null, empty, zero, or hold null or non-finite components, and vectors without label,
link with nothing and are kept; vectors of different lengths are not compared; repeated rows count as further
vectors; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from benchvary.llm import _text
from benchvary.llm._graph import components
from benchvary.session import materialize

#: Least number of tables, and the most that are tried.
TABLES, MOST_TABLES = 6, 256
#: Share of pairs just at the bound that must meet in some table, and the random pairs on which it is measured.
RECALL, RECALL_PAIRS = 0.999, 4000
SEED = 20_240_229
#: Nodes of a bucket whose pairs are listed; beyond it blocks are compared inside workers.
LISTED = 48
BLOCK = 256


def hadamard(x: np.ndarray) -> np.ndarray:
    """Fast Walsh-Hadamard transform of each row; the width is a power of two."""
    n, d = x.shape
    h = 1
    while h < d:
        y = x.reshape(n, d // (2 * h), 2, h)
        x = np.concatenate([y[:, :, :1] + y[:, :, 1:], y[:, :, :1] - y[:, :, 1:]], axis=2).reshape(n, d)
        h *= 2
    return x / np.sqrt(d)


def cross_polytope(x: np.ndarray, table: int, part: int, seed: int = SEED) -> tuple[np.ndarray, np.ndarray]:
    """Best and second best value of each row: twice the coordinate, plus one where it is negative."""
    d = 1 << max(0, x.shape[1] - 1).bit_length()
    y = np.zeros((len(x), d))
    y[:, : x.shape[1]] = x
    rng = np.random.default_rng([seed, table, part, d])
    for _ in range(3):
        y = hadamard(y * rng.choice([-1.0, 1.0], d))
    size = np.abs(y)
    rows = np.arange(len(y))
    best = size.argmax(axis=1)
    size[rows, best] = -1
    second = size.argmax(axis=1)
    return 2 * best + (y[rows, best] < 0), 2 * second + (y[rows, second] < 0)


def _table_keys(x: np.ndarray, table: int, values: int) -> np.ndarray:
    """(rows, 1 + values) keys of one table: the own bucket, then the probes."""
    found = [cross_polytope(x, table, k) for k in range(values)]
    out = []
    for probe in range(-1, values):
        key = np.full(len(x), table + 1, dtype=np.uint64)
        for k, (best, second) in enumerate(found):
            key = _text.mix(key * np.uint64(1_000_003) + (second if k == probe else best).astype(np.uint64))
        out.append(key)
    return np.stack(out, axis=1)


def bucket_keys(x: np.ndarray, values: int, tables: int = TABLES) -> np.ndarray:
    """(rows, tables * (1 + values)) keys: of each table the own bucket, then the probes."""
    return np.concatenate([_table_keys(x, t, values) for t in range(tables)], axis=1)


def hash_values(nodes: int) -> int:
    """Hash values of a bucket key for so many vectors."""
    return max(1, round(np.log(max(nodes, 2)) / np.log(128)))


def tables_for(values: int, dims: int, least: float, fewest: int = TABLES) -> int:
    """Tables in which the share RECALL of random pairs with the cosine least meets; fewest at least."""
    rng = np.random.default_rng([SEED, dims])
    a, b = (x / np.linalg.norm(x, axis=1, keepdims=True) for x in rng.standard_normal((2, RECALL_PAIRS, dims)))
    across = b - (a * b).sum(axis=1, keepdims=True) * a
    size = np.linalg.norm(across, axis=1, keepdims=True)
    b = least * a + np.sqrt(max(0.0, 1 - least**2)) * np.divide(across, size, out=np.zeros_like(across), where=size > 1e-9)
    apart = np.ones(RECALL_PAIRS, dtype=bool)
    for t in range(MOST_TABLES):
        x, y = _table_keys(a[apart], t, values), _table_keys(b[apart], t, values)
        apart[apart] = ~(x[:, :, None] == y[:, None, :]).any(axis=(1, 2))
        if t + 1 >= fewest and apart.mean() <= 1 - RECALL:
            return t + 1
    return MOST_TABLES


def _usable(vec_col: str) -> object:
    v = F.col(vec_col)
    return v.isNotNull() & (F.size(v) > 0) & ~F.exists(v, lambda c: c.isNull() | F.isnan(c) | (F.abs(c) == float("inf"))) & F.exists(v, lambda c: c != 0)


def _width(dims: int) -> int:
    """Bits of the width of the transform."""
    return max(0, dims - 1).bit_length()


def _pair_up(rows: DataFrame, values: int, tables: dict[int, int]) -> DataFrame:
    """(bucket, node) of all keys of every node; tables: how many by width."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            vec = [np.asarray(v, dtype=np.float64) for v in batch.column(2).to_pylist()]
            label = batch.column(1).to_numpy(zero_copy_only=False).astype(np.int64)
            dims = np.array([len(v) for v in vec])
            for d in np.unique(dims):
                own = np.flatnonzero(dims == d)
                x = np.stack([vec[k] for k in own])
                x = x / np.abs(x).max(axis=1, keepdims=True)
                keys = bucket_keys(x / np.linalg.norm(x, axis=1, keepdims=True), values, tables[_width(int(d))])
                keys = _text.mix(keys + _text.mix(label[own].astype(np.uint64) * np.uint64(4099) + np.uint64(d))[:, None])
                n = keys.shape[1]
                yield pa.RecordBatch.from_arrays([pa.array(keys.ravel().view(np.int64)), pa.array(np.repeat(batch.column(0).to_numpy()[own], n))], names=["bucket", "node"])

    return rows.select("node", "label", "vec").mapInArrow(run, "bucket long, node long")


def _unit(rows: list) -> np.ndarray:
    x = np.asarray(rows, dtype=np.float64)
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _listed_links(pairs: DataFrame, nodes: DataFrame, least: float) -> DataFrame:
    """(a, b, n_a, n_b) of candidate pairs that are similar, with the multiplicities of both ends."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            va, vb = batch.column(4).to_pylist(), batch.column(5).to_pylist()
            same = np.array([len(x) == len(y) for x, y in zip(va, vb, strict=True)], dtype=bool)
            keep = np.zeros(len(va), dtype=bool)
            for d in {len(x) for x in va}:
                at = np.flatnonzero(same & np.array([len(x) == d for x in va]))
                if len(at):
                    keep[at] = (_unit([va[k] for k in at]) * _unit([vb[k] for k in at])).sum(axis=1) >= least
            yield batch.select([0, 1, 2, 3]).filter(pa.array(keep))

    left = nodes.select(F.col("node").alias("a"), F.col("label").alias("la"), F.col("n").alias("n_a"), F.col("vec").alias("va"))
    right = nodes.select(F.col("node").alias("b"), F.col("label").alias("lb"), F.col("n").alias("n_b"), F.col("vec").alias("vb"))
    both = pairs.join(left, "a").join(right, "b").where("la = lb").select("a", "b", "n_a", "n_b", "va", "vb")
    return both.mapInArrow(run, "a long, b long, n_a long, n_b long")


def _block_links(hot: DataFrame, nodes: DataFrame, least: float) -> DataFrame:
    """(a, b, links): links > 0: a links with so many rows; b: a has a forest edge to b. hot: (bucket, node, buckets, size)."""
    blocks = F.ceil(F.col("size") / BLOCK).cast("int")
    dealt = hot.withColumn("blocks", blocks).withColumn("block", F.pmod(F.xxhash64("node", "bucket"), F.col("blocks")).cast("int"))
    # block p meets block q >= p under the key (bucket, p, q)
    copies = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).select(
        "bucket", "node", "buckets", "block", F.least("block", "other").alias("p"), F.greatest("block", "other").alias("q")
    )
    rows = copies.join(nodes.select("node", "label", "n", "vec"), "node").select("bucket", "p", "q", "block", "node", "label", "n", "buckets", "vec")
    dealt_out = rows.repartition("bucket", "p", "q").sortWithinPartitions("bucket", "p", "q", "block", "node")

    def solve(rows: list[tuple]) -> Iterator[pa.RecordBatch]:
        bucket, p, q = rows[0][:3]
        groups: dict[tuple, list[tuple]] = {}
        for r in rows:
            groups.setdefault((r[5], len(r[8])), []).append(r)
        a_out, b_out, n_out = [], [], []
        for own in groups.values():
            x = _unit([r[8] for r in own])
            block = np.array([r[3] for r in own])
            node = np.array([r[4] for r in own])
            mult = np.array([r[6] for r in own])
            wide = max(len(r[7]) for r in own)
            buckets = np.array([sorted(r[7]) + [2**63 - 1] * (wide - len(r[7])) for r in own])
            near = np.triu(x @ x.T >= least, 1)
            if p != q:
                near &= block[:, None] != block[None, :]
            i, j = np.nonzero(near)
            keep = np.zeros(len(i), dtype=bool)
            for s in range(0, len(i), 20_000):
                bi, bj = buckets[i[s : s + 20_000]], buckets[j[s : s + 20_000]]
                shared = (bi[:, :, None] == bj[:, None, :]).any(axis=2) & (bi != 2**63 - 1)
                first = np.where(shared, bi, 2**63 - 1).min(axis=1)
                keep[s : s + 20_000] = first == bucket
            root = list(range(len(own)))

            def top(k: int, root: list[int] = root) -> int:
                while root[k] != k:
                    root[k] = root[root[k]]
                    k = root[k]
                return k

            for u, v in zip(i.tolist(), j.tolist(), strict=True):
                u, v = top(u), top(v)
                if u != v:
                    root[max(u, v)] = min(u, v)
                    a_out.append(node[u])
                    b_out.append(node[v])
                    n_out.append(0)
            n = np.bincount(i[keep], mult[j[keep]], len(own)) + np.bincount(j[keep], mult[i[keep]], len(own))
            for k in np.flatnonzero(n):
                a_out.append(node[k])
                b_out.append(None)
                n_out.append(int(n[k]))
        yield pa.RecordBatch.from_arrays([pa.array(a_out, pa.int64()), pa.array(b_out, pa.int64()), pa.array(n_out, pa.int64())], names=["a", "b", "links"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if held and held[-1][:3] != row[:3]:
                    yield from solve(held)
                    held = []
                held.append(row)
        if held:
            yield from solve(held)

    return dealt_out.mapInArrow(run, "a long, b long, links long")


def near_vectors(vectors: DataFrame, least: float = 0.93, id_col: str = "vec_id", vec_col: str = "embedding", label_col: str = "label", tables: int = TABLES) -> DataFrame:
    """(vec_id, n_links, component_id, kept) for every row of vectors."""
    slim = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vec_col).cast("array<double>").alias("vec"), F.col(label_col).cast("long").alias("label"))
    usable = slim.where(_usable("vec") & F.col("label").isNotNull() & F.col("vec_id").isNotNull())
    nodes = materialize(usable.groupBy("label", "vec").agg(F.min("vec_id").alias("node"), F.count("*").alias("n")), "vectors")
    # one row may stand in two nodes only if an id repeats with other components; nodes are then told apart by joins on label and vec
    total = nodes.count()
    values = hash_values(total)
    width = F.when(F.size("vec") > 1, F.length(F.bin(F.size("vec") - 1))).otherwise(0)
    widest = nodes.groupBy(width.alias("width")).agg(F.max(F.size("vec")).alias("dims")).collect()
    needed = {r["width"]: tables_for(values, r["dims"], least, tables) for r in widest}
    keys = materialize(_pair_up(nodes, values, needed).distinct(), "buckets")
    sizes = keys.groupBy("bucket").agg(F.count("*").alias("size")).where("size > 1")
    sized = materialize(keys.join(sizes, "bucket"), "sized")
    hot = sized.where(F.col("size") > LISTED)
    hot_of = hot.groupBy("node").agg(F.collect_list("bucket").alias("buckets"))
    none = F.array().cast("array<bigint>")
    few = sized.where(F.col("size") <= LISTED).join(hot_of, "node", "left").withColumn("buckets", F.coalesce("buckets", none))
    x, y = few.alias("x"), few.alias("y")
    pairs = (
        x.join(y, (F.col("x.bucket") == F.col("y.bucket")) & (F.col("x.node") < F.col("y.node")) & ~F.arrays_overlap("x.buckets", "y.buckets"))
        .select(F.col("x.node").alias("a"), F.col("y.node").alias("b"))
        .distinct()
    )
    listed = materialize(_listed_links(pairs, nodes, least), "links")
    blocks = materialize(_block_links(hot.join(hot_of, "node"), nodes, least), "block-links")
    degree = (
        listed.select(F.col("a").alias("node"), F.col("n_b").alias("links"))
        .unionByName(listed.select(F.col("b").alias("node"), F.col("n_a").alias("links")))
        .unionByName(blocks.where("links > 0").select(F.col("a").alias("node"), "links"))
        .groupBy("node")
        .agg(F.sum("links").alias("links"))
    )
    comp = components(listed.select("a", "b").unionByName(blocks.where("b is not null").select("a", "b")))
    known = nodes.join(degree, "node", "left").join(comp, "node", "left").select("label", "vec", F.col("node").alias("first"), (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("links"), F.coalesce("component", "node").alias("component"))
    usable_flag = slim.withColumn("ok", F.coalesce(_usable("vec") & F.col("label").isNotNull(), F.lit(False)))
    return usable_flag.join(known, ["label", "vec"], "left").select(
        "vec_id",
        F.when(F.col("ok"), F.col("links")).otherwise(F.lit(0)).cast("long").alias("n_links"),
        F.when(F.col("ok"), F.col("component")).otherwise(F.col("vec_id")).alias("component_id"),
    ).withColumn("component_id", F.coalesce("component_id", "vec_id")).withColumn("n_links", F.coalesce("n_links", F.lit(0).cast("long"))).withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))
