"""Benchmark passages in training text: n-gram seeds, then local alignment.

All word n-grams of all items seed the search, however popular they are, so what is found doesn't depend on how many
documents hold a passage. A seed fixes a stretch of the document around the item's place in it; stretches that hold too
few of the item's words for the least score are left out, and a local alignment with gaps (Smith-Waterman on words)
scores the others, so edited and paraphrased copies count too. Items too short for an alignment are found as exact
sequences of words.

Items are the stated query set: they are sent to all workers in blocks of a fixed size, and each block is one scan.
Texts are never shuffled.

Defined results: null and empty texts match nothing; items without words match nothing; an item of fewer than
LEAST_WORDS words is found where all its words stand in a row, at its first place in each document, with score 1; a
copy that shares no n-gram with a longer item isn't found; repeated rows and items give a row each; extra columns are
ignored; empty tables give an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from benchvary.llm import _text
from benchvary.session import modest_batches

NGRAM = 4
#: Least share of an item's full alignment score.
LEAST_SCORE = 0.6
#: Words an item needs for an alignment to mean something.
LEAST_WORDS = 6
#: Items sent to the workers at once.
ITEM_BLOCK = 20_000
#: Meetings of a document's n-grams with seeds that are handled at once.
MEETINGS = 1 << 20
MATCH, MISMATCH, GAP = 2.0, -1.0, -1.0


@dataclass
class Items:
    """A block of test items: word hashes of each, their n-grams as sorted seeds (hash, item, place), and the sorted
    whole sequences (hash, item) of short ones by their number of words."""

    ids: np.ndarray
    words: list[np.ndarray]
    grams: np.ndarray
    item: np.ndarray
    place: np.ndarray
    short: dict[int, tuple[np.ndarray, np.ndarray]]

    @classmethod
    def of(cls, ids: list[int], texts: list[str | None], n: int) -> Items:
        words, grams, item, place = [], [], [], []
        whole: dict[int, list[tuple[int, int]]] = {}
        for k, text in enumerate(texts):
            for _, _, data, offsets in _text.slices(pa.array([text or ""])):
                hashes, per_row, _, _ = _text.words(data, offsets)
            words.append(hashes)
            if 0 < len(hashes) < LEAST_WORDS:
                whole.setdefault(len(hashes), []).append((int(_text.shingles(hashes, per_row, len(hashes))[0][0]), k))
            elif len(hashes):
                own, _ = _text.shingles(hashes, per_row, n)
                grams.append(own)
                item.append(np.full(len(own), k))
                place.append(np.arange(len(own)))
        join = lambda x, kind: np.concatenate(x) if x else np.zeros(0, dtype=kind)
        g, i, p = join(grams, np.uint64), join(item, np.int64), join(place, np.int64)
        order = np.argsort(g, kind="stable")
        short = {size: (np.array([x[0] for x in sorted(found)], dtype=np.uint64), np.array([x[1] for x in sorted(found)], dtype=np.int64)) for size, found in whole.items()}
        return cls(np.array(ids, dtype=np.int64), words, g[order], i[order], p[order], short)


def _met(grams: np.ndarray, own: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(places in own, places in the sorted grams) of equal values, in runs of about MEETINGS, in the order of own."""
    lo = np.searchsorted(grams, own, "left")
    n = np.searchsorted(grams, own, "right") - lo
    hit = np.flatnonzero(n)
    total = np.cumsum(n[hit])
    i = 0
    while i < len(hit):
        done = total[i - 1] if i else 0
        j = max(i + 1, int(np.searchsorted(total, done + MEETINGS, "right")))
        at, m = hit[i:j], n[hit[i:j]]
        yield np.repeat(at, m), np.repeat(lo[at] - (np.cumsum(m) - m), m) + np.arange(m.sum())
        i = j


def align(item: np.ndarray, stretches: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Best local alignment score of item against each row of stretches (0 where padded), and where it ends in the row."""
    rows, width = stretches.shape
    place = np.arange(width + 1) * GAP
    prev = np.zeros((rows, width + 1))
    best, end = np.zeros(rows), np.zeros(rows, dtype=np.int64)
    for w in item:
        cur = np.zeros((rows, width + 1))
        step = prev[:, :-1] + np.where(stretches == w, MATCH, MISMATCH)
        cur[:, 1:] = np.maximum(np.maximum(step, prev[:, 1:] + GAP), 0)
        cur = np.maximum.accumulate(cur - place, axis=1) + place  # gaps along the row
        at = cur.argmax(axis=1)
        top = cur[np.arange(rows), at]
        better = top > best
        best, end = np.where(better, top, best), np.where(better, at, end)
        prev = cur
    return best, end


def find_leaks(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", ngram: int = NGRAM, least_score: float = LEAST_SCORE) -> DataFrame:
    """(doc_id, item_id, score, start, end, n_words): the best alignment of each item in each document that reaches
    least_score, a share of the item's own full score. start and end are code points of the document, end exclusive.
    """
    modest_batches(docs.sparkSession)
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    schema = "doc_id long, item_id long, score double, start long, end long, n_words long"
    n_items = benchmark.count()
    blocks = max(1, -(-n_items // ITEM_BLOCK))
    found = []
    for block in range(blocks):
        own = benchmark.select(F.col(item_col).cast("long").alias("i"), F.col(item_text_col).alias("t"))
        rows = own.where(F.pmod(F.xxhash64("i", "t"), F.lit(blocks)) == block).collect() if blocks > 1 else own.collect()
        rows.sort(key=lambda r: (r["i"] is None, r["i"] or 0, r["t"] or ""))
        items = Items.of([r["i"] if r["i"] is not None else -1 for r in rows], [r["t"] for r in rows], ngram)
        if len(items.grams) or items.short:
            found.append(slim.mapInArrow(_text.released(_searcher(docs.sparkSession.sparkContext.broadcast(items), ngram, least_score)), schema))
    if not found:
        return docs.sparkSession.createDataFrame([], schema)
    out = found[0]
    for f in found[1:]:
        out = out.unionByName(f)
    return out


def _joined(hits: np.ndarray) -> np.ndarray:
    """One column for each (row, item, diagonal), its stretch from the least left to the greatest right of its hits."""
    hits = hits[:, np.lexsort(hits[2::-1])]
    head = np.flatnonzero(np.concatenate([[True], (hits[:3, 1:] != hits[:3, :-1]).any(axis=0)])) if hits.shape[1] else np.zeros(0, dtype=np.int64)
    if not len(head):
        return hits
    return np.concatenate([hits[:3, head], np.minimum.reduceat(hits[3:4], head, axis=1), np.maximum.reduceat(hits[4:], head, axis=1)])


def _most_matches(item: np.ndarray, stretches: np.ndarray) -> np.ndarray:
    """Words that item and each row of stretches have in common, with multiplicity: no alignment matches more."""
    words, n = np.unique(item, return_counts=True)
    at = np.minimum(np.searchsorted(words, stretches), len(words) - 1)
    row, place = np.nonzero(words[at] == stretches)
    common = np.bincount(row * len(words) + at[row, place], minlength=len(stretches) * len(words)).reshape(-1, len(words))
    return np.minimum(common, n).sum(axis=1)


def _searcher(sent, ngram: int, least_score: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seeds: Items = sent.value
        sizes = np.array([len(w) for w in seeds.words])
        names = ["doc_id", "item_id", "score", "start", "end", "n_words"]
        for batch in batches:
            for i, j, data, offsets in _text.slices(batch.column(1)):
                hashes, per_row, starts, ends = _text.words(data, offsets)
                first = np.cumsum(per_row) - per_row
                out: dict[tuple[int, int], tuple] = {}
                for length, (whole, which) in seeds.short.items():
                    own, count = _text.shingles(hashes, per_row, length)
                    rows, gram_first = np.repeat(np.arange(j - i), count), np.cumsum(count) - count
                    for hit, seed in _met(whole, own):
                        row, item = rows[hit], which[seed]
                        at = first[row] + hit - gram_first[row]
                        _, once = np.unique(np.stack([row, item]), axis=1, return_index=True)
                        for r, k, a in zip(row[once].tolist(), item[once].tolist(), at[once].tolist(), strict=True):
                            if np.array_equal(hashes[a : min(a + length, first[r] + per_row[r])], seeds.words[k]):
                                out.setdefault((r, k), (1.0, a, a + length))
                own, count = _text.shingles(hashes, per_row, ngram)
                rows, gram_first = np.repeat(np.arange(j - i), count), np.cumsum(count) - count
                parts = [np.zeros((5, 0), dtype=np.int64)]
                for hit, seed in _met(seeds.grams, own):
                    row, item, place = rows[hit], seeds.item[seed], seeds.place[seed]
                    at = first[row] + hit - gram_first[row]  # word at which the n-gram starts
                    size = sizes[item]
                    slack = size // 4 + 2
                    left = np.maximum(at - place - slack, first[row])
                    right = np.minimum(at + size - place + slack, first[row] + per_row[row])
                    parts.append(_joined(np.stack([row, item, (at - place) // slack, left, right])))
                # hits of one item on nearly one diagonal are one stretch
                row, item, _, left, right = _joined(np.concatenate(parts, axis=1))
                for k in np.unique(item):
                    words = seeds.words[k]
                    mine = np.flatnonzero(item == k)
                    for part in range(0, len(mine), 256):
                        own_rows = mine[part : part + 256]
                        width = int((right - left)[own_rows].max())
                        places = left[own_rows][:, None] + np.arange(width)
                        inside = places < right[own_rows][:, None]
                        block = np.where(inside, hashes[np.minimum(places, len(hashes) - 1)], np.uint64(0))
                        near = np.flatnonzero(_most_matches(words, block) / len(words) >= least_score)
                        if not len(near):
                            continue
                        own_rows, block = own_rows[near], block[near]
                        score, end = align(words, block)
                        share = score / (MATCH * len(words))
                        for x in np.flatnonzero(share >= least_score).tolist():
                            r = int(row[own_rows[x]])
                            key = (r, int(k))
                            if key in out and out[key][0] >= share[x]:
                                continue
                            back, length = align(words[::-1], block[x : x + 1, : end[x]][:, ::-1])
                            stop = int(left[own_rows[x]] + end[x])
                            out[key] = (float(share[x]), stop - int(length[0]), stop)
                if out:
                    ids = batch.column(0).slice(i, j - i).to_pylist()
                    lead = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])  # code points before each byte
                    made = [
                        (ids[r], int(seeds.ids[k]), share, int(lead[starts[a]] - lead[offsets[r]]), int(lead[ends[b - 1]] - lead[offsets[r]]), b - a) for (r, k), (share, a, b) in sorted(out.items())
                    ]
                    kinds = [pa.int64(), pa.int64(), pa.float64(), pa.int64(), pa.int64(), pa.int64()]
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*made, strict=True), kinds, strict=True)], names=names)

    return run
