"""Repeated byte strings by two-stage suffix sorting.

Every start of a string of the given length is assigned to an anchor: the 64-byte window inside that string whose hash
is smallest. Equal strings have equal anchors at equal places, so all copies of a string meet under one anchor, and
anchors that occur once in the corpus are done. Starts that share an anchor form a window of text. Windows that occur
several times are repeated as a whole. Windows under one anchor that differ somewhere are put into a suffix array:
suffixes smaller than their successors are sorted directly, all others are induced from them by scanning the buckets
from left to right, and adjacent common prefixes, checked byte by byte, tell which starts repeat. An anchor with very
many different windows (a passage in a third of all documents, each in other surroundings) is split: its strings are
counted by a 128-bit hash with partial sums, so no task gets them all.

A second, shorter length can be reported beside the one that is removed: anchors then lie inside strings of the shorter
length, windows reach as far as the longer one, and one suffix array answers for both.

Defined results: null text counts as empty; texts shorter than the length keep every byte; repeated rows are two
places, so each loses what the other holds; matches never cross documents; extra columns are ignored; an empty table
gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from benchvary.llm import _text
from benchvary.session import forget, materialize, modest_batches

LENGTH = 400
GRAM = 64
#: Different windows of an anchor up to which they meet in one suffix array.
TOGETHER = 16_384
#: Bytes of windows that one suffix array takes, unless a single anchor has more.
ARRAY_BYTES = 256 << 10
#: Strings that are compared together.
STRINGS = 100_000
#: Stands behind each window; it is no byte of UTF-8.
END = np.uint8(255)
#: Bytes of text whose windows are found at once.
SLICE = 1 << 20
_PLACE = np.uint64((1 << 31) - 1)
_SYMBOL = _text.mix(np.arange(256, dtype=np.uint64) + np.uint64(977))


def _sorted_starts(data: np.ndarray, starts: np.ndarray, depth: int) -> np.ndarray:
    """Starts in the order of the first depth bytes from there, a shorter suffix first; ties only among equal bytes.

    The first eight bytes decide for most; starts that are still tied are compared as strings, so many at a time. Equal
    strings of full depth are sorted once.
    """
    starts = starts[::-1]
    h, inv = _text.prefix_hashes(data)
    full = starts[starts + depth <= len(data)]
    key = (h[full + depth] - h[full]) * inv[full]
    _, one, back = np.unique(key, return_index=True, return_inverse=True)
    order = np.concatenate([starts[starts + depth > len(data)], full[one]])
    padded = np.concatenate([data, np.zeros(16, dtype=np.uint8)])
    words = np.ndarray((len(padded) - 8,), dtype=">u8", buffer=padded.data, strides=(1,))
    value = words[order].astype(np.uint64)
    turn = np.argsort(value, kind="stable")
    order, value = order[turn], value[turn]
    heads = np.flatnonzero(np.concatenate([[True], value[1:] != value[:-1]])) if len(order) else np.zeros(0, dtype=np.int64)
    size = np.diff(np.append(heads, len(order)))
    tied = np.flatnonzero(np.repeat(size > 1, size))
    text = data.tobytes().decode("latin-1")  # one character for each byte, in the same order
    ends = np.cumsum(size[size > 1])
    at = 0
    while at < len(tied):
        to = int(ends[np.searchsorted(ends, min(at + STRINGS, len(tied)))])  # whole groups
        own = order[tied[at:to]].tolist()
        strings = [text[i : i + depth] for i in own]
        order[tied[at:to]] = [own[k] for k in sorted(range(len(own)), key=strings.__getitem__)]
        at = to
    # put the equal strings beside their representative
    alike = np.argsort(back, kind="stable")
    first = np.concatenate([[0], np.cumsum(np.bincount(back, minlength=len(one)))])
    number = np.full(len(data), -1)
    number[full[one]] = np.arange(len(one))
    place = number[order]
    n = np.where(place >= 0, first[place + 1] - first[place], 1)
    if (n == 1).all():
        return order
    out = np.repeat(order, n)
    many = np.repeat(place, n) >= 0
    within = np.arange(len(out)) - np.repeat(np.cumsum(n) - n, n)
    out[many] = full[alike[(first[np.maximum(np.repeat(place, n), 0)] + within)[many]]]
    return out


def suffix_array(data: np.ndarray, depth: int) -> np.ndarray:
    """Starts of all suffixes in the order of their first depth bytes, by two-stage sorting."""
    n = len(data)
    if not n:
        return np.zeros(0, dtype=np.int64)
    rise = np.empty(n, dtype=np.int16)
    rise[:-1] = data[1:].astype(np.int16) - data[:-1]
    rise[-1] = -1
    known = np.where(rise != 0, np.arange(n), n)
    nearest = np.minimum.accumulate(known[::-1])[::-1]
    small = rise[nearest] > 0  # the suffix is smaller than its successor
    direct = _sorted_starts(data, np.flatnonzero(small), depth)
    heads = np.searchsorted(data[direct], np.arange(257)) if len(direct) else np.zeros(257, dtype=np.int64)
    waiting: list[list[np.ndarray]] = [[] for _ in range(256)]
    waiting[data[-1]].append(np.array([n - 1]))
    done = []

    def induce(found: np.ndarray, own: int) -> np.ndarray:
        before = found[found > 0] - 1
        before = before[~small[before]]
        first = data[before]
        stays = before[first == own]
        rest, first = before[first != own], first[first != own]
        if len(rest):
            order = np.argsort(first, kind="stable")
            cuts = np.flatnonzero(np.diff(first[order])) + 1
            for part in np.split(rest[order], cuts):
                waiting[data[part[0]]].append(part)
        return stays

    for c in range(256):
        front = np.concatenate(waiting[c]) if waiting[c] else np.zeros(0, dtype=np.int64)
        waiting[c] = []
        while len(front):
            done.append(front)
            front = induce(front, c)
        own = direct[heads[c] : heads[c + 1]]
        if len(own):
            done.append(own)
            induce(own, c)
    return np.concatenate(done)


def common_prefixes(data: np.ndarray, order: np.ndarray, most: int) -> np.ndarray:
    """Length of the common prefix of each two neighbours in order, counted up to most, by hashes."""
    h, inv = _text.prefix_hashes(data)
    a, b = order[:-1], order[1:]
    room = np.minimum(len(data) - np.maximum(a, b), most)
    length = np.zeros(len(a), dtype=np.int64)
    step = 1 << (most.bit_length() - 1)
    while step:
        to = length + step
        fits = to <= room
        x, y, z = a[fits], b[fits], to[fits]
        same = (h[x + z] - h[x]) * inv[x] == (h[y + z] - h[y]) * inv[y]
        at = np.flatnonzero(fits)[same]
        length[at] += step
        step >>= 1
    return length


def _confirmed(data: np.ndarray, a: np.ndarray, b: np.ndarray, length: int) -> np.ndarray:
    """Which of the pairs of starts have equal strings, byte by byte; pairs that move on together are compared at once."""
    if not len(a):
        return np.zeros(0, dtype=bool)
    order = np.argsort(a, kind="stable")
    x, y = a[order], b[order]
    head = np.flatnonzero(np.concatenate([[True], (x[1:] != x[:-1] + 1) | (y[1:] != y[:-1] + 1)]))
    ok = np.ones(len(x), dtype=bool)
    raw = data.tobytes()
    for i, j in zip(head.tolist(), [*head[1:].tolist(), len(x)], strict=True):
        n = j - i + length - 1
        if raw[x[i] : x[i] + n] != raw[y[i] : y[i] + n]:
            ok[i:j] = [raw[x[k] : x[k] + length] == raw[y[k] : y[k] + length] for k in range(i, j)]
    out = np.empty(len(x), dtype=bool)
    out[order] = ok
    return out


def repeated_starts(bodies: list[np.ndarray], n_starts: list[int], lengths: tuple[int, ...]) -> tuple[np.ndarray, list[np.ndarray]]:
    """Where each body begins in their concatenation, and for each length which starts there repeat in the bodies.

    Only the first n_starts of a body count as starts; a string must end inside its body.
    """
    ended = [np.append(b, END) for b in bodies]
    size = np.array([len(b) for b in ended])
    first = np.cumsum(size) - size
    data = np.concatenate(ended)
    start_ok = np.zeros(len(data), dtype=bool)
    for f, n in zip(first.tolist(), n_starts, strict=True):
        start_ok[f : f + n] = True
    order = suffix_array(data, max(lengths))
    order = order[start_ok[order]]
    a, b = order[:-1], order[1:]
    room = np.repeat(first + size - 1, size) - np.arange(len(data))
    common = np.minimum(common_prefixes(data, order, max(lengths)), np.minimum(room[a], room[b]))
    out = []
    for length in lengths:
        same = np.flatnonzero(common >= length)
        same = same[_confirmed(data, a[same], b[same], length)]
        hit = np.zeros(len(data), dtype=bool)
        hit[a[same]] = True
        hit[b[same]] = True
        out.append(hit)
    return first, out


_FOUND = "doc_id long, text_key int, start int, n_starts int, short boolean"


def _found(doc: list | np.ndarray, key: list | np.ndarray, start: np.ndarray, n: np.ndarray, short: bool) -> pa.RecordBatch:
    cols = [pa.array(doc, pa.int64()), pa.array(key, pa.int32()), pa.array(np.asarray(start).astype(np.int32)), pa.array(np.asarray(n).astype(np.int32)), pa.array(np.full(len(start), short))]
    return pa.RecordBatch.from_arrays(cols, names=["doc_id", "text_key", "start", "n_starts", "short"])


def _windows(docs: DataFrame, least: int, length: int) -> DataFrame:
    """(doc_id, text_key, anchor, win, start, n_starts, size): runs of starts with one anchor inside their first least bytes.

    A window has size bytes: as far as the last start's string of the full length reaches, or the text ends; win hashes them.
    """
    span = least - GRAM + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, _, data, offsets in _text.slices(batch.column(2), SLICE):
                size = np.diff(offsets)
                if not (size >= least).any():
                    continue
                h, inv = _text.prefix_hashes(data)
                grams = _text.mix((h[GRAM:] - h[:-GRAM]) * inv[: len(h) - GRAM])
                low = (grams & ~_PLACE) | np.arange(len(grams), dtype=np.uint64)
                width = 1
                while 2 * width <= span:
                    low = np.minimum(low[:-width], low[width:])
                    width *= 2
                if width < span:
                    low = np.minimum(low[: len(low) - (span - width)], low[span - width :])
                inside = np.zeros(len(low) + 1, dtype=np.int8)
                long = size >= least
                inside[offsets[:-1][long]] += 1
                ends = offsets[1:][long] - least + 1
                inside[ends[ends <= len(low)]] -= 1
                starts = np.flatnonzero(np.cumsum(inside[:-1], dtype=np.int32))
                at = (low[starts] & _PLACE).astype(np.int64)
                head = np.flatnonzero(np.concatenate([[True], (at[1:] != at[:-1]) | (starts[1:] != starts[:-1] + 1)]))
                n = np.diff(np.append(head, len(at)))
                s, anchor = starts[head], at[head]
                row = np.searchsorted(offsets, s, "right") - 1
                e = np.minimum(s + n + length - 1, offsets[row + 1])
                win = _text.mix((h[e] - h[s]) * inv[s] + _text.mix(((n * 4096 + anchor - s) * 4096 + e - s).astype(np.uint64)))
                take = pa.array(i + row)
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).take(take), batch.column(1).take(take), pa.array(grams[anchor].view(np.int64)), pa.array(win.view(np.int64)), *(pa.array(x.astype(np.int32)) for x in (s - offsets[row], n, e - s))],
                    names=["doc_id", "text_key", "anchor", "win", "start", "n_starts", "size"],
                )

    return docs.mapInArrow(_text.released(run), "doc_id long, text_key int, anchor long, win long, start int, n_starts int, size int")


def _cut_out(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """(anchor, many, hot, doc_id, text_key, start, n_starts, body): the bytes of the wanted windows."""
    lists = wanted.groupBy("doc_id", "text_key").agg(F.collect_list(F.struct("anchor", "start", "n_starts", "size", "many", "hot")).alias("spots"))
    one = docs.join(lists, ["doc_id", "text_key"]).dropDuplicates(["doc_id", "text_key"]).select("doc_id", "text_key", F.encode(F.col("text"), "utf-8").alias("raw"), "spots")
    return one.select("doc_id", "text_key", "raw", F.explode("spots").alias("w")).select(
        "w.anchor", "w.many", "w.hot", "doc_id", "text_key", "w.start", "w.n_starts", F.expr("substring(raw, w.start + 1, w.size)").alias("body")
    )


def _by_suffixes(windows: DataFrame, lengths: tuple[int, ...]) -> DataFrame:
    """(doc_id, text_key, start, n_starts, short): runs of starts whose strings occur in another window of the anchor."""

    def solve(rows: list[tuple]) -> Iterator[pa.RecordBatch]:
        first, hits = repeated_starts([np.frombuffer(r[6], dtype=np.uint8) for r in rows], [r[5] for r in rows], lengths)
        doc, key, start = (np.array([r[c] for r in rows]) for c in (2, 3, 4))
        many = np.array([r[1] for r in rows])
        for k, hit in enumerate(hits):
            edge = np.diff(np.concatenate([[0], hit.astype(np.int8), [0]]))
            lo, hi = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
            w = np.searchsorted(first, lo, "right") - 1
            new = ~many[w]  # windows that occur several times are known
            w, lo, hi = w[new], lo[new], hi[new]
            yield _found(doc[w], key[w], start[w] + lo - first[w], hi - lo, k > 0)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if size >= ARRAY_BYTES and held[-1][0] != row[0]:
                    yield from solve(held)
                    held, size = [], 0
                held.append(row)
                size += len(row[6])
        if held:
            yield from solve(held)

    dealt = windows.select("anchor", "many", "doc_id", "text_key", "start", "n_starts", "body").repartition("anchor").sortWithinPartitions("anchor")
    return dealt.mapInArrow(_text.released(run), _FOUND)


def _by_counts(windows: DataFrame, length: int, short: bool) -> DataFrame:
    """The same for anchors with too many windows for one suffix array: every string is counted by two independent hashes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for doc, key, start, n, body in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                data = np.frombuffer(body, dtype=np.uint8)
                n = min(n, len(data) - length + 1)
                if n <= 0:
                    continue
                keys = []
                for symbols in (data, _SYMBOL[data]):
                    h, inv = _text.prefix_hashes(symbols)
                    keys.append(pa.array(_text.mix((h[length : length + n] - h[:n]) * inv[:n]).view(np.int64)))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(n, doc)), pa.array(np.full(n, key, dtype=np.int32)), pa.array((start + np.arange(n)).astype(np.int32)), *keys], names=["doc_id", "text_key", "start", "k1", "k2"])

    strings = windows.select("doc_id", "text_key", "start", "n_starts", "body").mapInArrow(_text.released(run), "doc_id long, text_key int, start int, k1 long, k2 long")
    often = strings.groupBy("k1", "k2").agg(F.count("*").alias("n")).where("n > 1").select(F.bitwise_not("k1").alias("w"), "k2")
    return strings.withColumn("w", F.bitwise_not("k1")).join(often, ["w", "k2"]).select("doc_id", "text_key", "start", F.lit(1).alias("n_starts"), F.lit(short).alias("short"))


def remove_repeats(docs: DataFrame, length: int = LENGTH, report: int | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_bytes, spans, kept, n_reported): every byte covered by a string of length bytes that also starts elsewhere is removed.

    spans: maximal removed runs as array<struct<start,end>> of bytes; kept: the remaining bytes, in order; n_reported:
    bytes covered by strings of report bytes (at most length; by default length) that also start elsewhere.
    """
    modest_batches(docs.sparkSession)
    report = length if report is None else report
    if not 2 * GRAM <= report <= length:
        raise ValueError(f"the shorter length must be at least {2 * GRAM}, and not above the other")
    lengths = (length,) if report == length else (length, report)
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text")).select("doc_id", F.hash("text").alias("text_key"), "text")
    spots = materialize(_windows(slim, report, length), "spots")
    # Keys of joins are turned, so that what was grouped is dealt anew and a popular anchor can be split over tasks.
    turned = F.bitwise_not("anchor").alias("w")
    shared = spots.groupBy("anchor").agg(F.count("*").alias("n"), F.min("win").alias("lo"), F.max("win").alias("hi")).where("n > 1")
    again = materialize(spots.withColumn("w", turned).join(shared.select(turned, (F.col("lo") != F.col("hi")).alias("mixed")), "w").drop("w"), "again")
    forget(spots)
    by_win = materialize(
        again.groupBy("anchor", "win").agg(F.count("*").alias("n"), F.first("mixed").alias("mixed"), F.min(F.struct("doc_id", "text_key", "start", "n_starts", "size")).alias("w")), "by-win"
    )
    pair = ["w", "win"]
    whole = again.withColumn("w", turned).join(by_win.where("n > 1").select(turned, "win"), pair)
    whole = materialize(whole.select("doc_id", "text_key", "start", "n_starts", "size"), "whole")
    forget(again)
    per_anchor = by_win.where("mixed").groupBy("anchor").agg(F.count("*").alias("wins")).select(turned, (F.col("wins") > TOGETHER).alias("hot"))
    wanted = by_win.where("mixed").select(turned, "anchor", (F.col("n") > 1).alias("many"), F.col("w").alias("at")).join(per_anchor, "w")
    windows = materialize(_cut_out(slim, wanted.select("anchor", "many", "hot", "at.doc_id", "at.text_key", "at.start", "at.n_starts", "at.size")), "windows")
    forget(by_win)
    marks = _by_suffixes(windows.where("not hot"), lengths)
    hot = windows.where("hot")
    some_hot = not hot.isEmpty()
    for k, own in enumerate(lengths):
        fits = F.least(F.col("n_starts"), F.col("size") - own + 1)
        marks = marks.unionByName(whole.where(fits > 0).select("doc_id", "text_key", "start", fits.alias("n_starts"), F.lit(k > 0).alias("short")))
        if some_hot:
            marks = marks.unionByName(_by_counts(hot, own, k > 0))
    per_doc = marks.groupBy("doc_id", "text_key").agg(F.collect_set(F.struct("start", "n_starts", "short")).alias("marks"))

    def runs_of(found: list[dict], short: bool, length: int) -> list[list[int]]:
        runs: list[list[int]] = []
        for a, b in sorted((x["start"], x["start"] + x["n_starts"] + length - 1) for x in found if x["short"] == short):
            if runs and a <= runs[-1][1]:
                runs[-1][1] = max(runs[-1][1], b)
            else:
                runs.append([a, b])
        return runs

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(1)
            for part in range(0, batch.num_rows, 256):
                ids, raws, sizes, spans, kept, told = batch.column(0).slice(part, 256), texts.slice(part, 256), [], [], [], []
                for raw, found in zip(raws, batch.column(2).slice(part, 256).to_pylist(), strict=True):
                    body = raw.as_py().encode()
                    sizes.append(len(body))
                    runs = runs_of(found or [], False, length)
                    spans.append([{"start": a, "end": b} for a, b in runs])
                    cuts = [0, *(x for r in runs for x in r), len(body)]
                    kept.append(b"".join(body[a:b] for a, b in zip(cuts[::2], cuts[1::2], strict=True)) if runs else body)
                    told.append(sum(b - a for a, b in (runs if len(lengths) == 1 else runs_of(found or [], True, report))))
                kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
                yield pa.RecordBatch.from_arrays(
                    [ids, pa.array(sizes, pa.int64()), pa.array(spans, kind), pa.array(kept, pa.binary()), pa.array(told, pa.int64())], names=["doc_id", "n_bytes", "spans", "kept", "n_reported"]
                )

    joined = slim.join(per_doc, ["doc_id", "text_key"], "left").select("doc_id", "text", "marks")
    return joined.mapInArrow(_text.released(cut), "doc_id long, n_bytes long, spans array<struct<start:long,end:long>>, kept binary, n_reported long")
