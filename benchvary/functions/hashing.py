"""Portable randomness: md5 buckets, equal in every SQL engine and stable under retries."""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column
from pyspark.sql import functions as F


def stable_hash(*parts: Column | str) -> Column:
    """First 32 bits of md5 of the parts joined with |; strings are literals."""
    cols = [F.lit(p) if isinstance(p, str) else p.cast("string") for p in parts]
    return F.conv(F.substring(F.md5(F.concat_ws("|", *cols)), 1, 8), 16, 10).cast("long")


def stable_bucket(n: int | Column, *parts: Column | str) -> Column:
    return stable_hash(*parts) % n


#: Shifts, sines and word order of md5 (RFC 1321), for many short messages at once.
_TURNS = ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21))
_SINES = [int(abs(math.sin(i + 1)) * 2**32) for i in range(64)]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
#: Messages that go through the rounds together, so that they stay in the processor's cache; bytes that fit one block.
_TOGETHER, _SHORT = 4096, 55


def _first_words(blocks: np.ndarray) -> np.ndarray:
    """First 32 bits of md5, as stable_hash reads them, of one padded block a row (bytes). The last three rounds don't touch them."""
    words = np.ascontiguousarray(blocks.view("<u4").T)
    used = words.any(axis=1)
    n = words.shape[1]
    a, b, c, d = (np.full(n, v, np.uint32) for v in _START)
    f, t = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(61):
        kind = i // 16
        if kind == 0:
            np.bitwise_xor(c, d, out=f), np.bitwise_and(f, b, out=f), np.bitwise_xor(f, d, out=f)
        elif kind == 1:
            np.bitwise_xor(b, c, out=f), np.bitwise_and(f, d, out=f), np.bitwise_xor(f, c, out=f)
        elif kind == 2:
            np.bitwise_xor(b, c, out=f), np.bitwise_xor(f, d, out=f)
        else:
            np.invert(d, out=f), np.bitwise_or(f, b, out=f), np.bitwise_xor(f, c, out=f)
        np.add(a, f, out=a), np.add(a, np.uint32(_SINES[i]), out=a)
        if used[g := (i, 5 * i + 1, 3 * i + 5, 7 * i)[kind] % 16]:
            np.add(a, words[g], out=a)
        turn = _TURNS[kind][i % 4]
        np.left_shift(a, np.uint32(turn), out=t), np.right_shift(a, np.uint32(32 - turn), out=a)
        np.bitwise_or(a, t, out=a), np.add(a, b, out=a)
        a, b, c, d = d, a, b, c
    return (b + np.uint32(_START[0])).byteswap()


def hash_many(keys: pa.Array, around: list[tuple[bytes, bytes]]) -> np.ndarray:
    """stable_hash of prefix + key + suffix, a row for each key and a column for each (prefix, suffix); a null key counts as empty."""
    keys = pc.fill_null(keys.cast(pa.large_binary()), b"")
    out = np.empty((len(keys), len(around)), np.uint32)
    if not len(keys):
        return out
    ends = np.frombuffer(keys.buffers()[1], np.int64)[keys.offset : keys.offset + len(keys) + 1]
    data = np.frombuffer(keys.buffers()[2] or b"", np.uint8)
    sizes = np.diff(ends)
    for size in np.unique(sizes):  # keys of one length have everything at the same place
        rows = np.flatnonzero(sizes == size)
        for k in range(0, len(rows), _TOGETHER):
            some = rows[k : k + _TOGETHER]
            text = data[ends[some][:, None] + np.arange(size)]
            for col, (before, after) in enumerate(around):
                length = len(before) + int(size) + len(after)
                if length > _SHORT:
                    out[some, col] = [int.from_bytes(hashlib.md5(before + t.tobytes() + after, usedforsecurity=False).digest()[:4], "big") for t in text]
                    continue
                blocks = np.zeros((len(some), 64), np.uint8)
                tail = np.frombuffer(after + b"\x80", np.uint8)
                blocks[:, : len(before)] = np.frombuffer(before, np.uint8)
                blocks[:, len(before) : len(before) + size] = text
                blocks[:, length - len(after) : length + 1] = tail
                blocks[:, 56], blocks[:, 57] = length * 8 & 255, length * 8 >> 8
                out[some, col] = _first_words(blocks)
    return out


def stable_buckets(key: Column, parts: dict[str, int], last: int, first: int = 1) -> Column:
    """array<long>: stable_bucket(n, salt.., key, k) for each (salt|.., n) of parts and each k from first to last, salt by salt.

    The same numbers as stable_bucket gives, worked out for a batch of rows at once: several times less CPU where a key
    meets many salts. Refer to the column more than once, outside lambdas or inside: Spark then works it out once a row.
    """
    around = [(f"{salt}|".encode(), f"|{k}".encode()) for salt in parts for k in range(first, last + 1)]
    most = np.repeat(np.array(list(parts.values()), np.int64), last + 1 - first)

    def run(keys: pa.Array) -> pa.Array:
        flat = (hash_many(keys, around) % most).ravel()
        return pa.ListArray.from_arrays(pa.array(np.arange(0, len(flat) + 1, len(around), dtype=np.int32)), pa.array(flat))

    return F.arrow_udf(run, "array<long>")(key)


def first_free(key: Column, held: Column, pool: Column) -> Column:
    """The name of pool that is not held and has the smallest stable_hash("n", key, name), then the smallest name; null for a null key."""

    def run(keys: pa.Array, held: pa.Array, pool: pa.Array) -> pa.Array:
        live = np.flatnonzero(keys.is_valid().to_numpy(zero_copy_only=False))
        if not len(live):
            return pa.nulls(len(keys), pa.string())
        names = sorted(x for x in pool[int(live[0])].as_py() if x is not None)  # one pool for all rows
        held = held.take(pa.array(live))
        taken = np.zeros((len(live), len(names) + 1), bool)
        at = pc.fill_null(pc.index_in(held.flatten(), pa.array(names, pa.string())), len(names)).to_numpy(zero_copy_only=False)
        taken[pc.list_parent_indices(held).to_numpy(zero_copy_only=False), at] = True
        numbers = hash_many(keys.take(pa.array(live)).cast(pa.string()), [(b"n|", f"|{x}".encode()) for x in names]).astype(np.int64)
        numbers[taken[:, :-1]] = 1 << 40
        out = np.full(len(keys), None, object)
        if names:
            best = numbers.argmin(axis=1)  # the first of equal ones
            some = numbers[np.arange(len(live)), best] < 1 << 40
            out[live[some]] = np.array(names, object)[best[some]]
        return pa.array(out, pa.string())

    return F.arrow_udf(run, "string")(key, held, pool)
