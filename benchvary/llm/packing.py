"""Concatenate and cut: all documents form one long row of token ids, which is cut into windows of equal length.

Two passes. The first tokenises every document once, writes its ids and its offset inside its partition, and
sums tokens by partition. A prefix sum over the partition totals (one number for each partition) gives each
document its place in the whole row; the second pass cuts documents at window borders with no shuffle. A document
that crosses a border leaves one record in each window. Only the very last window can have padding.

Defined results: null text counts as empty, and a document without text has the separator alone; repeated rows are
packed once each; extra columns are ignored; an empty table gives no pieces. Documents of any length are cut freely.
"""

from __future__ import annotations

import json
import os
import re
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from benchvary.llm import _text
from benchvary.session import materialize, modest_batches

WINDOW = 1024
SEPARATOR_ID = 0
#: Chunks of text whose ids a Python worker keeps; then it starts anew.
CACHE_ENTRIES = 350_000

#: A space beside other white space: there the text can't be split at single spaces.
_NOT_ISOLATED = re.compile(r"\s | \s")
_ISOLATED = re.compile(r"(?<=\S) (?=\S)")


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


class _Known(dict):
    """Ids by chunk; a chunk that is not known is encoded, and kept while there is room."""

    def __init__(self, encode, code: str, lead: str):
        super().__init__()
        self.encode, self.code, self.lead = encode, code, lead

    def __missing__(self, chunk: str) -> bytes:
        ids = array(self.code, self.encode(self.lead + chunk)).tobytes()
        if len(self) >= CACHE_ENTRIES:
            self.clear()
        self[chunk] = ids
        return ids


class CachedTokenizer:
    """Ids of whole texts under a byte-level vocabulary of the tokenizers library, looked up chunk by chunk.

    Byte-level pre-tokenisation never joins text across a single space between two non-space characters, so a text's
    ids are those of its space-separated chunks in a row. A chunk that a worker has not met is encoded from the same
    file's vocabulary by the faster of two engines; tests hold whole texts against the tokenizers library itself.
    Strings of special tokens are ordinary text. A file of another kind (a normaliser, merges that are not in rank
    order, another pattern) goes through the tokenizers library whole.
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.path = path
        self.model = Tokenizer.from_file(path)
        self.model.encode_special_tokens = True
        self.kind = np.dtype("<u2") if self.model.get_vocab_size() <= 1 << 16 else np.dtype("<u4")
        self.code = "H" if self.kind.itemsize == 2 else "I"
        encode = self._by_ranks()
        self.first, self.later = (_Known(encode, self.code, lead) for lead in ("", " ")) if encode else (None, None)

    def _by_ranks(self):
        """An encoder over the file's own vocabulary, or None where ids are not ranks or a probe differs."""
        import public_tokenizers
        import tiktoken

        spec = json.loads(self.model.to_str())
        if spec.get("normalizer") or spec["model"]["type"] != "BPE" or (spec.get("pre_tokenizer") or {}).get("type") != "ByteLevel" or spec["pre_tokenizer"].get("add_prefix_space"):
            return None
        special = {t["content"] for t in spec.get("added_tokens", ())}
        plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
        byte_of = {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(x for x in range(256) if x not in set(plain))}
        ranks = {bytes(byte_of[c] for c in t): i for t, i in spec["model"]["vocab"].items() if t not in special}
        encode = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={}).encode_ordinary
        probes = ["", " ", "It's 12 o'clock,  isn't it?\n\n Zäöß naïve élève 東京 \u00a0x", "thntblere\tofhe  |  x=1;", " a\r\n b"]
        return encode if all(encode(p) == self.model.encode(p, add_special_tokens=False).ids for p in probes) else None

    def forget(self) -> None:
        """Drop the chunks met so far, as when a worker turns to another operator."""
        for known in (self.first, self.later):
            if known is not None:
                known.clear()

    def encode(self, text: str) -> bytes:
        if self.later is None:
            return array(self.code, self.model.encode(text, add_special_tokens=False).ids).tobytes()
        head, *rest = _ISOLATED.split(text) if _NOT_ISOLATED.search(text) else text.split(" ")
        return self.first[head] + b"".join(map(self.later.__getitem__, rest))


_TOKENIZERS: dict[str, CachedTokenizer] = {}


def _tokenizer(path: str) -> CachedTokenizer:
    if path not in _TOKENIZERS:
        _TOKENIZERS[path] = CachedTokenizer(path)
        _text.HELD.append(_TOKENIZERS[path].forget)
    return _TOKENIZERS[path]


def tokenized(docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text_col: str = "text", separator_id: int = SEPARATOR_ID) -> DataFrame:
    """First pass: (doc_id, n_tokens, ids, part, part_start), where part_start counts the tokens before it in its partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok, part, at = _tokenizer(tokenizer_path), TaskContext.get().partitionId(), 0
        end = np.array([separator_id], dtype=tok.kind).tobytes()
        for batch in batches:
            for i in range(0, batch.num_rows, 500):
                rows = batch.slice(i, 500)
                ids = [tok.encode(t or "") + end for t in rows.column(1).to_pylist()]
                n = np.array([len(x) // tok.kind.itemsize for x in ids], dtype=np.int64)
                starts = at + np.cumsum(n) - n
                at += int(n.sum())
                yield pa.RecordBatch.from_arrays(
                    [rows.column(0), pa.array(n), pa.array(ids, pa.binary()), pa.array(np.full(len(n), part, dtype=np.int64)), pa.array(starts)],
                    names=["doc_id", "n_tokens", "ids", "part", "part_start"],
                )

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(
        _text.released(run, keep=True), "doc_id long, n_tokens long, ids binary, part long, part_start long"
    )


def concatenate_and_cut(docs: DataFrame, window: int = WINDOW, tokenizer_path: str | None = None, id_col: str = "doc_id", text_col: str = "text", separator_id: int = SEPARATOR_ID) -> DataFrame:
    """Pieces (doc_id, start, length, ids, doc_tokens, sequence_id, offset); ids: unsigned 32-bit little-endian values.

    The partition totals that reach the driver are one pair of numbers for each partition of the input.
    """
    modest_batches(docs.sparkSession)
    path = tokenizer_path or default_tokenizer()
    table = materialize(tokenized(docs, path, id_col, text_col, separator_id), "tokens")
    totals = sorted((r["part"], r["n"]) for r in table.groupBy("part").agg(F.sum("n_tokens").alias("n")).collect())
    before, base = 0, {}
    for part, n in totals:
        base[part] = before
        before += n
    kind = _tokenizer(path).kind

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            doc, count, ids, part, start = (batch.column(k) for k in range(5))
            out: list[tuple] = []
            for d, n, raw, g in zip(doc.to_pylist(), count.to_pylist(), ids, (base[p] + s for p, s in zip(part.to_pylist(), start.to_pylist(), strict=True)), strict=True):
                wide = np.frombuffer(raw.as_buffer(), dtype=kind).astype("<u4").tobytes()
                at = 0
                while at < n:
                    seq, off = divmod(g + at, window)
                    length = min(window - off, n - at)
                    out.append((d, at, length, wide[4 * at : 4 * (at + length)], n, seq, off))
                    at += length
                if len(out) >= 20_000:
                    yield _pieces(out)
                    out = []
            if out:
                yield _pieces(out)

    return table.select("doc_id", "n_tokens", "ids", "part", "part_start").mapInArrow(_text.released(cut), "doc_id long, start long, length long, ids binary, doc_tokens long, sequence_id long, offset long")


def _pieces(rows: list[tuple]) -> pa.RecordBatch:
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.int64(), pa.int64(), pa.int64()]
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=["doc_id", "start", "length", "ids", "doc_tokens", "sequence_id", "offset"])
