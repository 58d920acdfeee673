"""Sparse rule ensemble for text quality.

Statistics of whole texts are computed in one scan. Shallow boosted trees are grown on a bounded sample of labelled
rows; every path from a root to a node becomes a conjunctive rule over statistics; a lasso logistic regression gives
most rules the weight zero; what is left is compiled into one Spark column expression, so scoring is plain
arithmetic over columns.

Defined results: null and empty texts have all statistics 0 and get a score like any other; repeated rows are scored
alike; labels that are null are not learnt from; without labelled rows of both classes the score is the share of
label 1 among them, or 0.5; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from benchvary.llm import _text
from benchvary.session import modest_batches

#: Bound of the sample of labelled rows that the ensemble is fitted on.
SAMPLE_ROWS = 20_000
#: Bytes of text handled at once.
SLICE = 512 << 10
STATISTICS = ("n_words", "word_len", "distinct_words", "top_word", "letters", "upper", "digits", "marks", "symbols", "line_len", "repeated_lines", "short_words")

_CLASS = {
    "letters": [*range(65, 91), *range(97, 123), *range(128, 256)],
    "upper": [*range(65, 91)],
    "digits": [*range(48, 58)],
    "marks": [33, 34, 39, 40, 41, 44, 45, 46, 58, 59, 63],
    "symbols": [35, 36, 37, 38, 42, 43, 47, 60, 61, 62, 64, 91, 92, 93, 94, 95, 96, 123, 124, 125, 126],
}


def _statistics(column: pa.Array) -> np.ndarray:
    """A row of STATISTICS for each text."""
    out = []
    for i, j, data, offsets in _text.slices(column, SLICE):
        n = j - i
        size = np.maximum(np.diff(offsets), 1).astype(float)
        f = {k: np.zeros(n) for k in STATISTICS}
        starts, ends, per_row = _text.word_bounds(data, offsets)
        if len(data):
            h, inv = _text.prefix_hashes(data)
            own = _text.mix((h[ends] - h[starts]) * inv[starts])
            row = np.repeat(np.arange(n), per_row)
            words = np.maximum(per_row, 1)
            f["n_words"] = per_row.astype(float)
            f["word_len"] = np.bincount(row, ends - starts, n) / words
            f["short_words"] = np.bincount(row, (ends - starts) <= 3, n) / words
            order = np.lexsort((own, row))
            v, r = own[order], row[order]
            new = np.ones(len(v), dtype=bool)
            new[1:] = (v[1:] != v[:-1]) | (r[1:] != r[:-1])
            f["distinct_words"] = np.bincount(r[new], minlength=n) / words
            heads = np.flatnonzero(new)
            np.maximum.at(top := np.zeros(n), r[heads], np.diff(np.append(heads, len(v))))
            f["top_word"] = top / words
            cut = np.searchsorted
            for k, codes in _CLASS.items():
                table = np.zeros(256, dtype=bool)
                table[codes] = True
                at = np.flatnonzero(table[data])
                f[k] = np.diff(cut(at, offsets)) / size
            breaks = np.flatnonzero(data == 10)
            bounds = np.unique(np.concatenate([offsets[:-1][np.diff(offsets) > 0], breaks + 1]))
            bounds = bounds[bounds < len(data)]
            line_end = np.append(bounds[1:], len(data))
            line_row = np.searchsorted(offsets, bounds, "right") - 1
            lines = np.maximum(np.bincount(line_row, minlength=n), 1)
            f["line_len"] = np.diff(offsets) / lines
            body = _text.mix((h[line_end] - h[bounds]) * inv[bounds])
            order = np.lexsort((body, line_row))
            same = (body[order][1:] == body[order][:-1]) & (line_row[order][1:] == line_row[order][:-1])
            f["repeated_lines"] = np.bincount(line_row[order][1:][same], minlength=n) / lines
        out.append(np.stack([f[k] for k in STATISTICS], axis=1))
    return np.concatenate(out) if out else np.zeros((0, len(STATISTICS)))


def text_statistics(docs: DataFrame, text_col: str = "text", keep: tuple[str, ...] = ("doc_id",), within: str | None = None) -> DataFrame:
    """The columns of keep with the statistics as doubles named q_<statistic>.

    within: a struct column of keep that holds the text; it then travels once. Null texts count as empty.
    """
    modest_batches(docs.sparkSession)
    body = text_col
    while body in keep:
        body += "_"
    schema = docs.select(*keep).schema
    slim = docs.select(*keep) if within else docs.select(*keep, F.col(text_col).alias(body))
    at = keep.index(within) if within else len(keep)
    place = schema[within].dataType.names.index(text_col) if within else 0
    names = [*keep, *(f"q_{k}" for k in STATISTICS)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            stats = _statistics(batch.column(at).field(place) if within else batch.column(at))
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in range(len(keep))), *(pa.array(stats[:, k]) for k in range(len(STATISTICS)))], names=names)

    out = schema
    for k in STATISTICS:
        out = out.add(f"q_{k}", "double")
    return slim.mapInArrow(_text.released(run), out)


@dataclass
class Rule:
    """A conjunction of (statistic, is_greater, bound) with its weight."""

    terms: tuple[tuple[int, bool, float], ...]
    weight: float = 0.0

    def fires(self, x: np.ndarray) -> np.ndarray:
        hit = np.ones(len(x), dtype=bool)
        for k, greater, bound in self.terms:
            hit &= (x[:, k] > bound) == greater
        return hit

    def column(self) -> Column:
        cond = F.lit(True)
        for k, greater, bound in self.terms:
            c = F.col(f"q_{STATISTICS[k]}")
            cond = cond & ((c > F.lit(bound)) if greater else (c <= F.lit(bound)))
        return F.when(cond, F.lit(self.weight)).otherwise(F.lit(0.0))


@dataclass
class RuleEnsemble:
    bias: float
    rules: list[Rule] = field(default_factory=list)

    def score(self) -> Column:
        """The compiled score, 0 to 1, over columns q_<statistic>."""
        total = F.lit(self.bias)
        for rule in self.rules:
            total = total + rule.column()
        return 1.0 / (1.0 + F.exp(-total))

    def predict(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-(self.bias + sum((r.fires(x) * r.weight for r in self.rules), np.zeros(len(x))))))


def _grow(x: np.ndarray, residual: np.ndarray, cuts: list[np.ndarray], depth: int, least: int) -> tuple[list[tuple], np.ndarray]:
    """Rules of one regression tree by exact search over quantile cuts, and its prediction."""
    rules, fit, todo = [], np.zeros(len(x)), [((), np.arange(len(x)))]
    while todo:
        terms, rows = todo.pop()
        r, best = residual[rows], None
        fit[rows] = r.mean()
        if len(terms) < depth and len(rows) >= 2 * least:
            for k, c in enumerate(cuts):
                if not len(c):
                    continue
                bin_ = np.searchsorted(c, x[rows, k], "left")
                n = np.bincount(bin_, minlength=len(c) + 1).cumsum()[:-1]
                s = np.bincount(bin_, r, len(c) + 1).cumsum()[:-1]
                ok = (n >= least) & (len(rows) - n >= least)
                if ok.any():
                    gain = np.where(ok, s**2 / np.maximum(n, 1) + (r.sum() - s) ** 2 / np.maximum(len(rows) - n, 1), -1.0)
                    at = int(gain.argmax())
                    if best is None or gain[at] > best[0]:
                        best = (gain[at], k, float(c[at]))
            if best and best[0] > r.sum() ** 2 / len(rows) + 1e-9:
                _, k, bound = best
                up = x[rows, k] > bound
                for greater in (False, True):
                    path = (*terms, (k, greater, bound))
                    rules.append(path)
                    todo.append((path, rows[up == greater]))
    return rules, fit


def fit_ensemble(x: np.ndarray, y: np.ndarray, trees: int = 24, depth: int = 3, rate: float = 0.3, penalty: float = 0.002, steps: int = 400) -> RuleEnsemble:
    """Trees by gradient boosting on the logistic loss, then lasso weights by accelerated proximal gradient steps."""
    y = y.astype(float)
    if not len(y) or y.min() == y.max():
        share = (y.sum() + 1) / (len(y) + 2) if len(y) else 0.5
        return RuleEnsemble(float(np.log(share / (1 - share))))
    cuts = [np.unique(np.quantile(x[:, k], np.linspace(0.01, 0.99, 49))) for k in range(x.shape[1])]
    logit, seen = np.full(len(y), np.log(y.mean() / (1 - y.mean()))), {}
    least = max(5, len(y) // 200)
    for _ in range(trees):
        p = 1 / (1 + np.exp(-logit))
        rules, fit = _grow(x, y - p, cuts, depth, least)
        seen.update(dict.fromkeys(rules))
        logit = logit + rate * 4 * fit
    rules = [Rule(t) for t in seen]
    fires = np.stack([r.fires(x) for r in rules], axis=1).astype(float) if rules else np.zeros((len(y), 0))
    mean = fires.mean(axis=0)
    scale = np.sqrt(np.maximum(mean * (1 - mean), 1e-3))
    z = (fires - mean) / scale
    w = v = np.zeros(z.shape[1])
    b, t = float(np.log(y.mean() / (1 - y.mean()))), 1.0
    rate_ = 4 / max(np.linalg.norm(z, 2) ** 2 / len(y), 1e-9)
    for _ in range(steps):
        g = 1 / (1 + np.exp(-(b + z @ v))) - y
        b -= 2.0 * g.mean()
        new = v - rate_ * (z.T @ g) / len(y)
        new = np.sign(new) * np.maximum(np.abs(new) - rate_ * penalty, 0)
        t_new = (1 + np.sqrt(1 + 4 * t * t)) / 2
        v, w, t = new + (t - 1) / t_new * (new - w), new, t_new
    kept = np.flatnonzero(np.abs(w) > 1e-6)
    weights = w / scale
    return RuleEnsemble(float(b - (w * mean / scale).sum()), [Rule(rules[k].terms, float(weights[k])) for k in kept])


def train(stats: DataFrame, labels: DataFrame, label_col: str = "quality", id_col: str = "doc_id", sample_rows: int = SAMPLE_ROWS) -> RuleEnsemble:
    """Fit on at most about sample_rows labelled rows, taken evenly by a hash of the id."""
    known = labels.where(F.col(label_col).isNotNull() & F.col(id_col).isNotNull()).groupBy(F.col(id_col).cast("long").alias("doc_id")).agg(F.max(label_col).cast("int").alias("y"))
    n = known.count()
    if n > sample_rows:
        share = sample_rows / n
        known = known.where((F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) / (1 << 20)) < share)
    met = stats.join(F.broadcast(known), "doc_id").groupBy("doc_id").agg(F.min(F.struct("y", *(f"q_{k}" for k in STATISTICS))).alias("r"))  # an id that repeats counts once
    rows = met.select("r.*").toPandas()
    order = np.lexsort(rows.to_numpy(float).T) if len(rows) else []
    x = rows[[f"q_{k}" for k in STATISTICS]].to_numpy(float)[order]
    return fit_ensemble(x, rows["y"].to_numpy(float)[order])
