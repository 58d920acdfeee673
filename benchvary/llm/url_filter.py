"""URL filter: host and path rules first, gradient-boosted trees on lexical features for the rest.

The trees are trained on labelled URLs, those that a rule decides, in a bounded sample, and compiled into one Spark
column expression over native features: lengths, depth, digit share, entropy, parameter counts, and statistics of the
host's suffixes (how the labelled URLs under the same last label, or last two, were judged), kept for every suffix.

Defined results: a null URL or one without :// has empty host and path and is judged by its features all the same;
rules compare ASCII case-insensitively on hosts and exactly on paths; with labels of one kind only that verdict is
given, without labels allow; repeated rows are judged alike; an empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SAMPLE_ROWS = 20_000
#: The most frequent suffixes, whose statistics are part of the expression; those of all others meet the URLs in a join.
SUFFIXES = 200
#: Parts over which the URLs under those suffixes are dealt out in that join.
SALTS = 1024
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
FEATURES = ("url_len", "host_len", "path_len", "depth", "host_labels", "digits", "params", "marks", "entropy", "upper", "last_len", "https")


@dataclass(frozen=True)
class Rule:
    verdict: str
    host: str
    path: str

    @classmethod
    def of(cls, verdict: str, text: str) -> Rule:
        host, slash, path = text.partition("/")
        return cls(verdict, host.lower(), slash + path)

    @property
    def text(self) -> str:
        return self.host + self.path


def split_url(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path; empty without ://."""
    at = F.locate("://", url)
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url)))
    host = F.coalesce(F.translate(F.regexp_extract(rest, r"^([^/?#]*)", 1), _UPPER, _LOWER), F.lit(""))
    path = F.coalesce(F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1), F.lit(""))
    return host, path


def matched_rule(host: Column, path: Column, rules: tuple[Rule, ...]) -> tuple[Column, Column]:
    """(rule text, verdict) of the longest rule that fits, both null if none does; of equal rules the first."""
    text = verdict = F.lit(None).cast("string")
    for rule in sorted(reversed(rules), key=lambda r: len(r.text)):
        fits = ((host == rule.host) | F.endswith(host, F.lit("." + rule.host))) & F.startswith(path, F.lit(rule.path))
        text, verdict = F.when(fits, F.lit(rule.text)).otherwise(text), F.when(fits, F.lit(rule.verdict)).otherwise(verdict)
    return text, verdict


def _count(text: Column, what: str) -> Column:
    return (F.length(text) - F.length(F.translate(text, what, ""))).cast("double")


def lexical_features(url: Column, host: Column, path: Column) -> dict[str, Column]:
    url = F.coalesce(url, F.lit(""))
    n = F.greatest(F.length(url), F.lit(1)).cast("double")
    chars = "abcdefghijklmnopqrstuvwxyz0123456789./-"
    low = F.translate(url, _UPPER, _LOWER)
    entropy = F.lit(0.0)
    for c in chars:
        p = _count(low, c) / n
        entropy = entropy - F.when(p > 0, p * F.log2(p)).otherwise(F.lit(0.0))
    query = F.regexp_extract(url, r"\?([^#]*)", 1)
    return {
        "url_len": F.length(url).cast("double"),
        "host_len": F.length(host).cast("double"),
        "path_len": F.length(path).cast("double"),
        "depth": _count(path, "/"),
        "host_labels": _count(host, "."),
        "digits": _count(url, "0123456789") / n,
        "params": F.when(query != "", _count(query, "&") + 1.0).otherwise(F.lit(0.0)),
        "marks": _count(url, "-_%~=&?#"),
        "entropy": entropy,
        "upper": _count(url, _UPPER),
        "last_len": F.length(F.regexp_extract(path, r"([^/]*)/?$", 1)).cast("double"),
        "https": F.startswith(url, F.lit("https://")).cast("double"),
    }


def _suffix(host: Column, labels: int) -> Column:
    return F.substring_index(host, ".", -labels)


def boost(x: np.ndarray, y: np.ndarray, trees: int = 20, depth: int = 3, rate: float = 0.3, bins: int = 32) -> tuple[float, list]:
    """Trees of nested (feature, bound, left, right) or leaf values, by second-order steps on the logistic loss."""
    share = np.clip(y.mean(), 1e-6, 1 - 1e-6)
    bias = float(np.log(share / (1 - share)))
    cuts = [np.unique(np.quantile(x[:, k], np.linspace(0.02, 0.98, bins))) for k in range(x.shape[1])]
    binned = np.stack([np.searchsorted(c, x[:, k], "left") for k, c in enumerate(cuts)], axis=1)
    logit, forest = np.full(len(y), bias), []

    def grow(rows: np.ndarray, g: np.ndarray, h: np.ndarray, left: int):
        total_g, total_h = g[rows].sum(), h[rows].sum()
        leaf = float(rate * total_g / (total_h + 1.0))
        best = None
        if left and len(rows) >= 20:
            for k, c in enumerate(cuts):
                sg = np.bincount(binned[rows, k], g[rows], len(c) + 1).cumsum()[:-1]
                sh = np.bincount(binned[rows, k], h[rows], len(c) + 1).cumsum()[:-1]
                ok = (sh > 1.0) & (total_h - sh > 1.0)
                gain = np.where(ok, sg**2 / (sh + 1.0) + (total_g - sg) ** 2 / (total_h - sh + 1.0), -1.0)
                if len(gain) and (best is None or gain.max() > best[0]):
                    best = (gain.max(), k, int(gain.argmax()))
        if best is None or best[0] <= total_g**2 / (total_h + 1.0) + 1e-6:
            logit[rows] += leaf
            return leaf
        _, k, at = best
        low = binned[rows, k] <= at
        return (k, float(cuts[k][at]), grow(rows[low], g, h, left - 1), grow(rows[~low], g, h, left - 1))

    for _ in range(trees):
        p = 1 / (1 + np.exp(-logit))
        forest.append(grow(np.arange(len(y)), y - p, np.maximum(p * (1 - p), 1e-6), depth))
    return bias, forest


def _compiled(tree, names: list[str]) -> Column:
    if isinstance(tree, float):
        return F.lit(tree)
    k, bound, low, high = tree
    return F.when(F.col(names[k]) <= bound, _compiled(low, names)).otherwise(_compiled(high, names))


def _with_shares(base: DataFrame, labels: int) -> tuple[DataFrame, Column]:
    """base with what the column needs, and the column: how labelled URLs under the suffix of host were judged, smoothed."""
    suffix, block = _suffix(F.col("host"), labels), (F.col("_judged_") == "block").cast("long")
    known = base.groupBy(suffix.alias("s")).agg(F.count("*").alias("m"), F.count("_judged_").alias("n"), F.coalesce(F.sum(block), F.lit(0)).alias("b"))
    share = ((F.col("b") + 1.0) / (F.col("n") + 2.0)).alias("share")
    top = known.select("s", "m", share).orderBy(F.desc("m"), "s").limit(SUFFIXES + 1).collect()
    head = {r["s"]: r["share"] for r in top[:SUFFIXES]}
    if not head:
        return base, F.lit(0.5)
    value = F.try_element_at(F.create_map(*[F.lit(v) for pair in head.items() for v in pair]), suffix)
    if len(top) > SUFFIXES:
        s, salt, share_at = f"_s{labels}_", f"_salt{labels}_", f"_share{labels}_"
        in_head = lambda x: x.isin(list(head))
        tail = known.where(~in_head(F.col("s")) & (F.col("n") > 0)).select(F.col("s").alias(s), F.lit(0).cast("long").alias(salt), share.alias(share_at))
        dealt = F.when(in_head(suffix), F.pmod(F.xxhash64("_url_", *[c for c in base.columns if c != "_url_"]), F.lit(SALTS)) + 1).otherwise(F.lit(0)).cast("long")
        base = base.withColumns({s: suffix, salt: dealt}).join(tail, [s, salt], "left").drop(s, salt)
        value = F.coalesce(value, F.col(share_at))
    return base, F.coalesce(value, F.lit(0.5))


def judge_urls(pages: DataFrame, rules: tuple[Rule, ...], url_col: str = "url", keep: tuple[str, ...] = ("page_id",), sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """The columns of keep with host, path, rule, verdict and block_score (the trees' share for block)."""
    url = F.col("_url_")
    base = pages.select(*keep, F.col(url_col).alias("_url_"))
    host, path = split_url(url)
    base = base.withColumns({"host": host, "path": path})
    rule, verdict = matched_rule(F.col("host"), F.col("path"), rules)
    base = base.withColumns({"rule": rule, "_judged_": verdict})
    n = base.where(F.col("_judged_").isNotNull()).count()
    feats = lexical_features(url, F.col("host"), F.col("path"))
    for labels in (1, 2):
        base, feats[f"suffix{labels}"] = _with_shares(base, labels)
    names = [f"_f_{k}" for k in feats]
    full = base.withColumns(dict(zip(names, feats.values(), strict=True)))
    fit = full.where(F.col("_judged_").isNotNull()).select(*names, (F.col("_judged_") == "block").cast("int").alias("y"), F.xxhash64(*keep, "_url_").alias("h"))
    if n > sample_rows:
        fit = fit.where(F.pmod("h", F.lit(1 << 20)) < int(sample_rows / n * (1 << 20)))
    data = fit.drop("h").toPandas().sort_values([*names, "y"])
    y = data["y"].to_numpy(float)
    if not len(y) or y.min() == y.max():
        share = F.lit(float(y[0])) if len(y) else F.lit(0.0)
    else:
        bias, forest = boost(data[names].to_numpy(float), y)
        total = F.lit(bias)
        for tree in forest:
            total = total + _compiled(tree, names)
        share = 1.0 / (1.0 + F.exp(-total))
    judged = full.withColumn("block_score", share)
    return judged.select(*keep, "host", "path", "rule", F.coalesce("_judged_", F.when(F.col("block_score") >= 0.5, F.lit("block")).otherwise(F.lit("allow"))).alias("verdict"), "block_score")
