"""Outside services behind one batch protocol: a provider gets a pandas frame and gives one value for each row.

Generator, judge, answerer and caption inferrer differ only in the columns that they read. Providers run on the workers
in Arrow batches, must be picklable, and should give equal values for equal rows, since a lost task runs again; answers
that are costly are kept by calling through `cached`, which asks only for prompts that its table lacks.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import Protocol

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from benchvary.functions.text import normalize_answer


class Provider(Protocol):
    def __call__(self, batch: pd.DataFrame) -> pd.Series: ...


def called(df: DataFrame, provider: Provider, inputs: tuple[str, ...], name: str, kind: str = "string", batch: int = 256) -> DataFrame:
    """df with the provider's value for each row as column name; inputs: the columns that it gets. Null values stay null."""
    schema = T.StructType([*df.schema.fields, T.StructField(name, T._parse_datatype_string(kind))])

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for i in range(0, len(frame), batch):
                part = frame.iloc[i : i + batch].reset_index(drop=True)
                part[name] = provider(part[list(inputs)])
                yield part

    return df.mapInPandas(run, schema)


def cached(df: DataFrame, provider: Provider, inputs: tuple[str, ...], name: str, store: DataFrame | None = None, kind: str = "string") -> tuple[DataFrame, DataFrame]:
    """df with the provider's values, and the table (prompt_key, value) that a later run can pass as store.

    Each distinct prompt is asked once, and only if store lacks it.
    """
    from benchvary.session import materialize

    key = F.sha2(F.to_json(F.struct(*inputs)), 256).alias("prompt_key")
    asked = df.select(key, *inputs).dropDuplicates(["prompt_key"])
    if store is not None:
        asked = asked.join(store.select("prompt_key"), "prompt_key", "left_anti")
    new = materialize(called(asked, provider, inputs, "value", kind).select("prompt_key", "value"), "provider")
    known = new if store is None else store.select("prompt_key", "value").unionByName(new)
    return df.withColumn("prompt_key", key).join(known.withColumnRenamed("value", name), "prompt_key", "left").drop("prompt_key"), known


def caption_settles(pairs: DataFrame, provider: Provider) -> DataFrame:
    """pairs(question, answer, caption, ...) for which the provider says that the caption alone gives the answer."""
    return called(pairs, provider, ("question", "answer", "caption"), "settles", "boolean").where("settles").drop("settles")


def span_provider(batch: pd.DataFrame) -> pd.Series:
    """The default inferrer: the caption holds the answer."""

    def plain(s: pd.Series) -> list[str]:
        return [" ".join("".join(c if c.isalnum() else " " for c in (x or "").lower()).split()) for x in s]

    return pd.Series([bool(a) and a in c for a, c in zip(plain(batch["answer"]), plain(batch["caption"]), strict=True)])


def scored(answers: DataFrame, reference: str = "reference", raw: str = "raw") -> DataFrame:
    """Answers from a provider or an external table, with correct: the whole answer, as plain words, equals the reference."""
    return answers.withColumn("correct", F.coalesce((normalize_answer(F.col(raw)) == normalize_answer(F.col(reference))).cast("int"), F.lit(0)))
