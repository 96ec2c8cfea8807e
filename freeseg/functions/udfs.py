"""SQL functions: segment_text and bag_f1, and the table functions text_grams and text_tokens."""

from __future__ import annotations

from collections import Counter

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import apply, segment
from . import kernels


def freedom_slices(grams: DataFrame, config: segment.Config) -> apply.Model:
    """The slice of a trained model that a configuration reads, pruned at its level; it has to be small enough to broadcast."""
    held = apply.slices(grams, config)
    if held is None:
        raise ValueError(f"more than {apply.MOST_WINDOWS} windows; use segment.run, which joins them")
    return held


def register(spark: SparkSession, grams: DataFrame, config: segment.Config = segment.Config()) -> None:
    """Registers segment_text(lang, text) -> array<string> for a trained model, and bag_f1(hyp, ref) -> double, an aggregate of the tokens of rows."""
    own = apply.scorer(spark.sparkContext.broadcast(freedom_slices(grams, config)), config)

    @F.arrow_udf("array<string>")
    def segment_text(lang: pa.Array, text: pa.Array) -> pa.Array:
        return apply.tokens_of(pa.RecordBatch.from_arrays([lang, text], ["lang", "text"]), "lang", "text", own, config.threshold)

    spark.udf.register("segment_text", segment_text)
    register_measures(spark)


def register_measures(spark: SparkSession) -> None:
    """Registers bag_f1(hyp, ref) -> double, an aggregate of the tokens of rows; nulls are no tokens."""

    @F.pandas_udf("double")
    def bag_f1(hyp: pd.Series, ref: pd.Series) -> float:
        h, r = Counter(hyp.dropna()), Counter(ref.dropna())
        total = h.total() + r.total()
        return 2 * (h & r).total() / total if total else 0.0

    spark.udf.register("bag_f1", bag_f1)


class TextGrams:
    """text_grams(text, n): place (from 1) and gram of every gram of n symbols."""

    def eval(self, text: str, n: int):
        for i in range(len(text or "") - n + 1):
            yield i + 1, text[i : i + n]


class TextTokens:
    """text_tokens(text, threshold): tok_no, start and token of a text segmented by the freedom of its own symbols."""

    def eval(self, text: str, threshold: float):
        if not text:
            return
        nexts: dict[str, set[str]] = {}
        befores: dict[str, set[str]] = {}
        for a, b in zip(text, text[1:], strict=False):
            nexts.setdefault(a, set()).add(b)
            befores.setdefault(b, set()).add(a)
        grams = sorted(set(text))
        own = kernels.make_slice(grams, [len(nexts.get(g, ())) for g in grams], [len(befores.get(g, ())) for g in grams])
        at = 1
        for k, token in enumerate(kernels.tokens(text, {1: own}, "variance", threshold)):
            yield k + 1, at, token
            at += len(token)


def register_tables(spark: SparkSession) -> None:
    """Registers the table functions."""
    spark.udtf.register("text_grams", F.udtf(TextGrams, returnType="place int, gram string"))
    spark.udtf.register("text_tokens", F.udtf(TextTokens, returnType="tok_no int, start int, token string"))
