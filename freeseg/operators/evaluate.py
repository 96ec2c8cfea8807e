"""Measures: F1 on bags of tokens, precision of lexicon discovery, break and span F1, the tokens that differ, and costs."""

from __future__ import annotations

import time
import uuid

from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F

from . import profile

KEY = profile.KEY
DIGITS = 6


def solid(tokens: DataFrame) -> DataFrame:
    """The tokens that aren't blank."""
    return tokens.where(F.trim("token") != "")


def ratio(a: Column, b: Column) -> Column:
    """a / b rounded, 0 where b is 0."""
    return F.round(F.when(b > 0, a / b).otherwise(F.lit(0.0)), DIGITS)


def bag_match(hyp: DataFrame, ref: DataFrame, *by: str) -> DataFrame:
    """by, matched, hyp, ref: tokens found in both bags, each as often as in the bag that has it less often, and the sizes of the bags. One partial aggregation of each side, then a full outer join of counts."""
    count = lambda df, name: df.groupBy(*by, "token").agg(F.count("*").alias(name))
    both = count(hyp, "h").join(count(ref, "r"), [*by, "token"], "full_outer")
    h, r = F.coalesce("h", F.lit(0)), F.coalesce("r", F.lit(0))
    return both.groupBy(*by).agg(F.sum(F.least(h, r)).alias("matched"), F.sum(h).alias("hyp"), F.sum(r).alias("ref"))


def with_f1(matches: DataFrame) -> DataFrame:
    """Precision, recall and F1 beside the counts."""
    m, h, r = F.col("matched"), F.col("hyp"), F.col("ref")
    return matches.withColumns({"precision": ratio(m, h), "recall": ratio(m, r), "f1": ratio(2 * m, h + r)})


def f1(hyp: DataFrame, ref: DataFrame, *by: str, pool: str = "corpus") -> DataFrame:
    """F1 of the bags of each group, by default of each language. pool "statement": the mean of the statements' F1."""
    by = by or ("lang",)
    if pool == "corpus":
        return with_f1(bag_match(hyp, ref, *by))
    each = with_f1(bag_match(hyp, ref, *dict.fromkeys([*by, *KEY])))
    return each.groupBy(*by).agg(F.round(F.avg("f1"), DIGITS).alias("f1"))


def lexicon_precision(tokens: DataFrame, lexicon: DataFrame, *by: str, distinct: bool = False) -> DataFrame:
    """by, known, total, precision: the share of tokens that the lexicon has. distinct: of different tokens, not occurrences."""
    by = by or ("lang",)
    each = tokens.select(*by, "token").distinct() if distinct else tokens
    counts = each.groupBy(*dict.fromkeys([*by, "lang"]), "token").agg(F.count("*").alias("c"))
    words = lexicon.select("lang", F.col("word").alias("token"), F.lit(True).alias("known")).distinct()
    rated = counts.join(words, ["lang", "token"], "left")
    out = rated.groupBy(*by).agg(F.sum(F.when(F.col("known"), F.col("c")).otherwise(0)).alias("known"), F.sum("c").alias("total"))
    return out.withColumn("precision", ratio(F.col("known"), F.col("total")))


def corrected(lexicon: DataFrame, ref: DataFrame) -> DataFrame:
    """The lexicon with the reference tokens that it lacks."""
    extra = ref.select("lang", F.col("token").alias("word"), F.lit(1).cast("long").alias("freq"))
    return lexicon.select("lang", "word", "freq").unionByName(extra).groupBy("lang", "word").agg(F.max("freq").alias("freq"))


def boundary_f1(hyp: DataFrame, ref: DataFrame, *by: str) -> DataFrame:
    """F1 on breaks by place. hyp and ref: by, lang, stmt_id, gap."""
    by = by or ("lang",)
    on = list(dict.fromkeys([*by, *KEY, "gap"]))
    both = hyp.select(*on).distinct().withColumn("h", F.lit(1)).join(ref.select(*on).distinct().withColumn("r", F.lit(1)), on, "full_outer")
    h, r = F.coalesce("h", F.lit(0)), F.coalesce("r", F.lit(0))
    return with_f1(both.groupBy(*by).agg(F.sum(F.least(h, r)).alias("matched"), F.sum(h).alias("hyp"), F.sum(r).alias("ref")))


def span_f1(hyp: DataFrame, ref: DataFrame, *by: str) -> DataFrame:
    """F1 on whole tokens by place. hyp and ref: by, lang, stmt_id, start, len."""
    by = by or ("lang",)
    on = list(dict.fromkeys([*by, *KEY, "start", "len"]))
    both = hyp.select(*on).distinct().withColumn("h", F.lit(1)).join(ref.select(*on).distinct().withColumn("r", F.lit(1)), on, "full_outer")
    h, r = F.coalesce("h", F.lit(0)), F.coalesce("r", F.lit(0))
    return with_f1(both.groupBy(*by).agg(F.sum(F.least(h, r)).alias("matched"), F.sum(h).alias("hyp"), F.sum(r).alias("ref")))


def errors(hyp: DataFrame, ref: DataFrame) -> DataFrame:
    """lang, token, missed, invented: how many more of a token the reference has, and how many more the hypothesis has."""
    count = lambda df, name: df.groupBy("lang", "token").agg(F.count("*").alias(name))
    both = count(hyp, "h").join(count(ref, "r"), ["lang", "token"], "full_outer")
    h, r = F.coalesce("h", F.lit(0)), F.coalesce("r", F.lit(0))
    return both.select("lang", "token", F.greatest(r - h, F.lit(0)).alias("missed"), F.greatest(h - r, F.lit(0)).alias("invented")).where("missed > 0 or invented > 0")


def model_cost(grams: DataFrame) -> DataFrame:
    """lang, n, grams, bytes: how much a model holds, as UTF-8 and a count of 8 bytes for each gram."""
    return grams.groupBy("lang", "n").agg(F.count("*").alias("grams"), F.sum(F.octet_length("gram").cast("long") + 8).alias("bytes"))


def token_spans(tokens: DataFrame) -> DataFrame:
    """lang, stmt_id, start (from 1), len of tokens (lang, stmt_id, tok_no, token) that, blank ones too, make up the whole statement."""
    at = Window.partitionBy(*KEY).orderBy("tok_no")
    n = F.length("token")
    return tokens.select(*KEY, (F.sum(n).over(at) - n + 1).cast("int").alias("start"), n.alias("len"), "token")


def measured(df: DataFrame, write) -> dict:
    """The rows of df, and the seconds that write(df) takes; df is observed while it is written, so nothing runs twice."""
    seen = Observation(f"measured-{uuid.uuid4().hex}")
    began = time.time()
    write(df.observe(seen, F.count(F.lit(1)).alias("rows")))
    return {"seconds": time.time() - began, **seen.get}
