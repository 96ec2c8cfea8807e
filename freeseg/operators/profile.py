"""Profiles: one value for each gap of a statement, rank and direction, and the offshoots of it.

Gap g lies between symbols g and g + 1. Forward, its value is that of the gram which ends at symbol g; backward, that
of the gram which starts at symbol g + 1; there is no row where such a gram doesn't fit into the statement.

Here profiles are rows, and offshoots are windows over the gaps of a statement. `freeseg.functions.kernels` computes the
same in arrays.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import kernels
from . import compress, model

OFFSHOOTS = ("raw", "variance", "derivative", "peak")
BASES = ("tf", "p", "cp")
#: Digits to which offshoots are rounded before they are compared with a threshold, so that engines agree.
DIGITS = 9

KEY = ("lang", "stmt_id")


def gaps(statements: DataFrame, ranks, base: str = "tf", kind: str = "symbol") -> DataFrame:
    """lang, stmt_id, n, gap, dir, w: the window to look up at each gap. One linear scan of a text for each rank."""
    places = {n: kernels.place_of(base, n, kind) for n in ranks}
    found = F.array(*(F.struct(F.lit(n).alias("n"), F.lit(p.forward).alias("f"), F.lit(p.backward).alias("b"), F.regexp_extract_all("text", F.lit(rf"(?s)(?=(.{{{p.width}}}))."), F.lit(1)).alias("ws")) for n, p in places.items()))
    each = statements.where(F.length("text") >= 2).select(*KEY, F.length("text").alias("size"), F.inline(found))
    each = each.select(*KEY, "size", "n", "f", "b", F.posexplode("ws").alias("i", "w"))
    ways = F.array(*(F.struct((F.col("i") + F.col(d)).alias("gap"), F.lit(d).alias("dir")) for d in "fb"))
    return each.select(*KEY, "size", "n", "w", F.inline(ways)).where("gap >= 1 and gap < size").select(*KEY, "n", "gap", "dir", "w")


def values(grams: DataFrame, base: str, ranks, theta: float = 0.0, kind: str = "symbol", polarity: str = "high") -> DataFrame:
    """lang, n, w, dir, v: what a window gives to a gap, from gram counts up to the largest rank plus one (kind "symbol") or twice it ("gram"). Maxima are taken over the whole model. polarity "low": one minus the conditional probability."""
    return level_values(grams, base, ranks, (theta,), kind, polarity).drop("theta")


def level_values(grams: DataFrame, base: str, ranks, levels=compress.LEVELS, kind: str = "symbol", polarity: str = "high", only: DataFrame | None = None) -> DataFrame:
    """lang, n, w, dir, theta, v: the values at every compression level, each from one pass over vertices or rated edges. only: the windows (lang, n, w) that are wanted, each once; others are left out before the levels are told apart."""
    some = F.col("n").isin(list(ranks))
    own = grams.where(some)
    wanted = (lambda df: df.join(only, ["lang", "n", "w"], "left_semi")) if only is not None else (lambda df: df)
    each = lambda cond, v: F.inline(F.filter(F.array(*(F.struct(F.lit(float(t)).alias("theta"), F.when(cond(F.lit(float(t))), v).alias("v")) for t in levels)), lambda x: x["v"].isNotNull()))
    if base == "p":
        rated = model.probability(own).join(F.broadcast(model.vertex_max(own).select("lang", "n", "vmax")), ["lang", "n"]).withColumnRenamed("gram", "w")
        kept = wanted(rated).select("lang", "n", "w", each(lambda t: F.col("cnt") >= t * F.col("vmax"), F.col("p")))
        return kept.select("lang", "n", "w", F.explode(F.array(F.lit("f"), F.lit("b"))).alias("dir"), "theta", "v")
    edges = model.edges(grams).where(some) if kind == "symbol" else model.wide_edges(grams, ranks)
    if base == "tf":
        wide = wanted(compress.freedom_wide(own, edges, levels).withColumnRenamed("gram", "w"))
        counts = F.array(*(F.struct(F.lit(float(t)).alias("theta"), F.col(f"t{k}").cast("double").alias("v")) for k, t in enumerate(levels)))
        return wide.select("lang", "n", "w", "dir", F.inline(F.filter(counts, lambda x: x["v"] > 0)))
    w = F.when(F.col("dir") == "f", F.concat("gram", "nbr")).otherwise(F.concat("nbr", "gram"))
    rated = wanted(compress.rated(own, edges).withColumn("w", w))
    cp = F.col("cnt") / F.col("vcnt")
    return rated.select("lang", "n", "w", "dir", each(compress.holds, cp if polarity == "high" else 1 - cp))


def tops(value_rows: DataFrame) -> DataFrame:
    """lang, n, dir, top: the largest value of the model for each rank and direction."""
    return value_rows.groupBy("lang", "n", "dir").agg(F.max("v").alias("top"))


def looked_up(rows: DataFrame, value_rows: DataFrame, unseen: str = "zero", *more: str) -> DataFrame:
    """lang, stmt_id, more, n, gap, dir, v. Only values of windows that occur in the rows are joined; they are broadcast if they are few. An unseen window counts as 0 ("zero"), not at all ("null"), or as the next lower rank does in the rows ("backoff", then "zero")."""
    on = ["lang", "n", "dir", "w", *more]
    needed = value_rows.join(rows.select("lang", "n", "dir", "w").distinct(), ["lang", "n", "dir", "w"], "left_semi")
    got = rows.join(needed, on, "left").select(*KEY, *more, "n", "gap", "dir", F.col("v").cast("double").alias("v"))
    if unseen == "backoff":
        lower = Window.partitionBy(*KEY, *more, "gap", "dir").orderBy("n").rowsBetween(Window.unboundedPreceding, 0)
        got = got.withColumn("v", F.last("v", ignorenulls=True).over(lower))
    return got if unseen == "null" else got.withColumn("v", F.coalesce("v", F.lit(0.0)))


def profile(statements: DataFrame, grams: DataFrame, base: str, ranks, theta: float = 0.0, polarity: str = "high", kind: str = "symbol", unseen: str = "zero") -> DataFrame:
    """The profile of a base metric over gram counts; see `values` and `looked_up`."""
    ranks = list(ranks)
    from_ = list(range(1, max(ranks) + 1)) if unseen == "backoff" else ranks
    got = looked_up(gaps(statements, from_, base, kind), values(grams, base, from_, theta, kind, polarity), unseen)
    return got if from_ == ranks else got.where(F.col("n").isin(ranks))


def offshoot(profile: DataFrame, kind: str, pad: str = "edge", *more: str) -> DataFrame:
    """profile with the offshoot in place of v. more: further columns that tell profiles apart. pad "zero": nothing stands beyond the ends, as 0; "edge": the end's own value."""
    side = Window.partitionBy(*KEY, "n", "dir", *more)
    at = side.orderBy("gap")
    v = F.col("v")
    beyond = v if pad == "edge" else F.when(v.isNotNull(), F.lit(0.0))
    before, after = F.coalesce(F.lag("v").over(at), beyond), F.coalesce(F.lead("v").over(at), beyond)
    made: dict[str, Column] = {
        "raw": v,
        "variance": v - F.sum("v").over(side) / F.count("v").over(side),
        "derivative": F.when(F.col("dir") == "f", v - before).otherwise(v - after),
        "peak": (v - before) - (after - v),
    }
    return profile.withColumn("v", made[kind])


def scaled(profile: DataFrame, *more: str, top: DataFrame | None = None) -> DataFrame:
    """v over its largest value in the statement, for each rank and direction, or over the model's with `top` (see `tops`); 0 where that is not above 0. Rounded."""
    if top is None:
        most = F.max("v").over(Window.partitionBy(*KEY, "n", "dir", *more))
    else:
        profile, most = profile.join(F.broadcast(top), ["lang", "n", "dir"], "left"), F.col("top")
    out = profile.withColumn("v", F.round(F.when(most > 0, F.col("v") / most).when(F.col("v").isNotNull(), F.lit(0.0)), DIGITS))
    return out if top is None else out.drop("top")


def combined(profile: DataFrame, combine: str = "max", *more: str) -> DataFrame:
    """lang, stmt_id, gap, score: the mean over ranks, then the larger ("max") or the mean of the directions, or one of them ("forward", "backward")."""
    way = lambda d: F.round(F.avg(F.when(F.col("dir") == d, F.col("v"))), DIGITS)
    both = profile.groupBy(*KEY, *more, "gap").agg(way("f").alias("f"), way("b").alias("b"))
    score = {"max": F.greatest("f", "b"), "mean": F.round((F.coalesce("f", "b") + F.coalesce("b", "f")) / 2, DIGITS), "forward": F.col("f"), "backward": F.col("b")}[combine]
    return both.select(*KEY, *more, "gap", score.alias("score"))


def local_maxima(profile: DataFrame, threshold: float = 0.0, *more: str) -> DataFrame:
    """profile with is_break: v above its left neighbour, not below its right one, and above the threshold."""
    at = Window.partitionBy(*KEY, "n", "dir", *more).orderBy("gap")
    low = F.lit(float("-inf"))
    return profile.withColumn("is_break", (F.col("v") > F.coalesce(F.lag("v").over(at), low)) & (F.col("v") >= F.coalesce(F.lead("v").over(at), low)) & (F.col("v") > threshold))


def explain(spark, grams: DataFrame, lang: str, text: str, n: int = 1, base: str = "tf", theta: float = 0.0) -> DataFrame:
    """gap, symbol (before the gap), dir, and the value with its variance, derivative and peak, unscaled: the curves of one text."""
    st = spark.createDataFrame([(lang, "0", text)], "lang string, stmt_id string, text string")
    p = profile(st, grams, base, [n], theta)
    out = p
    for kind in OFFSHOOTS[1:]:
        out = out.join(offshoot(p, kind).select("gap", "dir", F.col("v").alias(kind)), ["gap", "dir"])
    return out.select("gap", F.substring(F.lit(text), F.col("gap"), F.lit(1)).alias("symbol"), "dir", F.col("v").alias("value"), *OFFSHOOTS[1:])
