"""From scores at gaps to tokens. A gap whose score exceeds the threshold is a break; tokens lie between breaks and, put together, are the statement.

`run` takes the array engine as long as the model's values for the configuration are few enough to be broadcast, and
joins them to rows otherwise. Both give the same tokens.
"""

from __future__ import annotations

from typing import NamedTuple

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import profile

KEY = profile.KEY


class Config(NamedTuple):
    base: str = "tf"  # tf, p, cp
    offshoot: str = "variance"  # raw, variance, derivative, peak
    ranks: tuple[int, ...] = (1,)
    theta: float = 0.0001
    threshold: float = 0.4
    combine: str = "max"  # max, mean, forward, backward
    kind: str = "symbol"  # neighbours are symbols, or grams ("gram")
    rule: str = "threshold"  # or "local_max": local maxima above the threshold in either direction
    scale: str = "sequence"  # by the statement's largest value, the model's ("model"), or not at all ("none")
    pad: str = "edge"  # or "zero"
    unseen: str = "zero"  # or "null", "backoff"
    polarity: str = "high"  # or "low", for cp

    @property
    def in_arrays(self) -> bool:
        """Whether the array engine knows all of it. A value of 0 is an unseen window's there, which that of polarity "low" need not be."""
        return self.pad == "edge" and (self.unseen == "zero" or self.unseen == "backoff" and self.polarity == "high")

    @property
    def read(self) -> tuple[int, ...]:
        """The ranks that are looked up."""
        return tuple(range(1, max(self.ranks) + 1)) if self.unseen == "backoff" else self.ranks


def breaks(scores: DataFrame, threshold: float) -> DataFrame:
    """lang, stmt_id, gap of the gaps whose score exceeds the threshold."""
    return scores.where(F.col("score") > threshold).select(*KEY, "gap")


def tokens(statements: DataFrame, cuts: DataFrame, keep_space: bool = True, *more: str) -> DataFrame:
    """lang, stmt_id, tok_no (from 1), start (from 1), len, token. more: columns of cuts that tell segmentations apart, which statements has too. Linear in the length of a text: its symbols are an array, cut before rows are made."""
    on = [*KEY, *more]
    lists = cuts.groupBy(*on).agg(F.array_sort(F.collect_set("gap")).alias("cuts"))
    with_cuts = statements.join(lists, on, "left").withColumn("cuts", F.coalesce("cuts", F.array().cast("array<int>")))
    spans = F.arrays_zip(F.concat(F.array(F.lit(0)), "cuts").alias("a"), F.concat("cuts", F.array(F.length("text"))).alias("b"))
    # The symbols stand in an array of one element, so they are made once and not for every span.
    made = F.transform(F.array(F.split("text", "")), lambda s: F.transform(spans, lambda x: F.struct((x["a"] + 1).alias("start"), (x["b"] - x["a"]).alias("len"), F.array_join(F.slice(s, x["a"] + 1, x["b"] - x["a"]), "").alias("token"))))[0]
    each = with_cuts.where(F.length("text") > 0).select(*on, F.posexplode(made).alias("no", "x"))
    out = each.select(*on, (F.col("no") + 1).alias("tok_no"), "x.*")
    return out if keep_space else out.where(F.trim("token") != "")


def joined(token_rows: DataFrame) -> DataFrame:
    """lang, stmt_id, text: the tokens put together."""
    row = F.array_sort(F.collect_list(F.struct("tok_no", "token")))
    return token_rows.groupBy(*KEY).agg(F.array_join(F.transform(row, lambda x: x["token"]), "").alias("text"))


def base_profile(statements: DataFrame, grams: DataFrame, base: str, ranks, theta: float = 0.0, polarity: str = "high", kind: str = "symbol", unseen: str = "zero") -> DataFrame:
    """The profile of a base metric, "tf", "p" or "cp", from gram counts up to the largest rank plus one, or twice it for neighbours that are grams."""
    return profile.profile(statements, grams, base, ranks, theta, polarity, kind, unseen)


def offshoots(statements: DataFrame, grams: DataFrame, c: Config) -> DataFrame:
    """The scaled offshoot of a configuration at each gap, rank and direction."""
    made = profile.offshoot(base_profile(statements, grams, c.base, c.ranks, c.theta, c.polarity, c.kind, c.unseen), c.offshoot, c.pad)
    if c.scale == "none":
        return made.withColumn("v", F.round("v", profile.DIGITS))
    return profile.scaled(made, top=profile.tops(profile.values(grams, c.base, c.ranks, c.theta, c.kind, c.polarity)) if c.scale == "model" else None)


def scores(statements: DataFrame, grams: DataFrame, config: Config = Config()) -> DataFrame:
    """Scores at the gaps of statements under a configuration."""
    return profile.combined(offshoots(statements, grams, config), config.combine)


def break_rows(statements: DataFrame, grams: DataFrame, config: Config = Config()) -> DataFrame:
    """The breaks of a configuration by the row engine."""
    if config.rule == "threshold":
        return breaks(scores(statements, grams, config), config.threshold)
    mean = offshoots(statements, grams, config).groupBy(*KEY, "gap", "dir").agg(F.round(F.avg("v"), profile.DIGITS).alias("v")).withColumn("n", F.lit(0))
    some = {"forward": "dir = 'f'", "backward": "dir = 'b'"}.get(config.combine, "true")
    return profile.local_maxima(mean.where(some), config.threshold).where("is_break").select(*KEY, "gap").distinct()


def run(statements: DataFrame, grams: DataFrame, config: Config = Config(), keep_space: bool = True, engine: str = "any", held=None) -> DataFrame:
    """The tokens of statements under a configuration: lang, stmt_id, tok_no, start, len, token. engine: "arrays", "rows", or "any" that suits. held: what `apply.slices` gives, where it is at hand."""
    from . import apply

    if engine != "rows" and config.in_arrays:
        held = apply.slices(grams, config) if held is None else held
        if held is not None:
            out = apply.token_rows(statements, held, config)
            return out if keep_space else out.where(F.trim("token") != "")
    return tokens(statements, break_rows(statements, grams, config), keep_space)


def run_all(statements: DataFrame, grams: DataFrame, configs: dict[str, Config]) -> dict[str, DataFrame]:
    """The tokens under each of some configurations. Those that look up the same values share one slice of the model."""
    from . import apply

    held, out = {}, {}
    for name, c in configs.items():
        key = (c.base, c.read, c.theta, c.kind, c.polarity)
        if c.in_arrays and key not in held:
            held[key] = apply.slices(grams, c)
        out[name] = run(statements, grams, c, engine="any" if held.get(key) else "rows", held=held.get(key))
    return out
