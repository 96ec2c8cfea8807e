"""Segmenting whole corpora and streams: a map over texts with a broadcast slice of the model, without a shuffle."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import kernels
from . import profile, segment

#: Windows of a model slice that may be broadcast, of some 24 bytes each. More are looked up by a join.
MOST_WINDOWS = 1_000_000
#: Symbols that are handled in arrays at once; a longer text is alone.
BATCH_SYMBOLS = 1_000_000

Model = dict[str, dict[int, kernels.Slice]]


def sliced(values: DataFrame, base: str, kind: str = "symbol", levels=(None,), most: int = MOST_WINDOWS) -> Model | None:
    """Slices by language and rank from values (lang, n, w, dir, v, and theta if there are levels), on the driver behind a check of their size; None if they are more than `most`."""
    wide = len(levels) > 1
    at = lambda d, t: (F.col("dir") == d) & (F.col("theta") == t) if wide else F.col("dir") == d
    cols = [F.coalesce(F.max(F.when(at(d, t), F.col("v"))), F.lit(0.0)).alias(f"{d}{k}") for k, t in enumerate(levels) for d in "fb"]
    rows = values.groupBy("lang", "n", "w").agg(*cols).limit(most + 1).toArrow()
    if rows.num_rows > most:
        return None
    out: Model = {}
    for part in rows.select(["lang", "n"]).group_by(["lang", "n"]).aggregate([]).to_pylist():
        some = rows.filter(pc.and_(pc.equal(rows["lang"], part["lang"]), pc.equal(rows["n"], part["n"])))
        f, b = (np.array([some[f"{d}{k}"].to_numpy() for k in range(len(levels))]) for d in "fb")
        s = kernels.make_slice(some["w"].to_pylist(), f if wide else f[0], b if wide else b[0], kernels.place_of(base, part["n"], kind))
        out.setdefault(part["lang"], {})[part["n"]] = s
    return out


def slices(grams: DataFrame, config: segment.Config = segment.Config(), most: int = MOST_WINDOWS) -> Model | None:
    """What a configuration looks up in a trained model, or None if that is too much to broadcast."""
    return sliced(profile.values(grams, config.base, config.read, config.theta, config.kind, config.polarity), config.base, config.kind, most=most)


def scorer(held, config: segment.Config) -> Callable[[str, kernels.Texts], np.ndarray]:
    """Scores of texts of a language by a broadcast model. A language without a model has no breaks."""

    backoff = config.ranks if config.unseen == "backoff" else ()
    local = config.threshold if config.rule == "local_max" else None

    def of(lang: str, t: kernels.Texts) -> np.ndarray:
        own = held.value.get(lang) or {}
        some = {n: own[n] for n in config.read if n in own}
        if backoff and some:
            some |= {n: kernels.make_slice([], [], [], kernels.place_of(config.base, n, config.kind)) for n in config.read if n not in own}
        return kernels.scores(t, some, config.offshoot, config.combine, config.scale, local, backoff)

    return of


def pieces(batch: pa.RecordBatch, lang: str, text: str):
    """Rows of a batch by language, up to about BATCH_SYMBOLS at once: language, row numbers and texts that aren't empty."""
    langs = batch.column(lang).cast(pa.string()).fill_null("").to_pylist()
    by: dict[str, list[int]] = {}
    texts = batch.column(text).to_pylist()
    for i, (g, t) in enumerate(zip(langs, texts, strict=True)):
        if t:
            by.setdefault(g, []).append(i)
    for g, rows in by.items():
        own, size = [], 0
        for i in (*rows, None):
            if own and (i is None or size + len(texts[i]) > BATCH_SYMBOLS):
                yield g, own, [texts[k] for k in own]
                own, size = [], 0
            if i is not None:
                own.append(i)
                size += len(texts[i])


def token_rows(statements: DataFrame, model: Model, config: segment.Config = segment.Config(), score=None, keys=profile.KEY, lang: str = "lang", text: str = "text") -> DataFrame:
    """keys, tok_no, start, len, token of statements, by a broadcast model. score: a function of language and texts in place of the configuration's, with breaks where it gives more than 0."""
    own = score or scorer(statements.sparkSession.sparkContext.broadcast(model), config)
    limit = 0.0 if score else config.threshold
    schema = T.StructType([statements.schema[c] for c in keys] + [T.StructField(c, T.IntegerType(), False) for c in ("tok_no", "start", "len")] + [T.StructField("token", T.StringType())])

    def run(batches):
        for batch in batches:
            for g, rows, texts in pieces(batch, lang, text):
                t = kernels.texts_of(texts)
                a, b = kernels.spans(t, own(g, t) > limit)
                of = np.searchsorted(t.first, a, side="right") - 1
                no = np.arange(len(a)) - np.searchsorted(a, t.first)[of] + 1
                at = pa.array(np.array(rows, np.int64)[of])
                i32 = lambda x: pa.array(x.astype(np.int32))
                yield pa.RecordBatch.from_arrays([*(batch.column(c).take(at) for c in keys), i32(no), i32(a - t.first[of] + 1), i32(b - a), kernels.token_array(texts, t, a)], schema.fieldNames())

    return statements.select(*dict.fromkeys([*keys, lang, text])).mapInArrow(run, schema)


def segment_texts(texts: DataFrame, model: Model, config: segment.Config = segment.Config(), lang: str = "lang", text: str = "text", out: str = "tokens") -> DataFrame:
    """texts with their tokens as an array, null for a null text. A language without a model gives one token. Works on streams."""
    own = scorer(texts.sparkSession.sparkContext.broadcast(model), config)
    keep = [c for c in texts.columns if c != out]
    schema = T.StructType([texts.schema[c] for c in keep] + [T.StructField(out, T.ArrayType(T.StringType()))])

    def run(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), tokens_of(batch, lang, text, own, config.threshold)], [*keep, out])

    return texts.select(*keep).mapInArrow(run, schema)


def tokens_of(batch: pa.RecordBatch, lang: str, text: str, own, threshold: float) -> pa.Array:
    """The tokens of each row of a batch: null for a null text, none for an empty one."""
    parts, order, sizes = [], [], []
    for g, rows, texts in pieces(batch, lang, text):
        t = kernels.texts_of(texts)
        a, _ = kernels.spans(t, own(g, t) > threshold)
        parts.append(kernels.token_array(texts, t, a))
        order += rows
        sizes.append(np.bincount(np.searchsorted(t.first, a, side="right") - 1, minlength=len(texts)))
    flat = pa.concat_arrays(parts) if parts else pa.array([], pa.string())
    offsets = np.concatenate([[0], *(np.cumsum(s) + sum(x.sum() for x in sizes[:k]) for k, s in enumerate(sizes))]).astype(np.int32)
    lists = pa.concat_arrays([pa.ListArray.from_arrays(pa.array(offsets), flat), pa.array([[]], pa.list_(pa.string()))])
    place = np.full(batch.num_rows, len(lists) - 1)
    place[order] = np.arange(len(order))
    null = batch.column(text).is_null().to_numpy(zero_copy_only=False)
    return lists.take(pa.array(place, mask=null))


def swept(texts: DataFrame, model: Model, config: segment.Config = segment.Config(), lang: str = "lang", text: str = "text", *keys: str) -> DataFrame:
    """keys, lang, start (from 1), len, token, low, high: every span that is a token for some threshold, with the thresholds for which it is."""
    own = scorer(texts.sparkSession.sparkContext.broadcast(model), config)
    names = [*dict.fromkeys([*keys, lang])]
    schema = T.StructType([texts.schema[c] for c in names] + [T.StructField("start", T.IntegerType()), T.StructField("len", T.IntegerType()), T.StructField("token", T.StringType()), T.StructField("low", T.DoubleType()), T.StructField("high", T.DoubleType())])

    def run(batches):
        for batch in batches:
            for g, numbers, some in pieces(batch, lang, text):
                t, rows, at = kernels.texts_of(some), [], []
                score = own(g, t)
                for i, x, first in zip(numbers, some, t.first.tolist(), strict=True):
                    for a, size, low, high in kernels.sweep(score[first : first + len(x) - 1]):
                        rows.append((a + 1, size, x[a : a + size], low, high))
                        at.append(i)
                cols = list(zip(*rows, strict=True)) or [[]] * 5
                types = [pa.int32(), pa.int32(), pa.string(), pa.float64(), pa.float64()]
                yield pa.RecordBatch.from_arrays([*(batch.column(c).take(pa.array(at, pa.int64())) for c in names), *(pa.array(c, t) for c, t in zip(cols, types, strict=True))], schema.fieldNames())

    return texts.select(*dict.fromkeys([*names, text])).mapInArrow(run, schema)
