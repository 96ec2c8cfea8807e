"""Toxicity by non-negative positive-unlabelled learning.

Only texts that are confirmed toxic count as labelled; all other texts are unlabelled. A linear model over hashed words
is fitted in numpy to the risk estimate  pi * R_p(+) + max(0, R_u(-) - pi * R_p(-)),  where pi is the class prior;
while the second part is below zero, the step goes the other way, which keeps the model from fitting it away.

The fit reads a bounded sample, MOST_POSITIVE and MOST_UNLABELLED rows, taken by a hash of the id. Scoring goes over
every whole text; the broadcast weights have a fixed size.

Nulls and odd input: null and empty texts have no words and get the score of the intercept. Null labels count as
unlabelled. Repeated label rows count once, toxic if any is. Without a toxic row every score is 0.
"""

from __future__ import annotations

import string
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .kernel import cut_batches, hash_strings, released, segment_sum, words_of

BUCKETS, MOST_POSITIVE, MOST_UNLABELLED = 1 << 18, 4000, 12_000
MARKS = string.punctuation + "…’‘“”«»¿¡–—"


class Model(NamedTuple):
    weights: np.ndarray  # by bucket
    bias: float


def word_buckets(distinct: pa.Array) -> np.ndarray:
    """A bucket for each word without the marks around it, -1 where nothing is left."""
    bare = [x.strip(MARKS) for x in distinct.to_pylist()]
    at = (hash_strings(pa.array(bare, pa.string())) % np.uint64(BUCKETS)).astype(np.int64)
    return np.where(np.array([bool(x) for x in bare], bool), at, -1)


def _distinct_pairs(rows: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    pairs = np.unique(rows * BUCKETS + values)
    return pairs // BUCKETS, pairs % BUCKETS


def features(docs: DataFrame, text: str) -> DataFrame:
    """docs with `buckets`, the distinct buckets of each text's words, in place of the text."""
    keep = [c for c in docs.columns if c != text]
    schema = T.StructType([docs.schema[c] for c in keep] + [T.StructField("buckets", T.ArrayType(T.IntegerType()))])

    @released
    def run(batches):
        for batch in cut_batches(batches, text):
            w = words_of(batch.column(text), "utf8")
            values = word_buckets(w.distinct)[w.codes]
            rows = np.repeat(np.arange(batch.num_rows), np.diff(w.offsets))
            rows, values = _distinct_pairs(rows[values >= 0], values[values >= 0])
            offsets = np.searchsorted(rows, np.arange(batch.num_rows + 1)).astype(np.int32)
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), pa.ListArray.from_arrays(pa.array(offsets), pa.array(values.astype(np.int32)))], [*keep, "buckets"])

    return docs.mapInArrow(run, schema)


def fit(positive: list[np.ndarray], unlabelled: list[np.ndarray], prior: float, steps: int = 300, rate: float = 0.05, decay: float = 2e-3, least_df: float = 0.01) -> Model:
    """Fits to bucket lists. Only buckets that occur in at least `least_df` of the positives, and in two of them, get weights."""
    if not positive:
        return Model(np.zeros(BUCKETS, np.float32), -np.inf)
    df_p = np.bincount(np.concatenate(positive), minlength=BUCKETS)
    df_u = np.bincount(np.concatenate([*unlabelled, np.zeros(0, np.int64)]).astype(np.int64), minlength=BUCKETS)
    used = np.flatnonzero(df_p >= max(2, least_df * len(positive)))
    # Inputs are scaled by how much likelier a bucket is in positives, so that telling words learn fast and others slowly.
    scale = np.log((df_p[used] + 0.5) / (len(positive) + 1)) - np.log((df_u[used] + 0.5) / (len(unlabelled) + 1))
    scale = np.maximum(scale, 0)
    place = np.full(BUCKETS, -1)
    place[used] = np.arange(len(used))

    def csr(lists):
        lists = [place[x] for x in lists]
        lists = [x[x >= 0] for x in lists]
        return np.concatenate([*lists, np.zeros(0, np.int64)]).astype(np.int64), np.concatenate([[0], np.cumsum([len(x) for x in lists])]).astype(np.int64)

    (ip, op), (iu, ou) = csr(positive), csr(unlabelled)
    w, b = np.zeros(len(used)), -1.0
    m, v = np.zeros(len(used) + 1), np.zeros(len(used) + 1)
    sig = lambda z: 1 / (1 + np.exp(-np.clip(z, -35, 35)))

    def back(index, offsets, g):
        return np.append(np.bincount(index, np.repeat(g, np.diff(offsets)) * scale[index], len(used)), g.sum())

    for t in range(1, steps + 1):
        zp = segment_sum((w * scale)[ip], op) + b
        zu = segment_sum((w * scale)[iu], ou) + b
        n_p, n_u = len(zp), max(len(zu), 1)
        negative = np.logaddexp(0, zu).sum() / n_u - prior * np.logaddexp(0, zp).sum() / n_p
        grad_negative = back(iu, ou, sig(zu) / n_u) - back(ip, op, prior * sig(zp) / n_p)
        if negative >= 0:
            grad = back(ip, op, -prior * sig(-zp) / n_p) + grad_negative
        else:
            grad = -grad_negative
        grad[:-1] += decay * w
        m, v = 0.9 * m + 0.1 * grad, 0.999 * v + 0.001 * grad**2
        step = rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-9)
        w, b = w - step[:-1], b - step[-1]
    weights = np.zeros(BUCKETS, np.float32)
    weights[used] = w * scale
    return Model(weights, float(b))


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text: str = "text", label: str = "toxic", most_positive: int = MOST_POSITIVE, most_unlabelled: int = MOST_UNLABELLED) -> Model:
    """Learns from docs and the labels of their ids. Of the labelled rows only the toxic ones are positives; the share of toxic rows among them is the class prior."""
    ids = docs.where(F.col(id_col).isNotNull()).select(F.col(id_col).alias("id")).distinct()
    known = labels.where(F.col(label).isNotNull()).groupBy(F.col(id_col).alias("id")).agg(F.max(label).alias("y"))
    known = ids.join(known, "id")
    counts = known.agg(F.count("*").alias("n"), F.coalesce(F.sum(F.col("y").cast("long")), F.lit(0)).alias("p")).first()
    if not counts.p:
        return fit([], [], 0.0)
    order = F.xxhash64(F.col("id"))
    positive = known.where("y = 1").orderBy(order, "id").limit(most_positive).select("id", F.lit(True).alias("p"))
    unlabelled = ids.orderBy(order, "id").limit(most_unlabelled).select("id", F.lit(False).alias("p"))
    # most_positive + most_unlabelled ids at most.
    chosen = F.broadcast(positive.unionByName(unlabelled).groupBy("id").agg(F.bool_or("p").alias("p"), F.bool_or(~F.col("p")).alias("u")))
    rows = docs.select(F.col(id_col).alias("id"), F.col(text).alias("t")).join(chosen, "id")
    got = features(rows.select("p", "u", "t"), "t").toArrow()
    lists = got.column("buckets").combine_chunks() if got.num_rows else pa.array([], pa.list_(pa.int32()))
    lists = lists.chunk(0) if isinstance(lists, pa.ChunkedArray) else lists
    flat, offsets = lists.flatten().to_numpy().astype(np.int64), lists.offsets.to_numpy()
    each = [flat[a:b] for a, b in zip(offsets[:-1], offsets[1:], strict=True)]
    p, u = got.column("p").to_pylist(), got.column("u").to_pylist()
    # Sorted, so that the sums don't depend on the order in which rows arrive.
    by = lambda flags: sorted((x for x, f in zip(each, flags, strict=True) if f), key=lambda x: x.tobytes())
    return fit(by(p), by(u), min(0.95, counts.p / counts.n))


def score_texts(texts: pa.Array, model: Model) -> np.ndarray:
    w = words_of(texts, "utf8")
    at = word_buckets(w.distinct)
    values = at[w.codes]
    used = np.where(values >= 0, model.weights[values] != 0, False)
    rows, values = _distinct_pairs(np.repeat(np.arange(len(texts)), np.diff(w.offsets))[used], values[used])
    z = np.bincount(rows, model.weights[values], len(texts)) + model.bias
    return np.where(np.isneginf(z), 0.0, 1 / (1 + np.exp(-np.clip(z, -700, 700))))


def predict(docs: DataFrame, model: Model, text: str = "text") -> DataFrame:
    """docs with `score`, 0 to 1, and `predicted`, 1 where the score is 0.5 or more; columns of those names are replaced."""
    held = docs.sparkSession.sparkContext.broadcast(model)
    keep = [c for c in docs.columns if c not in ("score", "predicted")]
    schema = T.StructType([docs.schema[c] for c in keep] + [T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType())])

    @released
    def run(batches):
        for batch in cut_batches(batches, text):
            score = score_texts(batch.column(text), held.value)
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), pa.array(score), pa.array((score >= 0.5).astype(np.int32))], [*keep, "score", "predicted"])

    return docs.select(*keep).mapInArrow(run, schema)
