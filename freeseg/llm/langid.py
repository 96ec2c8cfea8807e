"""Language identification by multinomial naive Bayes over hashed character n-grams.

Counting is one pass over the labelled texts: each task adds up its n-gram counts by language, and only sums are
shuffled. The model is a matrix of languages by buckets, whose size does not depend on the data, and is broadcast.

Nulls and odd input: a null, empty or letterless text gets `und` and score 0. Rows with a null language or null text
are not learned from. Repeated rows count as often as they occur. Ties go to the language that sorts first. With
nothing to learn from, every text gets `und`. Columns besides those named are passed through by `predict`.
"""

from __future__ import annotations

from collections import defaultdict
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .kernel import cut_batches, released, segment_sum, words_of

ORDERS, BUCKETS, ALPHA = (1, 2, 3, 4), 1 << 16, 0.5
#: Bytes of text whose n-grams are held at once.
SMALL = 2 << 20


class Model(NamedTuple):
    languages: list[str]
    log_prior: np.ndarray
    log_prob: np.ndarray  # buckets x languages
    orders: tuple[int, ...]


def word_grams(distinct: pa.Array, orders=ORDERS, buckets: int = BUCKETS) -> tuple[np.ndarray, np.ndarray]:
    """The n-grams of words between blanks: for each, the word's place in `distinct` and the n-gram's bucket."""
    text = " " + " ".join(distinct.to_pylist()) + " "
    points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    blank = points == 32
    word = np.cumsum(blank) - 1
    owners, found = [], []
    for n in orders:
        size = len(points) - n + 1
        if size <= 0:
            continue
        h, ok = np.full(size, n, np.uint64), np.ones(size, bool)
        for j in range(n):
            h = (h * np.uint64(0x100000001B3)) ^ points[j : j + size]
            if n == 1 or 0 < j < n - 1:
                ok &= ~blank[j : j + size]
        if n == 2:
            ok &= ~(blank[:size] & blank[1 : size + 1])
        h = h[ok]
        h = (h ^ (h >> np.uint64(29))) * np.uint64(0x9E3779B97F4A7C15)
        owners.append(word[:size][ok])
        found.append((h >> np.uint64(40)) % np.uint64(buckets))
    if not owners:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.concatenate(owners), np.concatenate(found).astype(np.int64)


def train(docs: DataFrame, text: str = "text", lang: str = "lang", orders=ORDERS, buckets: int = BUCKETS, alpha: float = ALPHA) -> Model:
    """Learns from every row that has a text and a language."""

    @released
    def count(batches):
        total: dict[str, np.ndarray] = defaultdict(lambda: np.zeros(buckets, np.int64))
        docs_of: dict[str, int] = defaultdict(int)
        for batch in cut_batches(batches, "t", SMALL):
            w = words_of(batch.column("t"), "utf8")
            owner, bucket = word_grams(w.distinct, orders, buckets)
            names = batch.column("l").dictionary_encode()
            row_lang = np.repeat(names.indices.to_numpy(zero_copy_only=False), np.diff(w.offsets))
            for k, name in enumerate(names.dictionary.to_pylist()):
                per_word = np.bincount(w.codes[row_lang == k], minlength=len(w.distinct))
                total[name] += np.bincount(bucket, per_word[owner], buckets).astype(np.int64)
                docs_of[name] += int(np.sum(names.indices.to_numpy(zero_copy_only=False) == k))
        for name, counts in total.items():
            at = np.flatnonzero(counts)
            size = len(at) + 1
            yield pa.RecordBatch.from_arrays(
                [pa.array([name] * size), pa.array(np.append(at, -1)), pa.array(np.append(counts[at], docs_of[name]))], ["l", "b", "c"]
            )

    rows = docs.where(F.col(text).isNotNull() & F.col(lang).isNotNull()).select(F.col(text).alias("t"), F.col(lang).cast("string").alias("l"))
    # Languages x buckets rows at most come to the driver: the model itself.
    found = rows.mapInArrow(count, "l string, b long, c long").groupBy("l", "b").agg(F.sum("c").alias("c")).toArrow()
    names = sorted(set(found.column("l").to_pylist()))
    place = {x: k for k, x in enumerate(names)}
    k = np.array([place[x] for x in found.column("l").to_pylist()], np.int64)
    b, c = found.column("b").to_numpy(), found.column("c").to_numpy()
    counts, n_docs = np.zeros((buckets, len(names))), np.zeros(len(names))
    counts[b[b >= 0], k[b >= 0]] = c[b >= 0]
    n_docs[k[b < 0]] = c[b < 0]
    total = counts.sum(0, keepdims=True)
    return Model(names, np.log(np.maximum(n_docs, 1) / max(n_docs.sum(), 1)), np.log(counts + alpha) - np.log(total + alpha * buckets), tuple(orders))


def score_texts(texts: pa.Array, model: Model) -> tuple[np.ndarray, np.ndarray]:
    """For each text the place of its language in model.languages, -1 for none, and that language's posterior probability."""
    letters = pc.match_substring_regex(texts.fill_null(""), r"\p{L}").to_numpy(zero_copy_only=False)
    if not model.languages:
        return np.full(len(texts), -1), np.zeros(len(texts))
    w = words_of(texts, "utf8")
    owner, bucket = word_grams(w.distinct, model.orders, len(model.log_prob))
    size = len(w.distinct)
    per_word = np.stack([np.bincount(owner, model.log_prob[bucket, k], size) for k in range(len(model.languages))], 1)
    logs = segment_sum(per_word[w.codes], w.offsets) + model.log_prior
    best = logs.argmax(1)
    posterior = 1 / np.exp(logs - logs.max(1, keepdims=True)).sum(1)
    return np.where(letters, best, -1), np.where(letters, posterior, 0.0)


def predict(docs: DataFrame, model: Model, text: str = "text", lang_col: str = "lang_pred", score_col: str = "score") -> DataFrame:
    """docs with the predicted language and its posterior probability; columns of those names are replaced."""
    held = docs.sparkSession.sparkContext.broadcast(model)
    keep = [c for c in docs.columns if c not in (lang_col, score_col)]
    schema = T.StructType([docs.schema[c] for c in keep] + [T.StructField(lang_col, T.StringType()), T.StructField(score_col, T.DoubleType())])

    @released
    def run(batches):
        m = held.value
        names = pa.array([*m.languages, "und"])
        for batch in cut_batches(batches, text, SMALL):
            best, score = score_texts(batch.column(text), m)
            yield pa.RecordBatch.from_arrays(
                [*(batch.column(c) for c in keep), names.take(pa.array(np.where(best < 0, len(m.languages), best))), pa.array(score)], [*keep, lang_col, score_col]
            )

    return docs.select(*keep).mapInArrow(run, schema)


def keep_identified(docs: DataFrame, model: Model, text: str = "text", least: float = 0.5) -> DataFrame:
    """The rows whose language is known with a posterior probability of `least` or more, columns as they were."""
    pred, score = "__lang_pred", "__lang_score"
    return predict(docs, model, text, pred, score).where((F.col(pred) != "und") & (F.col(score) >= least)).select(*docs.columns)
