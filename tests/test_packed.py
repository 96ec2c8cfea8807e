"""Grams in packed arrays against plain counts and the values of rows."""

import random
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from freeseg.functions import kernels
from freeseg.operators import baselines, model, packed, profile, tune

rng = random.Random(5)
LINES = [(lang, "".join(rng.choices("ab cé\U0001f600", k=k))) for lang in ("x", "y") for k in (1, 2, 7, 8, 9, 40, 200)] + [("x", ""), ("x", None), (None, "abc")]
MANY = [("z", "".join(chr(0x4E00 + k) for k in range(300)) + "ab"), ("z", "ab"), ("x", "一b")]


def plain(lines, n_max):
    return Counter((lang, n, t[i : i + n]) for lang, t in lines if lang and t for n in range(1, n_max + 1) for i in range(len(t) - n + 1))


@pytest.mark.parametrize("lines", [LINES, LINES + MANY])
@pytest.mark.parametrize("n_max", [5, 8])
def test_packed_counts(spark, lines, n_max):
    got = model.count_grams(spark.createDataFrame(lines, "lang string, line string").repartition(3), n_max)
    rows = got.collect()
    assert {(r.lang, r.n, r.gram): r.cnt for r in rows} == plain(lines, n_max) and len(rows) == len(plain(lines, n_max))


def test_a_long_gram_is_shuffled_in_its_longest_windows_only(spark):
    """A row of the shuffle is a part of a task's windows, not a gram."""
    lines = spark.createDataFrame([("x", "".join(rng.choices("abcdefgh ", k=20_000)))], "lang string, line string")
    plan = model.count_grams(lines, 8)._jdf.queryExecution().executedPlan().toString()
    assert "part" in plan.split("Exchange")[1] and plan.count("Exchange") == 1 and "HashAggregate" not in plan


def test_numbers_are_kept():
    for x in ([], [0], [5, 2**63, 2**64 - 1]):
        x = np.array(x, np.uint64)
        assert (packed.grown(packed.shrunk(x)) == x).all() and (packed.grown_keys(packed.shrunk_keys(x)) == x).all()


@pytest.fixture(scope="module")
def grams(spark):
    lines = [x for x in LINES if x[0] and x[1]]
    test = [("x", "ab cab éa"), ("y", "cab a"), ("w", "ab"), ("x", "qa")]
    return model.count_grams(spark.createDataFrame(lines, "lang string, line string"), 5).cache(), model.count_grams(spark.createDataFrame(test, "lang string, line string"), 5).drop("cnt").cache()


def test_values_are_those_of_rows(grams):
    counts, seen = grams
    ranks, levels = [1, 2, 4], [0.0, 0.05, 0.3]
    known = packed.alphabet(counts, seen, 5)
    pieces = [r.asDict() for r in packed.values(counts, seen, known, profile.BASES, ranks, levels).collect()]
    for base in profile.BASES:
        width = lambda n, base=base: kernels.place_of(base, n).width
        wanted = {(r.lang, r.n, r.gram) for r in seen.collect()}
        want = {(r.lang, r.n, float(r.theta), r.dir, r.w): r.v for r in profile.level_values(counts, base, ranks, levels).collect() if (r.lang, width(r.n), r.w) in wanted and r.v}
        found = {}
        for lang in "xyw":
            for n in ranks:
                for k, theta in enumerate(levels):
                    s = packed.read([x for x in pieces if (x["lang"], x["base"], x["n"]) == (lang, base, n)], known, base, n, k, theta)
                    for w in (w for of, m, w in wanted if (of, m) == (lang, width(n))):
                        at = s.lookup.of(kernels.gram_keys(kernels.points(w), width(n)))[0]
                        if at >= 0:
                            assert s.keys[at] == kernels.gram_keys(kernels.points(w), width(n))[0]
                            found |= {(lang, n, theta, d, w): v[at] for d, v in (("f", s.forward), ("b", s.backward)) if v[at]}
        assert found == want


def test_too_many_symbols_are_not_packed(spark, grams):
    more = spark.createDataFrame([("x", 1, chr(0x4E00 + k), 1) for k in range(300)], "lang string, n int, gram string, cnt long")
    assert packed.alphabet(grams[0], more, 8) is None and packed.alphabet(grams[0], more, 4) is not None


def test_the_grid_of_too_many_symbols_is_scored_by_rows(spark, monkeypatch):
    st = spark.createDataFrame([("x", "a", "ab ba"), ("x", "b", "b a")], "lang string, stmt_id string, text string")
    counts = model.count_grams(st.select("lang", F.col("text").alias("line")), 2).cache()
    search = lambda: sorted(map(tuple, tune.grid_search(st, counts, ["tf"], ["raw"], [(1,)], [0.0], [0.4]).collect()))
    want = search()
    monkeypatch.setattr(packed, "alphabet", lambda *_: None)
    assert search() == want and want


def test_texts_are_not_dealt_out_to_cells(spark):
    """All tasks read the same kept texts, so nothing is shuffled for them however many there are."""
    st = spark.createDataFrame([("x", "a", "ab ba")], "lang string, stmt_id string, text string")
    counts = model.count_grams(st.select("lang", F.col("text").alias("line")), 3)
    plan = tune.grid_search(st, counts, sets=((1,), (2,)), thresholds=(0.1, 0.4))._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan


def test_a_task_waits_for_its_values(spark, grams):
    """Texts that come before the values and the reference tokens are counted like others."""
    counts, seen = grams
    known, base = packed.alphabet(counts, seen, 5), "tf"
    pieces = [r.asDict() for r in packed.values(counts, seen, known, [base], [1], [0.0]).where("lang = 'x'").collect()]
    texts = ["ab cab éa", "qa"]
    words = Counter(r.token for r in baselines.reference_tokens(spark.createDataFrame([("x", str(k), t) for k, t in enumerate(texts)], "lang string, stmt_id string, text string")).collect())
    names = {"n": pa.int32(), "dir": pa.string(), "keys": pa.binary(), "data": pa.list_(pa.binary()), "token": pa.string(), "ref": pa.int64(), "text": pa.string()}
    rows = [{k: x[k] for k in tune.PIECE} for x in pieces] + [{"token": w, "ref": c} for w, c in words.items()] + [{"text": t} for t in texts]
    batch = lambda x: pa.RecordBatch.from_pylist([x], pa.schema(names))
    run = tune.task(known, base, 0, 0.0, [("raw", (1,))], [1], [0.1, 0.5], "max", len(pieces), len(words))
    got = [pa.Table.from_batches(run(map(batch, some))).to_pylist() for some in (rows, rows[::-1])]
    assert got[0] == got[1] and got[0][0]["ref"] == words.total() and got[0][0]["hyp"] > 0


def test_tokens_that_the_reference_has_once_are_flagged():
    """What is found of them is what counting gives."""
    texts = ["".join(rng.choices("ab  ", k=k)) for k in (1, 5, 40, 200)]
    tokens, limits = ["a", "ab", "b", "ba", "zz", "aab", "bbb"], 4
    t = kernels.texts_of(texts)
    q = np.random.default_rng(2).integers(0, limits + 1, len(t.points)).astype(np.uint8)
    counts, some, flags = np.zeros(7 * (limits + 1), np.int32), np.zeros(3 * (limits + 1), np.int32), np.zeros(4, np.uint32)
    totals = kernels.Bags(t, kernels.References(tokens)).add(q.copy(), limits, counts)
    assert (kernels.Bags(t, kernels.References(tokens, 3)).add(q.copy(), limits, some, flags) == totals).all()
    each = np.cumsum(counts.reshape(7, -1), axis=1)[:, :-1]
    assert (np.cumsum(some.reshape(3, -1), axis=1)[:, :-1] == each[:3]).all() and each[3:].any()
    assert [[bool(x >> k & 1) for k in range(limits)] for x in flags.tolist()] == (each[3:] > 0).tolist()
