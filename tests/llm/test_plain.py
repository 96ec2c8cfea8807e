"""Lines, decontamination, toxicity and the pipeline against plain loops over the smallest tables and over random texts."""

import random

import corpus_pipeline
import numpy as np
import pyarrow as pa
import pytest

from freeseg.llm import decontam, line_dedup, pieces, queries, toxicity
from freeseg.sources.store import kept

from . import plain
from .helpers import documents


def given(spark, sf, extra=()):
    """The smallest documents and some more as id -> text."""
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    return docs | {10_000 + k: t for k, t in enumerate(extra)}


def made(spark, docs):
    return spark.createDataFrame(sorted(docs.items()), "doc_id long, text string")


def templates(rng, n):
    vocabulary = [f"{a}{b}" for a in "abcdefgh" for b in "uvwxyz"]
    base = [[rng.choice(vocabulary) for _ in range(rng.randint(3, 14))] for _ in range(6)]
    out = []
    for _ in range(n):
        lines = []
        for _ in range(rng.randint(1, 6)):
            line = list(rng.choice(base))
            for _ in range(rng.randint(0, 3)):
                line[rng.randrange(len(line))] = rng.choice(vocabulary) if rng.random() < 0.7 else str(rng.randint(1, 99))
            lines.append(" ".join(line))
        out.append("\n".join(lines))
    return out


@pytest.mark.parametrize("seed", [1, 2])
def test_line_dedup_equals_a_plain_tree(spark, sf, seed):
    rng = random.Random(seed)
    docs = given(spark, sf, templates(rng, 150) + [None, "", "one two three four five six seven eight"])
    rows = sorted(docs.items())
    want = {i: gone for (i, _), gone in zip(rows, plain.dropped_lines(rows), strict=True)}
    got = {r.doc_id: r.dropped_lines for r in line_dedup.dedup_lines(made(spark, docs).repartition(5)).collect()}
    assert {i: (got[i], want[i]) for i in want if got[i] != want[i]} == {} and any(want.values())
    left = {r.doc_id: r.text for r in line_dedup.clean(made(spark, docs)).collect()}
    assert left == plain.without_lines(docs)


def test_one_document_of_many_like_lines_is_one_document(spark):
    """Nine differing lines of one document and one of another don't make ten documents."""
    lines = [f"short line of x{chr(97 + k)} words" for k in range(9)]
    few = documents(spark, ["\n".join(lines), "short line of zz words"])
    assert all(not r.dropped_lines for r in line_dedup.dedup_lines(few).collect())
    many = documents(spark, [f"short line of x{chr(97 + k)} words" for k in range(10)])
    assert sum(len(r.dropped_lines) for r in line_dedup.dedup_lines(many.repartition(4)).collect()) == 9


def quoted(rng, items):
    """Texts around items: whole, with other numbers and names, in part, and unlike ones."""
    filler = lambda n: " ".join(rng.choice(["so", "then", "we", "saw", "It", "was", "good.", "7", "km"]) for _ in range(n))
    out = []
    for x in items:
        w = x.split()
        swapped = [str(rng.randint(2, 99)) if v.isdigit() else rng.choice(["Ann", "Bob", "Eve"]) if v in ("Tom", "Sue") else v for v in w]
        a = rng.randrange(len(w))
        for part in (w, swapped, w[a:], w[: a + 1], w[:a] + ["other"] + w[a + 1 :]):
            out.append(f"{filler(rng.randint(0, 9))} {' '.join(part)} {filler(rng.randint(0, 9))}")
    return out


ITEMS = [
    "Tom has 3 apples. Tom buys 5 more apples from Sue. How many apples does Tom have now?", "A train goes 60 km in 2 hours. How far does it go in 5 hours if Sue drives?",
    "2 4 6 8 10 12 14 16 18 20", "Paris", "two words", "one plain sentence of exactly nine words stands here", "What is 2 and 2 and 3 and 3 if Tom says 2 and Sue says 3?",
]


@pytest.mark.parametrize("seed", [1, 2])
def test_decontamination_equals_plain_windows(spark, sf, seed):
    rng = random.Random(seed)
    bench = {r.item_id: r.text for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()}
    items = bench | {1000 + k: x for k, x in enumerate(ITEMS)}
    docs = given(spark, sf, quoted(rng, [*ITEMS, *rng.sample(sorted(bench.values()), 8)]) + ["Paris!", "two  Words", "Paris is far", "3 5 7 9 11 13 15 17 19 21", "2 4 6 8 10 12 14 16 18 20"])
    want = plain.contaminated(docs, items)
    table = spark.createDataFrame(sorted(items.items()), "item_id long, text string")
    got = {r.doc_id: (r.item_ids, r.coverage, r.reparameterised) for r in decontam.scan(made(spark, docs), table, block_bytes=[1 << 24, 3000][seed - 1]).collect()}
    assert {i: (got[i], want[i]) for i in want if (got[i][0], round(got[i][1], 9), got[i][2]) != (want[i][0], round(want[i][1], 9), want[i][2])} == {}
    assert sum(bool(v[0]) for v in want.values()) > 20


def test_a_list_of_numbers_holds_only_itself(spark):
    table = spark.createDataFrame([(1, ITEMS[2])], "item_id long, text string")
    texts = [" ".join(map(str, range(k, k + 4000))) for k in (1, 5)] + [ITEMS[2]]
    assert [bool(r.item_ids) for r in decontam.scan(documents(spark, texts), table).orderBy("doc_id").collect()] == [False, False, True]


def plain_fit(positive, unlabelled, prior, steps, rate=0.05, decay=2e-3):
    """The same risk by dense rows, its gradient by differences."""
    df_p, df_u = (np.bincount(np.concatenate(x), minlength=toxicity.BUCKETS) for x in (positive, unlabelled))
    used = np.flatnonzero(df_p >= max(2, 0.01 * len(positive)))
    scale = np.maximum(np.log((df_p[used] + 0.5) / (len(positive) + 1)) - np.log((df_u[used] + 0.5) / (len(unlabelled) + 1)), 0)
    rows = lambda lists: np.array([np.isin(used, x) * scale for x in lists])
    xp, xu = rows(positive), rows(unlabelled)

    def parts(theta):
        zp, zu = xp @ theta[:-1] + theta[-1], xu @ theta[:-1] + theta[-1]
        return prior * np.logaddexp(0, -zp).mean(), np.logaddexp(0, zu).mean() - prior * np.logaddexp(0, zp).mean()

    theta = np.append(np.zeros(len(used)), -1.0)
    m, v = np.zeros_like(theta), np.zeros_like(theta)
    for t in range(1, steps + 1):
        grad = np.zeros_like(theta)
        below = parts(theta)[1] < 0
        for j in range(len(theta)):
            e = np.zeros_like(theta)
            e[j] = 1e-6
            up, down = parts(theta + e), parts(theta - e)
            grad[j] = ((down[1] - up[1]) if below else (sum(up) - sum(down))) / 2e-6
        grad[:-1] += decay * theta[:-1]
        m, v = 0.9 * m + 0.1 * grad, 0.999 * v + 0.001 * grad**2
        theta = theta - rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-9)
    weights = np.zeros(toxicity.BUCKETS)
    weights[used] = theta[:-1] * scale
    return weights, theta[-1]


@pytest.mark.parametrize("prior", [0.1, 0.9])
def test_fit_follows_the_gradient_of_the_risk(prior):
    rng = np.random.default_rng(5)
    positive = [np.unique(rng.integers(0, 9, 4)) for _ in range(12)]
    unlabelled = [np.unique(rng.integers(4, 20, 5)) for _ in range(30)]
    m = toxicity.fit(positive, unlabelled, prior, steps=25)
    weights, bias = plain_fit(positive, unlabelled, prior, 25)
    assert m.weights == pytest.approx(weights, abs=2e-3) and m.bias == pytest.approx(bias, abs=2e-3)


def test_scores_are_those_of_a_plain_sum():
    rng = np.random.default_rng(6)
    m = toxicity.Model(rng.normal(0, 1, toxicity.BUCKETS).astype(np.float32), -0.3)
    texts = ["you are bad, bad!", "", None, "«Bad» ... ok", "x " * 50]
    got = toxicity.score_texts(pa.array(texts, pa.string()), m)
    for t, s in zip(texts, got, strict=True):
        bare = {w.strip(toxicity.MARKS) for w in plain.words((t or "").lower())} - {""}
        buckets = {int(b) for b in toxicity.word_buckets(pa.array(sorted(bare), pa.string()))}
        assert s == pytest.approx(1 / (1 + np.exp(-(sum(float(m.weights[b]) for b in buckets) + m.bias))))


def test_the_pipeline_equals_its_plain_stages(spark, sf):
    rows = {r.doc_id: r for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    items = {r.item_id: r.text for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()}
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    now = {i: r.text for i, r in rows.items()}
    stages = dict(corpus_pipeline.STAGES)

    def step(name, want):
        nonlocal docs
        docs = kept(stages[name](spark, docs, sf))
        got = {r.doc_id: r.text for r in docs.collect()}
        assert {i: (got.get(i), want.get(i)) for i in got.keys() | want.keys() if got.get(i) != want.get(i)} == {}, name
        return want

    known = plain.languages({i: (t, rows[i].lang) for i, t in now.items()})
    now = step("language_id", {i: t for i, t in now.items() if known[i] is not None})
    now = step("line_dedup", plain.without_lines(now))
    roots = plain.representatives(now)
    now = step("near_duplicates", {i: t for i, t in now.items() if roots[i] == i})
    held = plain.contaminated(now, items)
    now = step("decontamination", {i: t for i, t in now.items() if not held[i][0]})
    codec = pieces.Codec(pieces.read_pieces(queries.VOCABULARY))
    out = {r.doc_id: r for r in stages["sentencepiece"](spark, docs, sf).collect()}
    assert out.keys() == now.keys()
    for i, t in now.items():
        assert out[i].decodes and codec.decode(out[i].piece_ids) == t and out[i].n_pieces == len(out[i].piece_ids)
