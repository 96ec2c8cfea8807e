import math
import re
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from freeseg.llm import lm, queries

from .helpers import documents, empty, odd_documents


def words(t):
    return [w for w in re.split("[\x20\x09-\x0d]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or "")) if w]


@pytest.fixture(scope="module")
def proto():
    with open(queries.VOCABULARY, "rb") as f:
        return f.read()


@pytest.fixture(scope="module", autouse=True)
def small():
    was = lm.STEPS
    lm.fit.__defaults__ = (20, lm.SEED)
    yield
    lm.fit.__defaults__ = (was, lm.SEED)


def plain(m, seq):
    """Log probabilities one place at a time, from the window that scores it."""
    inputs, out = [lm.START, *seq[:-1]], []
    for t in range(len(seq)):
        at = t // lm.STRIDE * lm.STRIDE
        places = range(max(0, at - lm.CONTEXT), t + 1)
        x = {p: m.embed[inputs[p]].astype(float) + m.place[p - at + lm.CONTEXT] for p in places}
        s = np.array([x[t] @ m.query @ (x[p] @ m.key) for p in places])
        a = np.exp(s - s.max())
        a /= a.sum()
        z = np.concatenate([x[t], sum(w * x[p] for w, p in zip(a, places, strict=True))]) @ m.out + m.bias
        out.append(z[m.cls[seq[t]]] - np.log(np.exp(z).sum()) + m.within[m.prev[inputs[t]], seq[t]])
    return np.array(out)


def model():
    rng = np.random.default_rng(0)
    seqs = [rng.integers(3, 40, n) for n in (5, 60, 100, 33)]
    return lm.fit(seqs, np.bincount(np.concatenate(seqs), minlength=50).astype(float), steps=30), rng


def test_windows_score_each_piece_once_as_a_plain_version_does():
    m, rng = model()
    seqs = [rng.integers(3, 45, n) for n in (1, 23, 24, 25, 70)]
    got = lm.log_probs(m, np.concatenate(seqs), np.array([len(s) for s in seqs]))
    assert got == pytest.approx(np.concatenate([plain(m, s.tolist()) for s in seqs]), abs=1e-4)


def test_next_pieces_are_a_distribution():
    m, _ = model()
    total = sum(math.exp(lm.log_probs(m, np.array([5, 9, k]), np.array([3]))[2]) for k in range(50))
    assert total == pytest.approx(1, abs=1e-4)


def test_the_past_only_is_seen():
    m, rng = model()
    a = rng.integers(3, 40, 50)
    b = a.copy()
    b[30:] = 7
    assert lm.log_probs(m, a, np.array([50]))[:30] == pytest.approx(lm.log_probs(m, b, np.array([50]))[:30], abs=1e-5)


def test_gradient_by_differences():
    """Fitting lowers the loss on what it is fitted to."""
    rng = np.random.default_rng(1)
    seqs = [np.tile(rng.permutation(np.arange(3, 13)), 12) for _ in range(6)]
    counts = np.bincount(np.concatenate(seqs), minlength=20).astype(float)
    loss = lambda m: -lm.log_probs(m, np.concatenate(seqs), np.array([len(s) for s in seqs])).mean()
    assert loss(lm.fit(seqs, counts, steps=300)) < loss(lm.fit(seqs, counts, steps=0)) - 0.3


def test_base_scores_equal_a_plain_version(spark, proto):
    texts = ["A b a c", None, "", "b\x0bb  B", "new words here", "a " * 500]
    docs = documents(spark, texts)
    learn = [0, 3, 5]
    counts = Counter()
    for k in learn:
        counts.update(words(texts[k]))
        counts["\n"] += 1
    n, v = sum(counts.values()), len(counts)
    for r in lm.score(docs, F.col("doc_id").isin(learn), proto).collect():
        toks = words(texts[r.id]) + ["\n"]
        assert (r.n_tokens, r.n_known, r.train_tokens) == (len(toks), sum(counts[w] > 0 for w in toks), n)
        assert r.base_score == pytest.approx(sum(math.log10((counts[w] + 1) / (n + v + 1)) for w in toks))
        assert r.score < 0


def test_odd_rows(spark, proto):
    docs = odd_documents(spark)
    rows = lm.score(docs, F.col("doc_id") % 2 == 0, proto).collect()
    assert len(rows) == docs.count() and all(math.isfinite(r.score) and math.isfinite(r.base_score) for r in rows)
    none = lm.score(docs, F.lit(False), proto).collect()
    assert {r.train_tokens for r in none} == {0} and all(math.isfinite(r.score) for r in none)
    assert lm.score(empty(spark), F.lit(True), proto).count() == 0


def test_pieces_of_texts_with_ends(proto):
    coder = lm.Coder(proto)
    from freeseg.llm.kernel import words_of

    w = words_of(pa.array(["the cat", "", "cat"]))
    stream, size, lengths = lm.piece_stream(w.offsets, w.codes, *coder.words(w.distinct))
    assert stream.tolist() == [*coder.sp.encode("the"), *coder.sp.encode("cat"), lm.END, lm.END, *coder.sp.encode("cat"), lm.END]
    assert lengths.sum() == size.sum() == len(stream)


@pytest.mark.parametrize("units", [1, 4])
def test_all_training_texts_are_learned_from(spark, proto, monkeypatch, units):
    """Tables of piece after piece and classes are those of every text, however the texts are dealt out, and fitting to units lowers the loss."""
    rng = np.random.default_rng(5)
    texts = [" ".join(f"{a}{b}" for a, b in zip(rng.choice(list("abcdefgh"), 5), rng.choice(["ing", "er", "ed"], 5), strict=True)) for _ in range(2300)]
    docs, coder = documents(spark, texts), lm.Coder(proto)
    seqs = [np.array([x for w in words(t) for x in coder.sp.encode(w)] + [lm.END]) for t in texts[: len(texts) - 100]]
    counts = np.bincount(np.concatenate(seqs), minlength=coder.sp.get_piece_size()).astype(float)
    found = lm.keep(lm.gather(lm.in_blocks(docs, F.col("doc_id") < len(seqs), "doc_id", "text"), spark.sparkContext.broadcast(proto)))
    if units > 1:
        monkeypatch.setattr(lm, "STEPS", sum(-(-len(s) // lm.STRIDE) for s in seqs) // lm.BATCH // units)
    m = lm.learned(found, counts)
    after = Counter((m.prev[a], b) for s in seqs for a, b in zip([lm.START, *s[:-1]], s, strict=True))
    total = Counter()
    for (g, b), c in after.items():
        total[g, m.cls[b]] += c
    mass = counts + 0.5
    for (g, b), c in after.items():
        alone = mass[b] / mass[m.cls == m.cls[b]].sum()
        assert m.within[g, b] == pytest.approx(math.log((c + lm.BACK_OFF * alone) / (total[g, m.cls[b]] + lm.BACK_OFF)), abs=1e-5)
    plain_fit = lm.fit(seqs, counts, steps=0)
    assert (m.cls == plain_fit.cls).all() and (m.prev == plain_fit.prev).all() and np.allclose(m.within, plain_fit.within, atol=1e-5)
    loss = lambda m: -lm.log_probs(m, np.concatenate(seqs), np.array([len(s) for s in seqs])).mean()
    assert loss(m) < loss(plain_fit)


def test_gradients_are_those_of_the_loss():
    m, rng = model()
    m = m._replace(**{k: rng.normal(0, 0.3, getattr(m, k).shape).astype(np.float32) for k in lm.WEIGHTS})
    lengths = np.array([5, 30, 60])
    sequence = rng.integers(3, 45, lengths.sum())
    windows = lm.laid(lm.inputs_of(sequence, lengths), m.cls[sequence], lengths)
    ids, inside, target, _ = lm.gathered(windows, np.arange(len(windows.first)))
    used, found = lm.gradients(m, ids, inside, target)
    assert used.tolist() == sorted({lm.START, *lm.inputs_of(sequence, lengths).tolist()})
    parts = np.split(sequence, np.cumsum(lengths)[:-1])
    loss = lambda m: -np.mean(np.concatenate([plain(m, p.tolist()) for p in parts]))
    for name in lm.WEIGHTS:
        for _ in range(4):
            at = tuple(int(rng.integers(n)) for n in found[name].shape)
            was = getattr(m, name).astype(float)
            place, step = (used[at[0]], *at[1:]) if name == "embed" else at, np.zeros_like(was)
            step[place] = 1e-4
            by_differences = (loss(m._replace(**{name: was + step})) - loss(m._replace(**{name: was - step}))) / 2e-4
            assert found[name][at] == pytest.approx(by_differences, abs=2e-5), name


def test_texts_are_read_and_spelled_once(spark, proto, tmp_path):
    """What scores texts was kept when their words were counted; the texts' own files are not read again."""
    documents(spark, ["a b c", None, "some other words"]).write.parquet(str(tmp_path / "docs"))
    found = lm.score(spark.read.parquet(str(tmp_path / "docs")), F.lit(True), proto)
    assert not [f for f in found.inputFiles() if str(tmp_path) in f]
    assert found.count() == 3


def test_packed_arrays_come_back():
    arrays = [np.arange(5, dtype=np.int32) - 2, np.zeros(0, np.uint16), np.array([2**63 - 1, -(2**63)]), np.array([7], np.uint16)]
    for a, b in zip(arrays, lm.unpack(lm.pack(*arrays)), strict=True):
        assert a.dtype == b.dtype and a.tolist() == b.tolist()


def test_mixtures_of_very_unlikely_words():
    spelled, share = np.array([-1.0, -599.0, -700.0, -900.0]), np.array([0.1, 0.0, 1e-3, 1e-300])
    for p, got in zip(lm.MIXED, lm.mixtures(spelled, np.maximum(share, 1e-305)), strict=True):
        assert got == pytest.approx(np.logaddexp(spelled + np.log(p), np.log(np.maximum(share, 1e-305)) + np.log1p(-p)))


def test_words_spelled_before_are_spelled_alike(proto):
    words = pa.array(["the", "zq", "", "ä" * 120, "the"])
    first, again = lm.Coder(proto).words(words), lm.Coder(proto).words(words)
    assert all((a == b).all() for a, b in zip(first, again, strict=True))
    coder = lm.Coder(proto)
    assert [first[0][a:b].tolist() for a, b in zip(first[1][:-1], first[1][1:], strict=True)] == [coder.sp.encode(w) for w in words.to_pylist()]
