import random
import re

import pytest

from freeseg.llm import near_dup, tables

from .helpers import documents, empty, odd_documents


def words(t):
    return [w for w in re.split("[\x20\x09-\x0d]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or "")) if w]


def brute(rows, width, num, den):
    sets = {}
    for i, t in rows:
        w = words(t)
        sets[i] = {tuple(w[j : j + width]) for j in range(len(w) - width + 1)} if len(w) >= width else {tuple(w)} if w else set()
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for k, a in enumerate(ids):
        for b in ids[:k]:
            if sets[a] and den * len(sets[a] & sets[b]) >= num * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i in ids}


def corpus(seed=3):
    rng = random.Random(seed)
    vocab = [f"w{k}" for k in range(300)]
    out = []
    for _ in range(25):
        base = rng.choices(vocab, k=rng.choice([1, 2, 3, 4, 6, 10, 40, 200]))
        out.append(" ".join(base))
        for _ in range(rng.choice([0, 0, 1, 3, 12])):  # near copies of many likenesses
            copy = list(base)
            for _ in range(max(1, int(len(copy) * rng.choice([0.01, 0.03, 0.06, 0.1])))):
                copy[rng.randrange(len(copy))] = rng.choice(vocab)
            out.append(" ".join(copy).upper() if rng.random() < 0.1 else " ".join(copy))
    return out


@pytest.mark.parametrize(("width", "num", "den"), [(2, 80, 100), (5, 4, 5), (1, 1, 2)])
def test_components_equal_brute_force(spark, width, num, den):
    texts = corpus()
    got = {r.id: (r.n_shingles, r.component_id) for r in near_dup.groups(documents(spark, texts), width=width, num=num, den=den).collect()}
    assert got == brute(list(enumerate(texts)), width, num, den)


def test_a_chain_of_near_copies_is_one_component(spark):
    base = [f"w{k}" for k in range(100)]
    texts = [" ".join([*(f"y{j}" for j in range(3 * k)), *base[3 * k :]]) for k in range(12)]
    rows = list(enumerate(texts))
    got = {r.id: r.component_id for r in near_dup.groups(documents(spark, texts), width=2, num=80, den=100).collect()}
    assert got == {i: c for i, (_, c) in brute(rows, 2, 80, 100).items()} and set(got.values()) == {0}


def test_large_group_in_blocks(spark, monkeypatch):
    monkeypatch.setattr(near_dup, "BLOCK", 4)
    texts = corpus(8)
    got = {r.id: (r.n_shingles, r.component_id) for r in near_dup.groups(documents(spark, texts), width=2, num=80, den=100).collect()}
    assert got == brute(list(enumerate(texts)), 2, 80, 100)


def test_odd_rows(spark):
    rows = near_dup.groups(odd_documents(spark)).collect()
    assert len(rows) == odd_documents(spark).count()
    by = {r.id: r for r in rows}
    assert by[0].n_shingles == 0 and by[0].component_id == 0 and by[1].component_id == 1
    assert all(r.component_id is None for r in rows if r.id is None)
    left = near_dup.dedup(odd_documents(spark))
    assert left.columns == odd_documents(spark).columns
    assert left.where("doc_id = 9").count() == 1


def test_empty_table(spark):
    assert near_dup.groups(empty(spark)).count() == 0 and near_dup.dedup(empty(spark)).count() == 0


def test_one_of_each_group_stays(spark):
    text = " ".join(f"w{k}" for k in range(60))
    left = near_dup.dedup(documents(spark, [text, text + " z", "other words here", text, None]))
    assert sorted(r.doc_id for r in left.collect()) == [0, 2, 4]


@pytest.mark.parametrize("at_once", [-1, 1000])
def test_components_of_paths_and_stars(spark, at_once):
    edges = [(k + 1, k) for k in range(40)] + [(100, k) for k in range(101, 140)] + [(7, 7), (None, 3)]
    got = {r.node: r.component for r in tables.components(spark.createDataFrame(edges, "a long, b long"), at_once=at_once).collect()}
    assert got == {k: 0 for k in range(41)} | {k: 100 for k in range(100, 140)}
    assert tables.components(spark.createDataFrame([], "a long, b long"), at_once=at_once).count() == 0


@pytest.mark.parametrize(("n", "width"), [(5, 2), (5, 5), (10, 2)])
def test_values_on_one_bit_lose_no_pair(spark, n, width):
    """Texts whose sketches have several values on one bit, each with a copy without its last words that is just similar enough."""
    rng, bases = random.Random(n), []
    while len(bases) < 20:
        some = [" ".join(f"v{rng.randrange(10**6)}" for _ in range(n + width - 1)) for _ in range(4000)]
        for t, s in zip(some, near_dup.shingle_sets(near_dup.pa.array([" ".join(t.split()[: -n // 5]) for t in some]), width), strict=True):
            if len(s) - len({int(x) & near_dup.BITS - 1 for x in s}) >= 1 + (n > 5):
                bases.append(t)
    texts = [x for t in bases for x in (t, " ".join(t.split()[: -n // 5]))]
    got = {r.id: (r.n_shingles, r.component_id) for r in near_dup.groups(documents(spark, texts), width=width, num=4, den=5).collect()}
    assert got == brute(list(enumerate(texts)), width, 4, 5)
    assert all(got[2 * k + 1][1] == 2 * k for k in range(len(bases)))
