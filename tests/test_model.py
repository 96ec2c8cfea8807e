"""Counts, edges, freedom and compression against a plain counter."""

from collections import Counter, defaultdict

import pytest
from pyspark.sql import functions as F

from freeseg.functions import kernels
from freeseg.operators import compress, model

LINES = ["ab ac", "ca b", "", "a", "aaaa", "éà é, ça?", "to be or not to be", "αβγ 中文 αβ", "a😀b😀"]


@pytest.fixture(scope="module")
def lines(spark):
    return spark.createDataFrame([("x", t) for t in LINES if t], "lang string, line string").cache()


def plain(n_max, lines=LINES):
    c = Counter()
    for t in lines:
        for n in range(1, n_max + 1):
            c.update((n, t[i : i + n]) for i in range(len(t) - n + 1))
    return c


@pytest.mark.parametrize("n_max", [1, 2, 3, 4])
def test_counts_equal_a_plain_counter(lines, n_max):
    for counted in (model.count_grams(lines, n_max), model.count_grams_once(lines, n_max)):
        assert {(r.n, r.gram): r.cnt for r in counted.collect()} == plain(n_max)


@pytest.mark.parametrize("direction", ["f", "b"])
def test_symbol_edges(lines, direction):
    want = Counter()
    for t in LINES:
        for n in (1, 2):
            for i in range(len(t) - n):
                want[(n, t[i : i + n], t[i + n]) if direction == "f" else (n, t[i + 1 : i + n + 1], t[i])] += 1
    got = {(r.n, r.gram, r.nbr): r.cnt for r in model.symbol_edges(model.count_grams(lines, 3), direction).collect()}
    assert got == want


@pytest.mark.parametrize("direction", ["f", "b"])
def test_gram_edges(lines, direction):
    want = Counter()
    for t in LINES:
        for i in range(len(t) - 3):
            u, x = t[i : i + 2], t[i + 2 : i + 4]
            want[(u, x) if direction == "f" else (x, u)] += 1
    assert {(r.gram, r.nbr): r.cnt for r in model.gram_edges(lines, 2, direction).collect()} == want
    wide = model.wide_edges(model.count_grams(lines, 4), [2]).where(F.col("dir") == direction)
    assert {(r.gram, r.nbr): r.cnt for r in wide.collect()} == want and {r.n for r in wide.collect()} == {2}


def test_graph_and_degrees(lines):
    grams = model.count_grams(lines, 2).cache()
    ends, ties = model.as_graph(grams.where("n = 1"), model.edges(grams))
    ids = {r.id: r.weight for r in ends.collect()}
    assert ids["x\u00011\u0001a"] == plain(1)[1, "a"]
    rows = ties.collect()
    assert all(r.src in ids and r.dst in ids for r in rows)
    out, into = Counter(r.src for r in rows if r.dir == "f"), Counter(r.src for r in rows if r.dir == "b")
    assert {r.id: (r.out_degree, r.in_degree) for r in model.degree(grams.where("n = 1"), model.edges(grams)).collect()} == {i: (out[i], into[i]) for i in ids}


def test_pruned_targets_and_global_limits(lines):
    grams = model.count_grams(lines, 2).cache()
    edges = model.edges(grams)
    one = {r.gram for r in compress.prune_vertices(grams, 0.3).where("n = 1").collect()}
    kept, left = compress.prune(grams, edges, 0.3, prune_targets=True)
    _, loose = compress.prune(grams, edges, 0.3)
    assert {(r.gram, r.nbr) for r in left.collect()} == {(r.gram, r.nbr) for r in loose.collect() if r.nbr in one}
    top = max(r.cnt for r in grams.collect())
    assert all(r.cnt >= 0.3 * top for r in compress.prune_vertices(grams, 0.3, "global").collect())


def test_worked_example(spark):
    two = spark.createDataFrame([("x", "ab ac"), ("x", "ca b")], "lang string, line string")
    grams = model.count_grams(two, 2)
    assert {r.gram: r.cnt for r in grams.where("n = 1").collect()} == {"a": 3, "b": 2, "c": 2, " ": 2}
    free = {r.gram: (r.tf_f, r.tf_b) for r in model.both_ways(model.freedom(model.edges(grams))).collect()}
    assert free == {"a": (3, 2), " ": (2, 2), "b": (1, 2), "c": (1, 1)}


def test_edges_sum_to_counts_without_line_ends(lines):
    grams = model.count_grams(lines, 2).cache()
    out = {r.gram: r.s for r in model.symbol_edges(grams, "f").groupBy("gram").agg(F.sum("cnt").alias("s")).collect()}
    last = Counter(t[-1] for t in LINES if t)
    for (_, g), c in plain(1).items():
        assert out.get(g, 0) == c - last[g]


def test_merge_is_the_model_of_the_union(spark, lines):
    other = spark.createDataFrame([("x", "ab zz"), ("y", "ab")], "lang string, line string")
    merged = model.merge(model.count_grams(lines, 2), model.count_grams(other, 2))
    whole = model.count_grams(lines.unionByName(other), 2)
    assert merged.exceptAll(whole).isEmpty() and whole.exceptAll(merged).isEmpty()


def test_reversed_text_swaps_directions(lines):
    back = lines.select("lang", F.reverse("line").alias("line"))
    a = model.symbol_edges(model.count_grams(lines, 2), "b").select("gram", "nbr", "cnt")
    b = model.symbol_edges(model.count_grams(back, 2), "f").select("gram", "nbr", "cnt")
    assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def test_pruning(lines):
    grams = model.count_grams(lines, 2).cache()
    edges = model.edges(grams).cache()
    v, e = compress.prune(grams, edges, 0.0)
    assert v.count() == grams.count() and e.count() == edges.count()
    plain_edges, most = defaultdict(dict), {}
    for r in edges.collect():
        plain_edges[r.dir, r.gram][r.nbr] = r.cnt
    counts = {r.gram: r.cnt for r in grams.where("n = 1").collect()}
    for theta in (0.1, 0.4):
        v, e = compress.prune(grams, edges, theta)
        most = max(counts.values())
        want = {(d, g, x) for (d, g), xs in plain_edges.items() for x, c in xs.items() if c >= theta * max(xs.values()) and counts[g] >= theta * most}
        assert {(r.dir, r.gram, r.nbr) for r in e.collect()} == want
        levels = {(r.dir, r.gram): r.tf for r in compress.freedom_levels(grams, edges, (theta,)).collect()}
        assert levels == Counter((d, g) for d, g, _ in want)


def test_fewer_parameters_at_higher_levels(lines):
    grams = model.count_grams(lines, 2)
    rows = compress.parameter_count(grams, model.edges(grams)).groupBy("theta").agg(F.sum("params").alias("p")).orderBy("theta").collect()
    assert [r.p for r in rows] == sorted((r.p for r in rows), reverse=True)


def test_save_and_load(spark, lines, tmp_path):
    grams = model.count_grams(lines, 2)
    model.save(grams, str(tmp_path / "m"))
    back = model.load(spark, str(tmp_path / "m"))
    assert back.exceptAll(grams).isEmpty() and back.count() == grams.count()


def test_sketched_freedom_is_near(lines):
    grams = model.count_grams(lines, 2)
    exact = {r.gram: r.tf for r in model.freedom(model.edges(grams)).where("dir = 'f'").collect()}
    assert {r.gram: r.tf_f for r in model.freedom_sketch(lines, 1).collect()} == exact


@pytest.mark.parametrize("symbols", ["ab é\0", "".join(map(chr, range(0x4E00, 0x4F80)))])
def test_a_task_counts_its_batches_together(spark, symbols):
    """A task's grams leave it once, whatever number of batches they come in; those of more symbols than can be packed are counted too."""
    import random

    own = random.Random(5)
    rows = [(lang, "".join(own.choices(symbols, k=own.randrange(0, 9)))) for lang in ("x", "y") for _ in range(300)]
    want = Counter((lang, n, t[i : i + n]) for lang, t in rows for n in range(1, 5 + 1) for i in range(len(t) - n + 1))
    lines = spark.createDataFrame(rows, "lang string, line string").coalesce(1)
    got = model.count_grams(lines, 5).collect()
    assert {(r.lang, r.n, r.gram): r.cnt for r in got} == dict(want) and len(got) == len(want)


def test_packed_windows_of_several_batches():
    counts = kernels.WindowCounts(8)
    want = Counter()
    for lines in (["abc", "", "bca"], ["é\0a", "abcabcabcabc"], ["abc"]):
        assert counts.add("x", lines)
        want.update(t[i : i + n] for t in lines for n in range(1, 9) for i in range(len(t) - n + 1))
    got = [(g, c) for _, _, some, cs in counts.grams(2) for g, c in zip(some.to_pylist(), cs.tolist(), strict=True)]
    assert dict(got) == dict(want) and len(got) == len(want) and not len(counts)
    assert not counts.add("x", ["".join(map(chr, range(100, 400)))])
