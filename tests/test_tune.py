"""The grid, its two ways and what is read from it, against plain Python."""

import itertools
import re
from collections import Counter, defaultdict

import pytest
from pyspark.sql import functions as F

from freeseg.operators import baselines, evaluate, model, profile, segment, tune

LINES = {"en": ["the cat sat, the dog sat.", "a cat and a dog", "the end of the day.", "cats and dogs, dogs and cats"], "de": ["der hund und die katze.", "die katze, der hund"]}
TEST = [("en", "a", 0, "the cat and the dog."), ("en", "b", 1, "a day, a cat"), ("en", "c", 0, "?"), ("de", "a", 1, "der hund, die katze."), ("xx", "a", 0, "no model")]


@pytest.fixture(scope="module")
def test_set(spark):
    lines = spark.createDataFrame([(k, t) for k, ts in LINES.items() for t in ts], "lang string, line string")
    return spark.createDataFrame(TEST, "lang string, stmt_id string, half int, text string").cache(), model.count_grams(lines, 4).cache()


class Plain:
    """Counts, values, profiles and cells as definitions say."""

    def __init__(self, lines, n_max):
        self.c = Counter((len(t[i : i + n]), t[i : i + n]) for t in lines for n in range(1, n_max + 1) for i in range(len(t) - n + 1))
        self.top = defaultdict(int)
        for (n, _), v in self.c.items():
            self.top[n] = max(self.top[n], v)
        self.ways = {"f": defaultdict(dict), "b": defaultdict(dict)}
        for (n, w), v in self.c.items():
            if n > 1:
                self.ways["f"][w[:-1]][w[-1]] = v
                self.ways["b"][w[1:]][w[0]] = v

    def value(self, base, n, d, gram, nbr, theta):
        own = self.c.get((n, gram), 0)
        if not own or own < theta * self.top[n]:
            return 0.0
        if base == "p":
            return own / self.top[n]
        near = self.ways[d].get(gram, {})
        kept = {x: v for x, v in near.items() if v >= theta * max(near.values())}
        return float(len(kept)) if base == "tf" else kept.get(nbr, 0) / own

    def scores(self, text, base, kind, ranks, theta):
        ways = {}
        for d in "fb":
            rows = defaultdict(list)
            for n in ranks:
                v = {}
                for g in range(1, len(text)):
                    if d == "f" and g >= n:
                        v[g] = self.value(base, n, d, text[g - n : g], text[g], theta)
                    if d == "b" and g + n <= len(text):
                        v[g] = self.value(base, n, d, text[g : g + n], text[g - 1], theta)
                if not v:
                    continue
                mean = sum(v.values()) / len(v)
                near = lambda g, k, v=v: v.get(g + k, v[g])
                made = {g: {"raw": x, "variance": x - mean, "derivative": x - near(g, -1 if d == "f" else 1), "peak": (x - near(g, -1)) - (near(g, 1) - x)}[kind] for g, x in v.items()}
                most = max(made.values())
                for g, x in made.items():
                    rows[g].append(round(x / most, 9) if most > 0 else 0.0)
            ways[d] = {g: round(sum(x) / len(x), 9) for g, x in rows.items()}
        return [max((w[g] for w in ways.values() if g in w), default=float("-inf")) for g in range(1, len(text))]


def reference(text):
    return re.findall(r"[^\s!-/:-@\[-`{-~]+|[!-/:-@\[-`{-~]", text)


SETS, LEVELS, LIMITS = ((1,), (3,), (1, 2)), (0.0, 0.1, 0.3), (0.0, 0.1, 0.4, 0.9)


def plain_grid(by_half):
    out = {}
    models = {lang: Plain(lines, 4) for lang, lines in LINES.items()}
    for base, kind, ranks, theta, limit in itertools.product(profile.BASES, profile.OFFSHOOTS, SETS, LEVELS, LIMITS):
        hyp, ref = defaultdict(Counter), defaultdict(Counter)
        for lang, _, half, text in TEST:
            key = (lang, half) if by_half else (lang,)
            scores = models[lang].scores(text, base, kind, ranks, theta) if lang in models else [0.0] * (len(text) - 1)
            ends = [0, *(g for g, s in enumerate(scores, 1) if s > limit), len(text)]
            hyp[key].update(t for a, b in zip(ends, ends[1:], strict=False) if (t := text[a:b]).strip(" "))
            ref[key].update(reference(text))
        for key in ref:
            out[(*key, base, kind, "+".join(map(str, ranks)), theta, limit)] = ((hyp[key] & ref[key]).total(), hyp[key].total(), ref[key].total())
    return out


@pytest.mark.parametrize("by", [(), ("half",)])
@pytest.mark.parametrize("most", [10**6, 0])
def test_grid_equals_plain_python(test_set, by, most):
    st, grams = test_set
    got = tune.grid_search(st, grams, sets=SETS, levels=LEVELS, thresholds=LIMITS, by=by, most=most).collect()
    rows = {(r.lang, *(r[c] for c in by), r.base, r.offshoot, r.ranks, r.theta, r.threshold): (r.matched, r.hyp, r.ref) for r in got}
    want = plain_grid(bool(by))
    assert len(got) == len(rows) and rows.keys() == want.keys()
    assert {k: (rows[k], v) for k, v in want.items() if rows[k] != v} == {}


def test_grid_agrees_with_single_runs(test_set):
    st, grams = test_set
    cells = tune.grid_search(st, grams, ["tf"], ["variance"], [(1,)], [0.0], [0.4]).collect()
    one = {r.lang: r.f1 for r in evaluate.f1(evaluate.solid(segment.run(st, grams, segment.Config(theta=0.0))), baselines.reference_tokens(st)).collect()}
    assert {r.lang: r.f1 for r in cells} == one


def test_halves_best_and_heatmap(spark):
    cell = "lang string, half int, base string, offshoot string, ranks string, theta double, threshold double, f1 double"
    rows = [("x", h, "tf", "raw", "1", 0.0, t, f) for h, fs in ((0, (0.5, 0.9, 0.9)), (1, (0.8, 0.6, 0.4))) for t, f in zip((0.1, 0.2, 0.3), fs, strict=True)]
    halves = spark.createDataFrame(rows, cell)
    got = {r.chosen_on: (r.winners, r.f1_own, r.f1_other, r.best_other) for r in tune.split_check(halves).collect()}
    assert got == {0: (2, 0.9, 0.5, 0.8), 1: (1, 0.8, 0.5, 0.9)}
    assert sorted((r.half, r.threshold) for r in tune.best(halves, "lang", "half").collect()) == [(0, 0.2), (0, 0.3), (1, 0.1)]
    heat = tune.heatmap(halves.where("half = 0"), (0.1, 0.3), "lang").first()
    assert (heat["ranks"], heat["t_0.1"], heat["t_0.3"]) == ("1", 0.5, 0.9)


def test_unsupervised_choice_and_summary(spark):
    rows = [("x", "tf", "raw", "1", 0.0, t, h, 0.1 * h) for t, h in ((0.1, 8), (0.2, 4), (0.3, 4), (0.4, 1))]
    scores = spark.createDataFrame(rows, "lang string, base string, offshoot string, ranks string, theta double, threshold double, hyp long, f1 double")
    assert tune.select_unsupervised(scores).first().threshold == 0.3
    f1 = spark.createDataFrame([("x", "a", 0.5), ("y", "a", 0.6)], "lang string, method string, f1 double")
    right, ref = spark.createDataFrame([("x", "a", 0.9)], "lang string, method string, precision double"), spark.createDataFrame([("x", 1.0)], "lang string, precision double")
    assert sorted((r.lang, r.method, r.f1, r.precision, r.reference) for r in tune.summary(f1, right, ref).collect()) == [("x", "a", 0.5, 0.9, 1.0), ("y", "a", 0.6, None, None)]


def test_rank_sets():
    assert len(tune.rank_sets(7)) == 127 and {(n,) for n in range(1, 8)} <= set(tune.SETS) and set(tune.rank_sets(3)) <= set(tune.SETS)


def test_sweep_of_the_arrays_is_that_of_the_tree(test_set):
    st, grams = test_set
    from freeseg.operators import apply

    held = apply.slices(grams, segment.Config())
    spans = apply.swept(st, held, segment.Config(), "lang", "text", "stmt_id")
    for limit in (0.0, 0.4):
        want = segment.run(st, grams, segment.Config(threshold=limit)).select("lang", "stmt_id", "start", "len", "token")
        got = spans.where(f"low <= {limit} and high > {limit}").select(*want.columns)
        assert got.exceptAll(want).isEmpty() and want.exceptAll(got).isEmpty()
    assert not spans.where(F.col("low") >= F.col("high")).count()


def test_tokens_of_all_thresholds_at_once():
    """What is counted by numbers of exceeded thresholds is what cutting the texts gives."""
    import numpy as np

    from freeseg.functions import kernels

    rng, limits = np.random.default_rng(3), [0.0, 0.2, 0.5, 0.9]
    texts = ["".join(rng.choice(list("ab  "), k)) for k in (1, 2, 7, 30, 90)] + ["   ", "b" * 150 + " a"]
    tokens = ["a", "ab", "ba", "b", "bb", "aab", "zz", "b" * 70, "b" * 150]
    t, wide = kernels.texts_of(texts), len(limits) + 1
    score = np.round(rng.random(len(t.points)), 1)
    counts = np.zeros(len(tokens) * wide, np.int32)
    totals = kernels.Bags(t, kernels.References(tokens)).add(kernels.exceeded(score, [np.nextafter(x, np.inf) for x in limits]), len(limits), counts)
    got = np.cumsum(counts.reshape(-1, wide), axis=1)[:, :-1]
    for k, x in enumerate(limits):
        starts, ends = kernels.spans(t, score > x)
        want = Counter(w for a, b in zip(starts, ends, strict=True) if (w := "".join(texts)[a:b]).strip(" "))
        assert totals[k] == want.total() and got[:, k].tolist() == [want[w] for w in tokens]


def test_limits_of_rounded_means():
    """A mean reaches a threshold's limit just if it is above the threshold when rounded."""
    import numpy as np

    from freeseg.functions import kernels

    thresholds = [-0.5, 0.0, *tune.THRESHOLDS]
    for x, least in zip(thresholds, kernels.limits(thresholds), strict=True):
        assert kernels.round_half_up(np.float64(least)) > x >= kernels.round_half_up(np.nextafter(least, -np.inf))


def test_a_task_goes_through_its_texts_for_a_few_offshoots_at_once(test_set, monkeypatch):
    monkeypatch.setattr(tune, "COUNTS", 1)
    monkeypatch.setattr(tune, "CHUNK_SYMBOLS", 10)
    test_grid_equals_plain_python(test_set, ("half",), 10**6)
