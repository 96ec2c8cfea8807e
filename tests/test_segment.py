"""Profiles, offshoots, breaks and tokens: worked example, invariants, and the array engine against the row engine."""

import itertools
import math
import random
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from freeseg.functions import kernels, udfs
from freeseg.operators import apply, baselines, evaluate, model, profile, segment
from freeseg.plans import workloads
from freeseg.sources import corpus


@pytest.fixture(scope="module")
def toy(spark):
    lines = spark.createDataFrame([("x", "ab ac"), ("x", "ca b")], "lang string, line string")
    st = spark.createDataFrame([("x", 1, "ab ac")], "lang string, stmt_id long, text string")
    return st, model.count_grams(lines, 3).cache()


def ways(p):
    out = {"f": {}, "b": {}}
    for r in p.collect():
        out[r.dir][r.gap] = r.v
    return {d: [v[g] for g in sorted(v)] for d, v in out.items()}


def test_worked_example(toy):
    st, grams = toy
    p = segment.base_profile(st, grams, "tf", [1]).cache()
    assert ways(p) == {"f": [3, 1, 2, 3], "b": [2, 2, 2, 1]}
    assert ways(profile.offshoot(p, "variance"))["f"] == [0.75, -1.25, -0.25, 0.75]
    assert ways(profile.offshoot(p, "derivative")) == {"f": [0, -2, 1, 1], "b": [0, 0, 1, 0]}
    assert ways(profile.offshoot(p, "peak"))["f"] == [2, -3, 0, 1]
    f, b = kernels.base(kernels.texts_of(["ab ac"]), kernels.make_slice(list("abc "), [3, 1, 1, 2], [2, 2, 1, 2]))
    assert f[:-1].tolist() == [3, 1, 2, 3] and b[:-1].tolist() == [2, 2, 2, 1] and np.isnan([f[-1], b[-1]]).all()


@pytest.fixture(scope="module")
def real(spark, sf):
    grams = model.count_grams(corpus.train_lines(spark, sf), 4).cache()
    odd = spark.createDataFrame([("en", "o0", 0, "aa"), ("en", "o1", 1, "  ?!"), ("en", "o2", 0, "ééé中文 x😀y"), ("en", "o3", 0, "z"), ("xx", "o4", 0, "no model")], "lang string, stmt_id string, half int, text string")
    return corpus.statements(spark, sf).where("length(text) < 400").unionByName(odd).cache(), grams


def lists(rows):
    return {(r.lang, r.stmt_id): [x.token for x in r.t] for r in rows.groupBy("lang", "stmt_id").agg(F.array_sort(F.collect_list(F.struct("tok_no", "token"))).alias("t")).collect()}


CONFIGS = [segment.Config("tf", kind, (1, 2), 0.0001, 0.3) for kind in profile.OFFSHOOTS]
CONFIGS += [segment.Config("tf", "variance", (1,), 0.0001, 0.3, combine) for combine in ("mean", "forward", "backward")]
CONFIGS += [segment.Config(base, "peak", ranks, 0.001, 0.2, kind=wide) for base in ("p", "cp", "tf") for ranks, wide in (((1, 2), "symbol"), ((2,), "gram"))]


@pytest.mark.parametrize("c", CONFIGS, ids=lambda c: "-".join(map(str, (c.base, c.offshoot, c.ranks, c.combine, c.kind))))
def test_engines_agree(real, c):
    st, grams = real
    want = lists(segment.run(st, grams, c, engine="rows"))
    assert lists(segment.run(st, grams, c, engine="arrays")) == want
    if c.base == "tf" and c.kind == "symbol":
        got = {(r.lang, r.stmt_id): r.tokens for r in apply.segment_texts(st, udfs.freedom_slices(grams, c), c).collect()}
        assert got == want


def test_a_model_too_large_to_broadcast_is_joined(real, monkeypatch):
    st, grams = real
    want = lists(segment.run(st, grams))
    monkeypatch.setattr(apply, "slices", lambda *a, **k: None)
    assert lists(segment.run(st, grams)) == want
    assert apply.sliced(profile.values(grams, "tf", [1]), "tf", most=3) is None


def test_null_and_empty_texts(spark, real):
    st = spark.createDataFrame([("en", "a", None), ("en", "b", ""), (None, "c", "ab cd")], "lang string, stmt_id string, text string")
    assert lists(segment.run(st, real[1])) == {(None, "c"): ["ab cd"]}
    assert {r.stmt_id: r.tokens for r in apply.segment_texts(st, udfs.freedom_slices(real[1], segment.Config())).collect()} == {"a": None, "b": [], "c": ["ab cd"]}


def test_padding_scale_and_unseen(spark, toy):
    st, grams = toy
    p = segment.base_profile(st, grams, "tf", [1])
    assert ways(profile.offshoot(p, "derivative", "zero"))["f"] == [3, -2, 1, 1]
    scaled = lambda **how: sorted(r.v for r in segment.offshoots(st, grams, segment.Config(offshoot="raw", theta=0.0, **how)).where("dir = 'f'").collect())
    assert scaled(scale="none") == [1, 2, 3, 3] and scaled(scale="model") == [0.333333333, 0.666666667, 1, 1]
    odd = spark.createDataFrame([("x", 1, "abz")], "lang string, stmt_id long, text string")
    back = lambda unseen: [r.v for r in segment.base_profile(odd, grams, "tf", [2], unseen=unseen).where("dir = 'b' and gap = 1").collect()]
    # "bz" is unseen and so is "z" after it: two symbols back off to what begins with b.
    assert back("zero") == [0] and back("null") == [None] and back("backoff") == [2]


def test_conditional_probability_across_a_gap(toy):
    st, grams = toy
    assert [round(x, 6) for x in ways(segment.base_profile(st, grams, "cp", [1]))["f"]] == [0.333333, 0.5, 0.5, 0.333333]
    low = ways(segment.base_profile(st, grams, "cp", [1], polarity="low"))["f"]
    assert [round(x, 6) for x in low] == [0.666667, 0.5, 0.5, 0.666667]


def test_local_maxima_as_a_rule(toy):
    st, grams = toy
    c = segment.Config("tf", "derivative", (1,), 0.0, 0.0, "forward", rule="local_max")
    # The forward derivative is 0, -2, 1, 1: it rises to its third value.
    assert [r.token for r in segment.run(st, grams, c).orderBy("tok_no").collect()] == ["ab ", "ac"]


def test_explained_profile(spark, toy):
    rows = profile.explain(spark, toy[1], "x", "ab ac").where("dir = 'f'").orderBy("gap").collect()
    assert [(r.symbol, r.value, r.variance, r.derivative, r.peak) for r in rows] == [("a", 3, 0.75, 0, 2), ("b", 1, -1.25, -2, -3), (" ", 2, -0.25, 1, 0), ("a", 3, 0.75, 1, 1)]


def test_tokens_are_the_text_and_breaks_shrink(real):
    st, grams = real
    scores = segment.scores(st, grams, segment.Config()).cache()
    sizes = []
    for t in (0.0, 0.2, 0.5, 0.9):
        toks = segment.tokens(st, segment.breaks(scores, t))
        assert segment.joined(toks).join(st, ["lang", "stmt_id", "text"], "left_anti").isEmpty()
        sizes.append(toks.count())
    assert sizes == sorted(sizes, reverse=True)


def test_variance_sums_to_zero(real):
    st, grams = real
    p = profile.offshoot(segment.base_profile(st, grams, "tf", [1]), "variance")
    assert p.groupBy("lang", "stmt_id", "dir").agg(F.abs(F.sum("v")).alias("s")).where("s > 1e-6").isEmpty()


def test_sweep_gives_the_tokens_of_every_threshold():
    rng = np.random.default_rng(1)
    for size in (1, 2, 7, 30):
        scores = np.round(rng.random(size), 1)
        text = "".join(chr(97 + k % 26) for k in range(size + 1))
        spans = kernels.sweep(scores)
        assert len(spans) < 2 * len(text)
        for t in (-0.5, 0.0, 0.15, 0.3, 0.5, 0.95, 1.0):
            want = kernels.cut(text, np.flatnonzero(scores > t) + 1)
            assert [text[a : a + n] for a, n, low, high in sorted(spans) if low <= t < high] == want


def test_swept_corpus(real):
    st, grams = real
    c = segment.Config()
    spans = apply.swept(st, udfs.freedom_slices(grams, c), c, "lang", "text", "stmt_id").where(f"low <= {c.threshold} and high > {c.threshold}")
    toks = segment.run(st, grams, c).select("lang", "stmt_id", "start", "len", "token")
    assert toks.exceptAll(spans.select(*toks.columns)).isEmpty()


def test_local_maxima(toy):
    st, grams = toy
    p = segment.base_profile(st, grams, "tf", [1]).where("dir = 'f'")
    assert [r.is_break for r in profile.local_maxima(p).orderBy("gap").collect()] == [True, False, False, True]


def test_mutual_information_merging_is_the_threshold_cut(spark, sf, real):
    st, grams = real
    st = st.where("lang = 'en' and length(stmt_id) < 3")
    mi = {(r.stmt_id, r.gap): r.mi for r in baselines.mi_gaps(st, grams).collect()}
    toks = segment.tokens(st, baselines.mi_breaks(st, grams, 1.0))
    got = {r.stmt_id: [x.token for x in r.t] for r in toks.groupBy("stmt_id").agg(F.array_sort(F.collect_list(F.struct("tok_no", "token"))).alias("t")).collect()}
    for r in st.collect():
        parts = [[g] for g in range(len(r.text))]  # places of symbols
        while True:  # best pair of neighbours first
            at = [(mi.get((r.stmt_id, a[-1] + 1)), k) for k, a in enumerate(parts[:-1])]
            at = [(v, -k) for v, k in at if v is not None and v >= 1.0]
            if not at:
                break
            k = -max(at)[1]
            parts[k : k + 2] = [parts[k] + parts[k + 1]]
        assert got[r.stmt_id] == ["".join(r.text[i] for i in p) for p in parts]
    assert lists(baselines.mi_tokens(st, grams, 1.0)) == lists(toks)


def test_mutual_best_pairs(spark):
    lines = spark.createDataFrame([("x", t) for t in ("ab", "ab", "ab", "bc", "ca", "cb")], "lang string, line string")
    st = spark.createDataFrame([("x", "s", "abca")], "lang string, stmt_id string, text string")
    mi = {r.gap: r.mi for r in baselines.mi_gaps(st, model.count_grams(lines, 2)).collect()}
    assert mi[1] > mi[2] and mi[3] > mi[2]
    assert [r.gap for r in baselines.mi_breaks(st, model.count_grams(lines, 2), variant="mutual_best").collect()] == [2]


def plain_merges(lines, rounds, least=2):
    """Re-estimated merging in plain Python."""
    now, done = {lang: [list(t) for t in texts] for lang, texts in lines.items()}, []
    for _ in range(rounds):
        for lang in sorted(now):
            one, two = Counter(x for t in now[lang] for x in t), Counter(p for t in now[lang] for p in itertools.pairwise(t))
            s1, s2 = one.total(), two.total()
            rated = [(-round(math.log2((c / s2) / ((one[x] / s1) * (one[y] / s1))), 9), -c, x, y) for (x, y), c in two.items() if c >= least]
            if not rated:
                continue
            _, _, x, y = min(rated)
            done.append((lang, x, y))
            for t in now[lang]:
                i = 0
                while i < len(t) - 1:
                    if t[i] == x and t[i + 1] == y:
                        t[i : i + 2] = [x + y]
                    i += 1
    return done, now


def test_iterative_merging_takes_the_most_informative_pair(spark):
    # "q" and "z" occur together only, "a" and "b" far more often but also apart.
    texts = {"x": ["ab a b ab ba ab", "qz a qz b", "aab bba ab"], "y": ["xyxy xy", "yx xy"]}
    lines = spark.createDataFrame([(k, t) for k, ts in texts.items() for t in ts], "lang string, line string")
    merges, left = baselines.mi_merges(lines, 4)
    want, after = plain_merges(texts, 4)
    assert merges == want and merges[0] == ("x", "q", "z")
    assert sorted((r.lang, r.toks) for r in left.collect()) == sorted((k, t) for k, ts in after.items() for t in ts)


def test_merging_writes_counts_and_not_the_corpus(spark):
    texts = {"x": ["aaaa baa aaab", "aaa a\U0001f600a", "ba ba aa"], "y": ["abcabc ab c", "bc abc", "a bc"]}
    rows = [(k, t) for k, ts in texts.items() for t in ts] + [(None, "ab"), ("x", None)]
    written = []

    def keep(df):
        out = df.cache()
        written.append(out.count())
        return out

    merges, left = baselines.mi_merges(spark.createDataFrame(rows * 50, "lang string, line string"), 5, keep)
    want, after = plain_merges({k: ts * 50 for k, ts in texts.items()}, 5)
    assert merges == want and max(written) < 100
    after |= {None: [["a", "b"]] * 50}
    assert Counter((r.lang, tuple(r.toks)) for r in left.where("toks is not null").collect()) == Counter((k, tuple(t)) for k, ts in after.items() for t in ts)


@pytest.mark.parametrize("by", ["length", "frequency", "blend"])
def test_greedy_lexicon(spark, by):
    lex = spark.createDataFrame([("x", "ab", 5), ("x", "abc", 2), ("x", "c", 9), ("x", "d", 1)], "lang string, word string, freq long")
    st = spark.createDataFrame([("x", 1, "abcdz"), ("x", 2, ""), ("y", 3, "ab")], "lang string, stmt_id long, text string")
    toks = {}
    for r in baselines.lexicon_tokens(st, lex, by).orderBy("tok_no").collect():
        toks.setdefault(r.stmt_id, []).append(r.token)
    want = {"length": ["abc", "d", "z"], "frequency": ["ab", "c", "d", "z"], "blend": ["ab", "c", "d", "z"]}[by]
    assert toks == {1: want, 3: ["a", "b"]}
    joined = {}
    for r in baselines.lexicon_tokens(st, lex, by, most=1).orderBy("tok_no").collect():
        joined.setdefault(r.stmt_id, []).append(r.token)
    assert joined == toks


@pytest.mark.parametrize("most", [2_000_000, 40, 1])
def test_lexicons_without_words_are_looked_up_as_one(spark, most):
    rng = random.Random(5)
    made = sorted({"".join(rng.choice("abc") for _ in range(rng.randint(1, 5))) for _ in range(150)})
    lex = spark.createDataFrame([(g, w, 1 + len(w)) for g in "xy" for w in made[: 150 if g == "x" else 40]], "lang string, word string, freq long").cache()
    texts = [(g, i, "".join(rng.choice("abcd") for _ in range(60))) for i in range(8) for g in "xyz"]
    st = spark.createDataFrame(texts, "lang string, stmt_id long, text string").cache()
    got = Counter((r.lang, r.percent, r.token) for r in baselines.missing_tokens(st, lex, (0, 10, 50), most=most, blocks=20).collect())
    want = Counter()
    for percent in (0, 10, 50):
        words = {(r.lang, r.word) for r in baselines.without_words(lex, percent).collect()}
        for g, _, text in texts:
            at = 0
            while at < len(text):
                n = next((n for n in range(5, 1, -1) if (g, text[at : at + n]) in words and at + n <= len(text)), 1)
                want[g, percent, text[at : at + n]] += 1
                at += n
    assert got == want


def test_a_lexicon_of_some_blocks_is_not_joined(spark):
    """Joined spans are a row for each place and length, which fills the disk."""
    lex = spark.createDataFrame([("x", w, 2) for w in ("ab", "abc", "c", "d")], "lang string, word string, freq long")
    st = spark.createDataFrame([("x", 1, "abcdz")], "lang string, stmt_id long, text string")
    plan = lambda **how: baselines.lexicon_tokens(st, lex, **how)._jdf.queryExecution().toString()
    assert "Join" not in plan(most=3) and "Join" in plan(most=3, blocks=1)
    of = lambda **how: sorted((r.tok_no, r.token) for r in baselines.lexicon_tokens(st, lex, **how).collect())
    assert of(most=3) == of(most=3, blocks=1) == of() == [(1, "abc"), (2, "d"), (3, "z")]


def test_other_rules_in_arrays_equal_rows(spark):
    rng = random.Random(3)
    text = lambda n: "".join(rng.choice("aabcd ") for _ in range(n))
    lines = spark.createDataFrame([(g, text(20)) for g in "xy" for _ in range(12)] + [("z", "a")], "lang string, line string")
    st = spark.createDataFrame([(g, i, text(rng.randint(0, 30)) + "e" * (i % 3)) for i in range(12) for g in "xyzw"], "lang string, stmt_id long, text string").cache()
    grams = model.count_grams(lines, 4).cache()
    some = [*workloads.RULES.values(), segment.Config(ranks=(1, 2), theta=0.0, rule="local_max", threshold=0.1, combine="forward"), segment.Config("cp", "peak", (1, 3), 0.01, 0.2, unseen="backoff", scale="model"), segment.Config("p", "raw", (3,), 0.0, 0.3, unseen="backoff")]
    for c in some:
        assert c.in_arrays
        a, b = (segment.run(st, grams, c, engine=e).select("lang", "stmt_id", "tok_no", "start", "len", "token") for e in ("arrays", "rows"))
        assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty(), c
    a, b = (x.select("lang", "stmt_id", "token") for x in (baselines.mi_tokens(st, grams, variant="mutual_best"), segment.tokens(st, baselines.mi_breaks(st, grams, variant="mutual_best"))))
    assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()
    lex = spark.createDataFrame([(g, w, 2) for g in "xy" for w in ("ab", "a a", "bcd", "c")], "lang string, word string, freq long")
    a, b = (baselines.hybrid_run(st, grams, segment.Config(theta=0.0, threshold=0.2), lex, blocks=k).select("lang", "stmt_id", "start", "token") for k in (8, 0))
    assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def test_rules_are_planned_one_at_a_time(spark, sf):
    """All methods in one plan, with their broadcasts, are more than the driver holds."""
    plan = workloads.w40_rules(spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "Window" not in plan and plan.count("Join") == 1


def test_f1_is_symmetric_and_one_for_equal_bags(real):
    st, grams = real
    a, b = segment.run(st, grams, keep_space=False), baselines.reference_tokens(st)
    one, two = ({r.lang: r.f1 for r in evaluate.f1(x, y).collect()} for x, y in ((a, b), (b, a)))
    assert one == two
    assert {r.f1 for r in evaluate.f1(b, b).collect()} == {1.0}


def test_freedom_is_above_conditional_probability_and_mutual_information(spark, sf, real):
    st, grams = real
    ref = baselines.reference_tokens(st).where("lang = 'en'")
    best = lambda toks: evaluate.f1(toks.where("lang = 'en' and trim(token) <> ''"), ref).first().f1
    tf = best(segment.run(st, grams))
    assert tf > best(baselines.cp_tokens(st, grams)) and tf > best(segment.tokens(st, baselines.mi_breaks(st, grams, 1.0)))
    assert tf > best(segment.run(st, grams, segment.Config(ranks=(2,))))


def test_hybrid_keeps_lexicon_words_whole(spark):
    cuts = spark.createDataFrame([("x", 1, g) for g in (1, 2, 3)], "lang string, stmt_id long, gap int")
    words = spark.createDataFrame([("x", 1, 1, "ab"), ("x", 1, 2, "cd")], "lang string, stmt_id long, tok_no int, token string")
    assert [r.gap for r in baselines.hybrid_breaks(cuts, words).collect()] == [2]
    st = spark.createDataFrame([("x", 1, "abcd")], "lang string, stmt_id long, text string")
    free = spark.createDataFrame([("x", 1, k) for k in (1, 2, 3, 4)], "lang string, stmt_id long, start int")
    assert lists(baselines.hybrid_tokens(st, free, words)) == {("x", 1): ["ab", "cd"]}


def test_reference_spans_lie_where_the_tokens_are(spark):
    st = spark.createDataFrame([("x", 1, " Ab, c.\t(d) ")], "lang string, stmt_id long, text string")
    spans = sorted((r.start, r.len, r.token) for r in baselines.reference_spans(st).collect())
    assert spans == [(2, 2, "Ab"), (4, 1, ","), (6, 1, "c"), (7, 1, "."), (9, 1, "("), (10, 1, "d"), (11, 1, ")")]


def test_costs(spark, tmp_path):
    lines = spark.createDataFrame([("x", "éa")], "lang string, line string")
    assert {r.n: (r.grams, r.bytes) for r in evaluate.model_cost(model.count_grams(lines, 2)).collect()} == {1: (2, 19), 2: (1, 11)}
    cost = evaluate.measured(spark.range(7), lambda df: df.write.parquet(str(tmp_path / "o")))
    assert cost["rows"] == 7 and cost["seconds"] > 0


def test_boundary_and_span_f1(spark):
    row = "lang string, stmt_id long, gap int"
    h, r = spark.createDataFrame([("x", 1, 1), ("x", 1, 2)], row), spark.createDataFrame([("x", 1, 2), ("x", 1, 5)], row)
    assert evaluate.boundary_f1(h, r).first().f1 == 0.5
    span = "lang string, stmt_id long, start int, len int"
    assert evaluate.span_f1(spark.createDataFrame([("x", 1, 1, 2)], span), spark.createDataFrame([("x", 1, 1, 2), ("x", 1, 3, 1)], span)).first().f1 == pytest.approx(0.666667)
