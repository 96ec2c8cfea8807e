"""The experiment workloads over the given tables: each takes (spark, sf_dir) and returns a DataFrame.

Counts, profiles and tokens are those of all documents or of the whole benchmark; where F1 or precision is measured the
model learns from the documents that aren't held out, and the test set is the benchmark and every line of those that are.
"""

from __future__ import annotations

from collections import Counter

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baselines, compress, evaluate, model, profile, segment, tune
from ..shipping import ship
from ..sources import corpus
from ..sources.store import kept

#: The configuration that wins for text with spaces, and the one for text without.
SPACED = segment.Config("tf", "variance", (1,), 0.0001, 0.4)
UNSPACED = segment.Config("tf", "peak", (2,), 0.001, 0.05)
MI_CUT = 0.0
#: The part of the grid that w36 searches on the benchmark; w25-w28 search all of it on the whole test set.
SMALL_SETS = ((1,), (2,), (1, 2))
LIMITS = (0.0, *tune.THRESHOLDS)
SIZES = {"small": [1], "medium": [1, 2, 3], "all": [1, 2, 3, 4, 5, 6, 7, 8, 9]}
MISSING = (0, 5, 10, 20)
R = 9


def grams_of(spark: SparkSession, sf_dir: str, n_max: int) -> DataFrame:
    """Gram counts of all documents."""
    return model.count_grams(corpus.all_lines(spark, sf_dir), n_max)


def _grams(spark, sf_dir, n_max):
    """A model of all documents, saved: what uses it several times doesn't count again."""
    return kept(grams_of(spark, sf_dir, n_max))


def _trained(spark, sf_dir, n_max):
    """A model of the training documents, saved."""
    return kept(model.count_grams(corpus.train_lines(spark, sf_dir), n_max))


def w01_gram_counts(spark, sf_dir):
    return grams_of(spark, sf_dir, 3)


def w02_forward_edges(spark, sf_dir):
    return model.symbol_edges(grams_of(spark, sf_dir, 3), "f").drop("dir")


def w03_backward_edges(spark, sf_dir):
    return model.symbol_edges(grams_of(spark, sf_dir, 3), "b").drop("dir")


def w04_gram_gram_edges(spark, sf_dir):
    return model.wide_edges(grams_of(spark, sf_dir, 4), [1, 2])


def w05_freedom(spark, sf_dir):
    return model.both_ways(model.freedom(model.edges(grams_of(spark, sf_dir, 3))))


def w06_probability(spark, sf_dir):
    return model.probability(grams_of(spark, sf_dir, 2)).select("lang", "n", "gram", F.round("p", R).alias("p"))


def w07_conditional(spark, sf_dir):
    grams = _grams(spark, sf_dir, 3)
    return model.conditional(model.edges(grams), grams).select("lang", "n", "gram", "dir", "nbr", F.round("cp", R).alias("cp"))


def w08_compress_levels(spark, sf_dir):
    grams = _grams(spark, sf_dir, 3)
    return compress.parameter_count(grams.where("n < 3"), model.edges(grams))


def w09_blend_models(spark, sf_dir):
    docs = corpus.table(spark, sf_dir, "documents").select("lang", "doc_id", "text")
    lines = lambda takes: corpus.lines(corpus.bucket_share(docs, "doc_id", 10, takes), "text", "lang", "doc_id")
    blend = model.merge(*(model.count_grams(lines(t), 2) for t in ([0, 1, 2, 3], [4, 5, 6], [7, 8, 9])))
    whole = grams_of(spark, sf_dir, 2).withColumnRenamed("cnt", "whole")
    both = blend.join(whole, list(model.KEYS), "full_outer")
    differs = F.count_if(~F.col("cnt").eqNullSafe(F.col("whole")))
    return both.groupBy("lang", "n").agg(F.count("*").alias("grams"), F.sum("cnt").alias("total"), differs.alias("differing"))


def _profile(spark, sf_dir, base, ranks, kind="symbol"):
    grams = _grams(spark, sf_dir, max(ranks) + 1 if kind == "symbol" else 2 * max(ranks))
    return segment.base_profile(corpus.benchmark(spark, sf_dir), grams, base, ranks, kind=kind)


def _ways(rows: DataFrame, names: dict[str, str], value: str = "v", by=("stmt_id", "gap")) -> DataFrame:
    """by, and a column for each direction."""
    return rows.groupBy(*by).agg(*(F.max(F.when(F.col("dir") == d, F.round(value, R))).alias(c) for d, c in names.items()))


def w10_profile_tf(spark, sf_dir):
    p = kept(_profile(spark, sf_dir, "tf", [1]))
    return _ways(p, {"f": "tf_f", "b": "tf_b"}).join(_ways(profile.offshoot(p, "variance"), {"f": "dvf", "b": "dvb"}), ["stmt_id", "gap"])


def w11_profile_deriv_peak(spark, sf_dir):
    p = kept(_profile(spark, sf_dir, "tf", [1]))
    return _ways(profile.offshoot(p, "derivative"), {"f": "df_f", "b": "df_b"}).join(_ways(profile.offshoot(p, "peak"), {"f": "peak_f", "b": "peak_b"}), ["stmt_id", "gap"])


def _p_like(p: DataFrame) -> DataFrame:
    p = kept(p)
    out = _ways(p, {"f": "v_f", "b": "v_b"})
    for kind, short in (("variance", "dv"), ("derivative", "d")):
        out = out.join(_ways(profile.offshoot(p, kind), {"f": f"{short}_f", "b": f"{short}_b"}), ["stmt_id", "gap"])
    return out


def w12_profile_p(spark, sf_dir):
    return _p_like(_profile(spark, sf_dir, "p", [1]))


def w13_profile_cp(spark, sf_dir):
    return _p_like(_profile(spark, sf_dir, "cp", [2]))


def w14_profile_ranks(spark, sf_dir):
    p = profile.scaled(profile.offshoot(_profile(spark, sf_dir, "tf", [1, 2, 3]), "variance"))
    return _ways(p, {"f": "dvf", "b": "dvb"}, by=("n", "stmt_id", "gap"))


def w15_tokens_tf_var(spark, sf_dir):
    """All documents, segmented by what their own lines teach."""
    return segment.run(corpus.corpus_statements(spark, sf_dir), _grams(spark, sf_dir, 2), SPACED).drop("start", "len")


def w16_tokens_tf_peak(spark, sf_dir):
    """All documents without their blanks, segmented by what such lines teach."""
    st = corpus.strip_spaces(corpus.corpus_statements(spark, sf_dir)).where("text <> ''")
    return segment.run(st, kept(model.count_grams(st.select("lang", F.col("text").alias("line")), 3)), UNSPACED).drop("start", "len")


def _together(made: dict[str, DataFrame], name: str) -> DataFrame:
    """lang, token, and the key of each frame as a column, of the tokens that aren't blank."""
    out = None
    for key, toks in made.items():
        one = evaluate.solid(toks).select("lang", "token", F.lit(key).alias(name))
        out = one if out is None else out.unionByName(one)
    return out


def _for_each(ref: DataFrame, name: str, values) -> DataFrame:
    return ref.withColumn(name, F.explode(F.array(*map(F.lit, values))))


COMBINES = ("max", "mean", "forward", "backward")


def w17_tokens_mean_vs_max(spark, sf_dir):
    st, grams = kept(corpus.statements(spark, sf_dir)), _trained(spark, sf_dir, 2)
    toks = _together(segment.run_all(st, grams, {c: SPACED._replace(combine=c) for c in COMBINES}), "combine")
    return evaluate.f1(toks, _for_each(baselines.reference_tokens(st), "combine", COMBINES), "lang", "combine")


def w18_mi_tokens(spark, sf_dir):
    return baselines.mi_tokens(corpus.corpus_statements(spark, sf_dir), _grams(spark, sf_dir, 2), MI_CUT).drop("start", "len")


def _lexicon(spark, sf_dir):
    return kept(baselines.with_delimiters(baselines.learn_lexicon(corpus.train_lines(spark, sf_dir))))


def w19_lexicon_length(spark, sf_dir):
    return baselines.lexicon_tokens(corpus.statements(spark, sf_dir), _lexicon(spark, sf_dir), "length")


def w20_lexicon_freq(spark, sf_dir):
    return baselines.lexicon_tokens(corpus.statements(spark, sf_dir), _lexicon(spark, sf_dir), "frequency")


def w21_lexicon_blend(spark, sf_dir):
    return baselines.lexicon_tokens(corpus.statements(spark, sf_dir), _lexicon(spark, sf_dir), "blend")


def w22_reference_tokens(spark, sf_dir):
    return baselines.reference_tokens(corpus.corpus_statements(spark, sf_dir).unionByName(corpus.benchmark(spark, sf_dir)))


#: The methods that are configurations, beside those of `all_methods` that are not.
CONFIGS = {
    "tf_variance": SPACED, "tf_raw": SPACED._replace(offshoot="raw"), "tf_derivative": SPACED._replace(offshoot="derivative"), "tf_peak": SPACED._replace(offshoot="peak"),
    "p": segment.Config("p", "raw", (1,), 0.0), "p_variance": segment.Config("p", "variance", (1,), 0.0), "p_derivative": segment.Config("p", "derivative", (1,), 0.0),
    "cp": segment.Config("cp", "raw", (1,), 0.0), "cp_variance": segment.Config("cp", "variance", (1,), 0.0), "cp_derivative": segment.Config("cp", "derivative", (1,), 0.0),
    "tf_gram": segment.Config("tf", "variance", (2,), 0.0001, kind="gram"), "cp_gram": segment.Config("cp", "variance", (2,), 0.0, kind="gram"),
}
METHODS = (*CONFIGS, "mi", "lexicon", "spaces", "symbols", "line")


def all_methods(st: DataFrame, grams: DataFrame, lexicon: DataFrame) -> dict[str, DataFrame]:
    """The tokens of every method at its default configuration."""
    return segment.run_all(st, grams, CONFIGS) | {
        "mi": baselines.mi_tokens(st, grams, MI_CUT), "lexicon": baselines.lexicon_tokens(st, lexicon),
        **{kind: baselines.trivial_tokens(st, kind) for kind in ("spaces", "symbols", "line")},
    }


def w23_f1_by_method(spark, sf_dir):
    st = kept(corpus.statements(spark, sf_dir))
    toks = _together(all_methods(st, _trained(spark, sf_dir, 4), _lexicon(spark, sf_dir)), "method")
    return evaluate.f1(toks, _for_each(baselines.reference_tokens(st), "method", METHODS), "lang", "method")


def _precision(toks: DataFrame, ref: DataFrame, lex: DataFrame) -> DataFrame:
    raw = evaluate.lexicon_precision(toks, lex, "lang", "method").withColumn("lexicon", F.lit("learned"))
    return raw.unionByName(evaluate.lexicon_precision(toks, evaluate.corrected(lex, ref), "lang", "method").withColumn("lexicon", F.lit("corrected")))


def w24_lexicon_precision(spark, sf_dir):
    st, grams = kept(corpus.statements(spark, sf_dir)), _trained(spark, sf_dir, 2)
    lex, ref = _lexicon(spark, sf_dir), kept(baselines.reference_tokens(st))
    return _precision(kept(_together({"tf_variance": segment.run(st, grams, SPACED), "lexicon": baselines.lexicon_tokens(st, lex), "reference": ref}, "method")), ref, lex)


def _grid(spark, sf_dir, *by):
    return tune.grid_search(kept(corpus.statements(spark, sf_dir)), _trained(spark, sf_dir, 8), by=by)


def w25_grid_scores(spark, sf_dir):
    return _grid(spark, sf_dir)


def w26_heatmap(spark, sf_dir):
    return tune.heatmap(_grid(spark, sf_dir), LIMITS, "lang", "base", "theta")


def w27_best_config(spark, sf_dir):
    return tune.best(kept(_grid(spark, sf_dir))).select("lang", *tune.CELL, "f1")


def w28_half_split(spark, sf_dir):
    return tune.split_check(kept(_grid(spark, sf_dir, "half")))


def w29_corpus_size(spark, sf_dir):
    """Every share of the corpus is counted once; a size is the sum of its shares, and a model of its own name."""
    st, docs = kept(corpus.statements(spark, sf_dir)), corpus.train_documents(spark, sf_dir)
    good = corpus.table(spark, sf_dir, "labels").where("quality = 1").select("doc_id").distinct().withColumn("good", F.lit(1))
    part = F.concat_ws("|", "lang", (F.col("doc_id") % 10).cast("string"), F.coalesce("good", F.lit(0)).cast("string"))
    shares = kept(model.count_grams(corpus.lines(docs.join(good, "doc_id", "left").select(part.alias("lang"), "text"), "text", "lang"), 2))
    name = F.split("lang", "[|]")
    sizes = F.array(*(F.when(name[1].isin(list(map(str, takes))), F.lit(k)) for k, takes in SIZES.items()), F.when(name[2] == "1", F.lit("good")))
    of = lambda lang, size: F.concat_ws("|", lang, size)
    each = shares.withColumn("size", F.explode(F.filter(sizes, lambda x: x.isNotNull())))
    grams = kept(each.groupBy(of(name[0], "size").alias("lang"), "n", "gram").agg(F.sum("cnt").alias("cnt")))
    names = [*SIZES, "good"]
    toks = evaluate.solid(segment.run(_for_each(st, "size", names).withColumn("lang", of("lang", "size")).drop("size"), grams, SPACED))
    toks = toks.select(name[0].alias("lang"), name[1].alias("size"), "token")
    return evaluate.f1(toks, _for_each(baselines.reference_tokens(st), "size", names), "lang", "size")


def w30_missing_words(spark, sf_dir):
    """The statements are cut in one pass by one lexicon, whose words know at which percentages they are missing."""
    st = kept(corpus.statements(spark, sf_dir))
    toks = evaluate.solid(baselines.missing_tokens(st, _lexicon(spark, sf_dir), MISSING))
    return evaluate.f1(toks, _for_each(baselines.reference_tokens(st), "percent", MISSING), "lang", "percent")


def w31_html_lines(spark, sf_dir):
    return corpus.html_lines(corpus.table(spark, sf_dir, "pages"))


def _sequence_tokens(seq: DataFrame, entity: str, config: segment.Config) -> DataFrame:
    st = kept(seq.select(F.lit("seq").alias("lang"), F.col(entity).alias("stmt_id"), F.col("line").alias("text")))
    grams = kept(model.count_grams(st.select("lang", F.col("text").alias("line")), max(config.ranks) + 1))
    return segment.run(st, grams, config).select(F.col("stmt_id").alias(entity), "tok_no", "token")


EVENTS = segment.Config("tf", "peak", (2,), 0.0, 0.5)


def w32_events_segments(spark, sf_dir):
    return _sequence_tokens(corpus.event_sequences(spark, sf_dir), "user_id", EVENTS)


def w33_orders_segments(spark, sf_dir):
    seq = corpus.sequences(corpus.table(spark, sf_dir, "orders"), "o_custkey", ["o_orderdate", "o_orderkey"], F.left("o_orderstatus", F.lit(1)))
    return _sequence_tokens(seq, "o_custkey", EVENTS)


def w34_conversation_shift(spark, sf_dir):
    """The benchmark by a model of another genre: all conversations together, whose languages the table doesn't tell, are the corpus named `en` here."""
    st = kept(corpus.benchmark(spark, sf_dir))
    lines = corpus.lines(corpus.table(spark, sf_dir, "conversations").select(F.lit("en").alias("lang"), "text"), "text", "lang")
    return evaluate.f1(segment.run(st, kept(model.count_grams(lines, 2)), SPACED, False), baselines.reference_tokens(st))


def w35_errors(spark, sf_dir):
    st = kept(corpus.statements(spark, sf_dir))
    return evaluate.errors(segment.run(st, _trained(spark, sf_dir, 2), SPACED, False), baselines.reference_tokens(st))


def w36_grid_benchmark(spark, sf_dir):
    """The grid of w25 on the benchmark alone, for ranks 1 and 2: all base metrics, offshoots, levels and thresholds."""
    return tune.grid_search(kept(corpus.benchmark(spark, sf_dir)), _trained(spark, sf_dir, 3), sets=SMALL_SETS)


UNSPACED_METHODS = {"tf_peak": UNSPACED, "tf_variance": UNSPACED._replace(offshoot="variance"), "tf_derivative": UNSPACED._replace(offshoot="derivative")}


def _unspaced(spark, sf_dir):
    """Statements without blanks, the reference from before, and the tokens of each method; freedom learns from lines without blanks."""
    st, ref = corpus.unspaced(kept(corpus.statements(spark, sf_dir)))
    st, ref = kept(st), kept(ref)
    lines = corpus.strip_spaces(corpus.train_lines(spark, sf_dir), "line").where("line <> ''")
    grams, lex = kept(model.count_grams(lines, 3)), _lexicon(spark, sf_dir)
    made = segment.run_all(st, grams, UNSPACED_METHODS) | {"lexicon": baselines.lexicon_tokens(st, lex), "symbols": baselines.trivial_tokens(st, "symbols"), "line": baselines.trivial_tokens(st, "line")}
    return made, ref, lex


def w37_unspaced_f1(spark, sf_dir):
    """F1 on text without blanks against the tokens from before they were taken out."""
    made, ref, _ = _unspaced(spark, sf_dir)
    return evaluate.f1(_together(made, "method"), _for_each(ref, "method", tuple(made)), "lang", "method")


def w38_unspaced_precision(spark, sf_dir):
    """Precision of the words discovered in text without blanks, beside that of the reference."""
    made, ref, lex = _unspaced(spark, sf_dir)
    return _precision(kept(_together({**{k: made[k] for k in (*UNSPACED_METHODS, "lexicon")}, "reference": ref}, "method")), ref, lex)


def w39_summary(spark, sf_dir):
    """For each language with blanks, and without (named so): F1 of the freedom-based and the lexicon-based tokens, and the precision of discovered words, against the corrected lexicon, beside that of the reference."""
    st = kept(corpus.statements(spark, sf_dir))
    lex, ref, grams = _lexicon(spark, sf_dir), kept(baselines.reference_tokens(st)), _trained(spark, sf_dir, 2)
    spaced = {"freedom": segment.run(st, grams, SPACED), "lexicon": baselines.lexicon_tokens(st, lex)}
    bare, _, _ = _unspaced(spark, sf_dir)
    without = {"freedom": bare["tf_peak"], "lexicon": bare["lexicon"]}
    tag = lambda df: df.withColumn("lang", F.concat("lang", F.lit(" unspaced")))
    toks = kept(_together(spaced, "method").unionByName(tag(_together(without, "method"))))
    refs = kept(ref.unionByName(tag(ref)))
    fixed = evaluate.corrected(lex, ref)
    fixed = kept(fixed.unionByName(tag(fixed)))
    scores = evaluate.f1(toks, _for_each(refs, "method", tuple(spaced)), "lang", "method")
    return tune.summary(scores, evaluate.lexicon_precision(toks, fixed, "lang", "method"), evaluate.lexicon_precision(refs, fixed))


RULES = {"tf_local_max": SPACED._replace(offshoot="derivative", rule="local_max"), "cp_local_max": segment.Config("cp", "derivative", (2,), 0.0, 0.0, kind="gram", rule="local_max"), "tf_variance_model": SPACED._replace(scale="model"), "tf_variance_unscaled": SPACED._replace(scale="none", threshold=5.0), "tf_backoff": SPACED._replace(ranks=(2,), unseen="backoff")}


def w40_rules(spark, sf_dir):
    """F1 of other rules: local maxima of derivatives, values scaled by the model or not at all, and unseen grams taken for the next shorter ones; and of the mutual-best variant of mutual information and the hybrid with a lexicon. The tokens of a method are saved before the next one's are planned, so the driver holds the plan and the broadcasts of one at a time."""
    st, grams, lex = kept(corpus.statements(spark, sf_dir)), _trained(spark, sf_dir, 4), _lexicon(spark, sf_dir)
    methods = {name: lambda c=c: segment.run(st, grams, c) for name, c in RULES.items()}
    methods["mi_mutual_best"] = lambda: baselines.mi_tokens(st, grams, variant="mutual_best")
    methods["hybrid"] = lambda: baselines.hybrid_run(st, grams, SPACED, lex)
    made = {name: kept(evaluate.solid(toks()).select("lang", "token")) for name, toks in methods.items()}
    return evaluate.f1(_together(made, "method"), _for_each(baselines.reference_tokens(st), "method", tuple(made)), "lang", "method")


def w41_places(spark, sf_dir):
    """F1 on breaks and on whole tokens by their places in the statements."""
    st = kept(corpus.statements(spark, sf_dir))
    toks = kept(evaluate.solid(segment.run(st, _trained(spark, sf_dir, 2), SPACED)))
    ref = kept(baselines.reference_spans(st))
    gaps = lambda t: t.where("start > 1").select("lang", "stmt_id", (F.col("start") - 1).alias("gap")).union(t.select("lang", "stmt_id", (F.col("start") + F.col("len") - 1).alias("gap"))).distinct()
    return evaluate.span_f1(toks, ref).withColumn("of", F.lit("spans")).unionByName(evaluate.boundary_f1(gaps(toks), gaps(ref)).withColumn("of", F.lit("breaks")))


def w42_sweep(spark, sf_dir):
    """Every span of the benchmark that is a token for some threshold, with the thresholds for which it is."""
    from ..operators import apply

    held = apply.slices(_grams(spark, sf_dir, 2), SPACED)
    out = apply.swept(corpus.benchmark(spark, sf_dir), held, SPACED, "lang", "text", "stmt_id")
    return out.select("stmt_id", "start", "len", "token", F.when(F.col("low") > float("-inf"), F.col("low")).alias("low"), F.when(F.col("high") < float("inf"), F.col("high")).alias("high"))


def w43_model_cost(spark, sf_dir):
    return evaluate.model_cost(grams_of(spark, sf_dir, 3))


def w44_degrees(spark, sf_dir):
    """How many vertices of the graph have each number of edges out and in, for each language and rank."""
    grams = _grams(spark, sf_dir, 3)
    of = model.degree(grams.where("n < 3"), model.edges(grams))
    key = F.split("id", "\u0001")
    return of.groupBy(key[0].alias("lang"), key[1].cast("int").alias("n"), "out_degree", "in_degree").agg(F.count("*").alias("vertices"))


def w45_unsupervised_threshold(spark, sf_dir):
    """The threshold that is chosen without a reference for every configuration of w36, and the F1 that it gives."""
    return tune.select_unsupervised(kept(w36_grid_benchmark(spark, sf_dir)))


def w46_mi_merges(spark, sf_dir):
    """The first merges of re-estimated mutual information in every language of the corpus, in order."""
    merges, _ = baselines.mi_merges(corpus.all_lines(spark, sf_dir), MI_ROUNDS)
    numbered, count = [], Counter()
    for lang, x, y in merges:
        count[lang] += 1
        numbered.append((lang, count[lang], x, y))
    return spark.createDataFrame(numbered, "lang string, round int, x string, y string")


MI_ROUNDS = 3


def _shipped(f):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship(spark)
        return f(spark, sf_dir)

    run.__name__ = f.__name__
    return run


QUERIES = {name: _shipped(f) for name, f in sorted(globals().items()) if name[:1] == "w" and name[1:3].isdigit()}
