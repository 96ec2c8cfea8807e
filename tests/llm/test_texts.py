"""Language, word pieces, sentence pieces, fingerprints, lines, decontamination and toxicity, each against a plain version."""

import hashlib
from collections import Counter
import random
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from freeseg.llm import decontam, kernel, langid, line_dedup, merkle, pieces, queries, toxicity, wordpiece

from .helpers import LONG, documents, empty, odd_documents

VOCABULARY = queries.VOCABULARY


def split(t):
    return [w for w in "".join(c if c not in "\x09\x0a\x0b\x0c\x0d" else " " for c in t or "").split(" ") if w]


def test_words(spark):
    texts = [r.text for r in odd_documents(spark).collect()]
    w = kernel.words_of(pa.array(texts, pa.string()), "")
    words = w.distinct.to_pylist()
    assert [[words[c] for c in w.codes[a:b]] for a, b in zip(w.offsets[:-1], w.offsets[1:], strict=True)] == [split(t) for t in texts]


def test_batches_are_cut_to_size():
    batch = pa.RecordBatch.from_pydict({"t": ["x" * 10, None, "y" * 100, "", "z" * 5]})
    cut = list(kernel.cut_batches(iter([batch]), "t", 12))
    assert [b.num_rows for b in cut] == [2, 1, 2] and pa.Table.from_batches(cut).column("t").to_pylist() == batch.column("t").to_pylist()


# Language identification


def test_language_scores_equal_a_plain_naive_bayes(spark):
    texts = [("de", "der hund und die katze"), ("en", "the dog and the cat"), ("en", "a dog"), (None, "und")]
    docs = spark.createDataFrame([(k, t, g) for k, (g, t) in enumerate(texts)], "doc_id long, text string, lang string")
    m = langid.train(docs, buckets=512)
    assert m.languages == ["de", "en"]

    def grams(t):
        out = []
        for w in t.lower().split():
            _, b = langid.word_grams(pa.array([w]), buckets=512)
            out += b.tolist()
        return out

    counts = np.zeros((512, 2))
    for g, t in texts[:3]:
        np.add.at(counts[:, m.languages.index(g)], grams(t), 1)
    logp = np.log(counts + 0.5) - np.log(counts.sum(0) + 256)
    for t in ("die katze", "cat the", "zzz"):
        z = logp[grams(t)].sum(0) + np.log([1 / 3, 2 / 3])
        best, score = langid.score_texts(pa.array([t]), m)
        assert best[0] == z.argmax() and score[0] == pytest.approx(1 / np.exp(z - z.max()).sum())
    assert len(grams("ab")) == 2 + 3 + 2 + 1  # a, b; _a, ab, b_; _ab, ab_; _ab_


def test_language_of_held_out_documents(spark, sf):
    out = queries.op2_language_id(spark, sf).join(spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert np.mean([r.lang == r.lang_pred for r in out]) > 0.95
    assert all((zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in out)


def test_language_of_odd_rows(spark):
    docs = odd_documents(spark)
    m = langid.train(docs)
    out = {r.doc_id: r for r in langid.predict(docs, m).where("doc_id is not null").collect()}
    assert all(out[k].lang_pred == "und" and out[k].score == 0 for k in (0, 1, 2, 3, 4, 7, 8)) and out[5].lang_pred == "en"
    none = langid.train(empty(spark))
    assert {r.lang_pred for r in langid.predict(docs, none).collect()} == {"und"}
    assert langid.predict(empty(spark), m).count() == 0
    assert langid.keep_identified(docs, m).columns == docs.columns


# Word pieces


def greedy(word, first, inner):
    n = at = 0
    while at < len(word):
        pool = inner if at else first
        end = next((e for e in range(len(word), at, -1) if word[at:e] in pool), 0)
        if not end:
            return 0
        n, at = n + 1, end
    return n


def test_automaton_equals_greedy_matching():
    rng = np.random.default_rng(5)
    for _ in range(40):
        some = lambda n: {"".join(rng.choice(list("abc"), rng.integers(1, 5))) for _ in range(n)}
        first, inner = some(6), some(6)
        a = wordpiece.build(sorted(first), sorted(inner))
        for _ in range(60):
            word = "".join(rng.choice(list("abcd"), rng.integers(1, 12), p=[0.33, 0.33, 0.3, 0.04]))
            assert wordpiece.count_pieces(word, a) == greedy(word, first, inner), (word, first, inner)


def test_token_counts(spark):
    first, inner = wordpiece.read_vocabulary(VOCABULARY)
    f, i = set(first), set(inner)
    for r in wordpiece.token_counts(odd_documents(spark), first, inner).collect():
        parts = [p for w in split(r.text) for p in wordpiece.split_marks(w)]
        counts = [greedy(p, f, i) for p in parts] if r.text != LONG else None
        if counts is not None:
            assert (r.n_words, r.n_tokens, r.n_unknown) == (len(parts), sum(counts) + counts.count(0), counts.count(0))
    assert wordpiece.token_counts(empty(spark), first, inner).count() == 0


# Sentence pieces


def best_score(text, scores, low):
    top = [0.0] + [-np.inf] * len(text)
    for e in range(1, len(text) + 1):
        top[e] = top[e - 1] + low * len(text[e - 1].replace("▁", " ").encode())
        for a in range(max(0, e - 20), e):
            if text[a:e] in scores:
                top[e] = max(top[e], top[a] + scores[text[a:e]])
    return top[-1]


def test_viterbi_is_optimal_and_decodes():
    vocabulary = pieces.read_pieces(VOCABULARY)
    codec = pieces.Codec(vocabulary)
    scores = {p: s for p, s, kind in vocabulary if kind == "normal"}
    for text in ("the quick brown fox", "  two  blanks ", "Ünïcödé 中文 \U0001f600!", "a\nb\n\nc", "x" * 40, "tab\there"):
        ids = codec.encode(text).tolist()
        assert codec.decode(ids) == text
        got = sum(codec.byte_score if vocabulary[k][2] == "byte" else vocabulary[k][1] for k in ids)
        assert got == pytest.approx(best_score("▁" + text.replace(" ", "▁"), scores, codec.byte_score))


def test_chunks_give_what_the_whole_text_gives():
    codec = pieces.Codec(pieces.read_pieces(VOCABULARY))
    text = "some words,  more words\nand a line 中 end"
    assert codec.encode(text).tolist() == codec.best("▁" + text.replace(" ", "▁"))


def test_round_trip_of_odd_rows(spark):
    vocabulary = pieces.read_pieces(VOCABULARY)
    coded = pieces.encode(odd_documents(spark), vocabulary)
    assert coded.where("not decodes").isEmpty()
    back = pieces.decode(coded.select("doc_id", "piece_ids", F.col("text").alias("was")), vocabulary)
    assert all(r.text == (r.was or "").replace("▁", " ") for r in back.collect())
    assert pieces.encode(empty(spark), vocabulary).count() == 0


# Fingerprints


def test_edits_equal_a_plain_version(spark):
    texts = ["one two three\nfour five", "", "six", None, "seven eight nine ten eleven"]
    docs = documents(spark, texts)
    rows = sorted(merkle.compare_edits(docs).collect(), key=lambda r: r.doc_id)
    plain = [t or "" for t in texts]
    for k, r in enumerate(rows):
        n = len(plain[k]) // 2
        edited = plain[k][: len(plain[k]) - n] + plain[(k + 1) % len(plain)][:n]
        assert r.n_chars == len(plain[k]) and r.edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        assert r.edited_fingerprint == merkle.trees([edited])[0].fingerprint and r.near_edited == merkle.likeness(r.fingerprint, r.edited_fingerprint)
    assert rows[1].near_edited == 1.0


@pytest.mark.parametrize("buckets", [1, 3, 50])
def test_every_row_meets_the_next(spark, buckets):
    docs = documents(spark, [f"text number {k}" for k in range(37)], 5).select((F.col("doc_id") * 7 % 41).alias("doc_id"), "text")
    table = merkle.in_order(docs, buckets=buckets).mapInArrow(lambda it: (pa.RecordBatch.from_pydict({"a": [i for i, _ in rows], "b": [*(t for _, t in rows[1:]), after]}) for rows, after in merkle.neighbours(it)), "a long, b string").collect()
    text = {r.doc_id: r.text for r in docs.collect()}
    order = sorted(text)
    got = {r.a: r.b for r in table}
    assert got == {i: text[order[(k + 1) % len(order)]] for k, i in enumerate(order)}


def test_differences_locate_the_edited_paragraph():
    lines = [f"paragraph number {k} has some words of its own" for k in range(30)]
    other = [*lines]
    other[17] = "this one is new"
    a, b = (merkle.trees(["\n".join(x)])[0].fingerprint for x in (lines, other))
    tree = merkle.parse(a)
    assert tree.fingerprint == a and len(tree.sections) > 2
    flat = [(i, j) for i, x in enumerate(tree.sections) for j in range(len(x.paragraphs))]
    assert [flat.index(d) for d in merkle.differences(a, b)] == [17]
    assert 0.8 < merkle.likeness(a, b) < 1 and merkle.likeness(a, a) == 1


def plain_likeness(a: merkle.Tree, b: merkle.Tree) -> float:
    """Leaves under equal sections, then under equal paragraphs, then equal ones, over all."""
    if a.root == b.root:
        return 1.0
    at = "words" if a.short and b.short else "pieces"
    cut = lambda p: [getattr(p, at)[k : k + 3] for k in range(0, len(getattr(p, at)), 3)]
    left, right = list(a.sections), list(b.sections)
    shared = 0
    for x in list(left):
        for y in right:
            if x.digest == y.digest:
                left.remove(x)
                right.remove(y)
                shared += sum(len(cut(p)) for p in x.paragraphs)
                break
    here, there = [p for x in left for p in x.paragraphs], [p for x in right for p in x.paragraphs]
    for x in list(here):
        for y in there:
            if x.digest == y.digest:
                here.remove(x)
                there.remove(y)
                shared += len(cut(x))
                break
    shared += (Counter(w for p in here for w in cut(p)) & Counter(w for p in there for w in cut(p))).total()
    total = sum(len(cut(p)) for t in (a, b) for x in t.sections for p in x.paragraphs)
    return 2 * shared / total if total else 0.0


def test_likeness_descends_the_tree():
    rng = random.Random(4)
    line = lambda: " ".join(rng.choice("abcdefgh") * rng.randint(1, 3) for _ in range(rng.randint(0, 14)))
    texts = ["\n".join(line() for _ in range(rng.randint(1, 30))) for _ in range(40)]
    texts += [t[: len(t) // 2] + rng.choice(texts)[: len(t) // 2] for t in texts] + ["", "\n\n", "one"]
    made = merkle.trees(texts)
    for a, b in [(rng.choice(made), rng.choice(made)) for _ in range(300)] + list(zip(made, made[40:], strict=False)):
        got = merkle.compare(a, b)
        assert got.likeness == pytest.approx(plain_likeness(a, b)) and merkle.likeness(a.fingerprint, b.fingerprint) == got.likeness
        assert (got.likeness == 1.0) == (a.fingerprint == b.fingerprint) or got.likeness < 1.0 or a.root != b.root
        assert all(i < len(a.sections) and j < len(a.sections[i].paragraphs) for i, j in got.differs)
    assert all(merkle.parse(t.fingerprint) == t for t in made)


def test_half_of_a_short_text_is_seen(spark):
    rows = merkle.compare_edits(documents(spark, ["one two three four five six seven eight", "nothing of this kind is in the other text at all"])).orderBy("doc_id").collect()
    assert 0.4 <= rows[0].near_edited <= 0.6 and rows[0].near_next == 0.0 and rows[0].edited_paragraphs == [0]


def test_fingerprints_of_odd_rows(spark):
    docs = odd_documents(spark)
    rows = merkle.compare_edits(docs).collect()
    assert len(rows) == docs.count() and merkle.compare_edits(empty(spark)).count() == 0
    by = {}
    for r in merkle.fingerprints(docs).collect():
        by.setdefault(r.text or "", set()).add(r.fingerprint)
    assert all(len(v) == 1 for v in by.values()) and len({x for v in by.values() for x in v}) == len(by)


# Lines


def test_lines_equal_a_plain_version(spark):
    page = "page {} of the very long manual with nine words"
    texts = [f"alpha beta gamma delta epsilon zeta eta theta iota\nown line number a\n{page.format(k)}\nshort line here" for k in range(4)] + ["unrelated text in a line", None, ""]
    for most in (1000, -1):
        rows = {r.doc_id: r for r in line_dedup.dedup_lines(documents(spark, texts), most=most).collect()}
        assert rows[0].dropped_lines == [] and rows[0].text == texts[0]
        for k in (1, 2, 3):
            assert rows[k].dropped_lines == [0, 2] and rows[k].text == "own line number a\nshort line here"
        assert rows[4].text == texts[4] and rows[5].text is None and rows[6].text == ""


def test_templates_generalise_words_that_differ(spark):
    base = "please contact our friendly support team about order {} before the end of this month"
    texts = [base.format(w) for w in ("alpha", "beta", "gamma")]
    assert [r.dropped_lines for r in line_dedup.dedup_lines(documents(spark, texts)).orderBy("doc_id").collect()] == [[], [0], [0]]


def test_short_lines_need_many_documents(spark):
    few, many = ["all rights reserved"] * 3, ["all rights reserved"] * 12
    texts = lambda xs: [f"{x}\nown text {chr(97 + k)}" for k, x in enumerate(xs)]
    count = lambda xs: sum(len(r.dropped_lines) for r in line_dedup.dedup_lines(documents(spark, texts(xs))).collect())
    assert count(few) == 0 and count(many) == 11


def test_documents_without_a_word_left_go(spark):
    line = "a line of eight words is here now"
    left = line_dedup.clean(documents(spark, [line, line, line + "\nmore", ""]))
    assert {r.doc_id: r.text for r in left.collect()} == {0: line, 2: "more", 3: ""}


def test_lines_of_odd_rows(spark):
    docs = odd_documents(spark)
    out = line_dedup.dedup_lines(docs)
    assert out.count() == docs.count() and line_dedup.clean(docs).columns == docs.columns
    assert line_dedup.dedup_lines(empty(spark)).count() == 0


def test_large_leaf_is_read_in_parts(spark, monkeypatch):
    monkeypatch.setattr(line_dedup, "MOST_FORMS", 5)
    texts = [f"same three words then {chr(97 + k)}{chr(98 + k)} and more of its own {chr(99 + k)} text" for k in range(20)] * 2
    rows = line_dedup.dedup_lines(documents(spark, texts), similar=1.0).orderBy("doc_id").collect()
    assert [len(r.dropped_lines) for r in rows] == [0] * 20 + [1] * 20


def test_a_large_leaf_is_one_group(spark):
    """Lines that differ by the word after the depth only are one template, however many other lines their leaf has."""
    name = lambda k: "".join(chr(97 + int(d)) for d in str(k))
    other = "\n".join(f"same three words q{name(k)} r{name(7 * k)} s{name(11 * k)} t{name(13 * k)} u{name(17 * k)} v{name(19 * k)}" for k in range(4000))
    texts = [f"same three words {x} signed this page for us" for x in ("anna", "ben", "carl", "dora", "emil", "fritz", "gina", "hans", "ida", "jan", "kim", "lea")]
    rows = line_dedup.dedup_lines(documents(spark, [other, *texts])).orderBy("doc_id").collect()
    assert [len(r.dropped_lines) for r in rows] == [0, 0] + [1] * 11


@pytest.mark.parametrize("n", [4, 5, 8, 11, 20])
def test_templates_by_index_are_those_of_a_scan(monkeypatch, n):
    rng = np.random.default_rng(n)
    bodies = rng.integers(0, 4, (12, n)).astype(np.uint16)[rng.integers(0, 12, 400)]
    for similar in (0.5, 0.8, 1.0):
        some = np.where(rng.random(bodies.shape) < 0.12, rng.integers(0, 6, bodies.shape), bodies).astype(np.uint16)
        some[:, 0] = rng.integers(0, 2)
        monkeypatch.setattr(line_dedup, "MOST_FORMS", 10**6)
        scan = line_dedup.cluster(list(some), similar)
        monkeypatch.setattr(line_dedup, "MOST_FORMS", 1)
        assert line_dedup.cluster(list(some), similar) == scan


# Decontamination

ITEM = "A train leaves Berlin at 9 and travels 120 km in 3 hours while another train leaves later. How fast does the train from Berlin go?"


def items(spark, texts):
    return spark.createDataFrame(list(enumerate(texts)), "item_id long, text string")


def test_found_with_other_slots(spark):
    other = ITEM.replace("Berlin", "Madrid").replace("120", "450").replace(" 9 ", " 7 ")
    mixed = ITEM.replace("from Berlin", "from Paris")
    far = "A train leaves and nothing of the rest of the item is in this text at all, which has words of its own."
    docs = documents(spark, [f"before it {ITEM} and after", f"x y {other} z", mixed, far, None, "", ITEM.upper() + "%%%"])
    rows = {r.doc_id: r for r in decontam.scan(docs, items(spark, [ITEM, "tiny"])).collect()}
    assert rows[0].item_ids == [0] and not rows[0].reparameterised
    assert rows[1].item_ids == [0] and rows[1].reparameterised
    assert [rows[k].item_ids for k in (2, 3, 4, 5)] == [[]] * 4
    left = decontam.clean(docs, items(spark, [ITEM]))
    assert 0 not in {r.doc_id for r in left.collect()} and left.columns == docs.columns


def test_windows_equal_plain_slices():
    c = decontam.canonical(pa.array(["one two three four", "a b", "", None, "two three four five"]))
    at, h = decontam.windows(c, 3)
    assert len(at) == 4 and h[1] == h[2] and len(set(h.tolist())) == 3


def test_every_planted_item_is_found(spark, sf):
    bench = {r.item_id: r.text for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()}
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    want = {i: {k for k, x in bench.items() if x in t} for i, t in texts.items()}
    got = {r.doc_id: set(r.item_ids) for r in queries.op10_decontamination(spark, sf).collect()}
    assert all(want[i] <= got[i] for i in want)
    assert sum(bool(got[i]) for i in want if not want[i]) <= 0.02 * len(want)


def test_blocks_of_items_and_odd_rows(spark, monkeypatch):
    monkeypatch.setattr(decontam, "BLOCK_BYTES", 50)
    blocks = list(decontam.item_blocks(items(spark, [ITEM, "another item of six words here", None]), "item_id", "text", 50))
    assert sorted(x for ids, _ in blocks for x in ids) == [0, 1] and len(blocks) > 1
    docs = odd_documents(spark)
    assert decontam.scan(docs, items(spark, [])).where("size(item_ids) > 0").isEmpty()
    assert decontam.scan(docs, items(spark, ["line line line line", ""])).count() == docs.count()
    assert decontam.scan(empty(spark), items(spark, [ITEM])).count() == 0


def test_found_with_names_at_sentence_starts_and_free_numbers_and_in_long_quotations(spark):
    tom = "Tom has 3 apples. Tom buys 5 more apples. How many apples does Tom have now?"
    twos = "a farmer has 2 white cows and 2 black cows and sells some of them at the old market"
    long = " ".join(f"part{chr(97 + k // 26)}{chr(97 + k % 26)}" for k in range(60))
    ann = tom.replace("Tom", "Ann").replace("3", "8").replace("5", "4")
    wrong = "Ann has 3 apples. Bob buys 5 more apples. How many apples does Eve have now?"
    docs = documents(spark, [f"So it goes. {ann} That is all.", twos.replace("2 white", "3 white").replace("2 black", "5 black"), "x y " + " ".join(long.split()[20:50]) + " z", " ".join(long.split()[20:40]), wrong])
    rows = {r.doc_id: r for r in decontam.scan(docs, items(spark, [tom, twos, long])).collect()}
    assert [rows[k].item_ids for k in range(5)] == [[0], [1], [2], [], []]
    assert rows[0].reparameterised and rows[1].reparameterised and not rows[2].reparameterised


# Toxicity


def test_toxicity_of_held_out_documents(spark, sf):
    big = sf.replace("0.001", "0.1")
    out = queries.op9_toxicity(spark, big).join(spark.read.parquet(f"{big}/labels.parquet").select("doc_id", "toxic"), "doc_id").where("held_out").collect()
    pos, neg = [r.score for r in out if r.toxic], [r.score for r in out if not r.toxic]
    auc = np.mean([(p > n) + 0.5 * (p == n) for p in pos for n in neg])
    right = np.mean([r.predicted == r.toxic for r in out])
    assert auc > 0.9 and right > 0.9


def test_risk_estimate_stays_non_negative_with_hidden_positives():
    rng = np.random.default_rng(2)
    clean = lambda: np.unique(rng.integers(10, 200, 30))
    toxic = lambda: np.unique(np.append(clean(), rng.integers(0, 5, 2)))
    m = toxicity.fit([toxic() for _ in range(60)], [toxic() if k % 5 == 0 else clean() for k in range(400)], 0.2)
    score = lambda x: 1 / (1 + np.exp(-(m.weights[x].sum() + m.bias)))
    assert np.mean([score(toxic()) >= 0.5 for _ in range(100)]) > 0.9 and np.mean([score(clean()) < 0.5 for _ in range(100)]) > 0.9


def test_toxicity_of_odd_rows(spark):
    docs = odd_documents(spark)
    labels = spark.createDataFrame([(9, 1), (9, 1), (12, None), (5, 0), (None, 1)], "doc_id long, toxic int")
    out = toxicity.predict(docs, toxicity.train(docs, labels)).collect()
    assert len(out) == docs.count() and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.5) for r in out)
    none = toxicity.train(empty(spark), labels)
    assert {r.score for r in toxicity.predict(docs, none).collect()} == {0.0}
    assert toxicity.predict(empty(spark), none).count() == 0
