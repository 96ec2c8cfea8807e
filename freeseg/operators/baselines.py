"""What freedom-based segmentation is compared with: mutual information, greedy lexicons, the reference and trivial splits."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import kernels
from ..sources.store import kept
from . import apply, evaluate, profile, segment

KEY = profile.KEY
#: A run without blanks and marks, or one mark.
REFERENCE = r"[^\s\p{Punct}]+|\p{Punct}"
#: Entries of a lexicon that may be broadcast at once, and how many such blocks tasks may hold, some 20 bytes an entry.
LEXICON_ROWS, LEXICON_BLOCKS = 2_000_000, 8


def reference_tokens(statements: DataFrame) -> DataFrame:
    """lang, stmt_id, tok_no, token: text cut at blanks, every mark set apart."""
    found = F.regexp_extract_all("text", F.lit(REFERENCE), F.lit(0))
    return statements.select(*KEY, F.posexplode(found).alias("no", "token")).select(*KEY, (F.col("no") + 1).alias("tok_no"), "token")


def reference_spans(statements: DataFrame) -> DataFrame:
    """lang, stmt_id, start, len, token of the reference tokens in their statements: with the blanks between them they make up the text."""
    found = F.regexp_extract_all("text", F.lit(REFERENCE + r"|\s+"), F.lit(0))
    every = statements.select(*KEY, F.posexplode(found).alias("tok_no", "token"))
    return evaluate.token_spans(every).where(F.col("token").rlike(r"^\S"))


def trivial_tokens(statements: DataFrame, kind: str) -> DataFrame:
    """lang, stmt_id, tok_no, token: "symbols", the whole "line", or a split at "spaces"."""
    parts = {"symbols": F.split("text", ""), "line": F.array("text"), "spaces": F.filter(F.split("text", " "), lambda x: x != "")}[kind]
    return statements.select(*KEY, F.posexplode(parts).alias("no", "token")).select(*KEY, (F.col("no") + 1).alias("tok_no"), "token")


def mutual_information(grams: DataFrame) -> DataFrame:
    """lang, pair, mi of neighbouring symbols: the logarithm to base 2 of how much likelier they are together than by chance."""
    one, two = grams.where("n = 1"), grams.where("n = 2")
    total = lambda g, name: F.broadcast(g.groupBy("lang").agg(F.sum("cnt").alias(name)))  # noqa: E731  a row for each language
    c = lambda name, as_: one.select("lang", F.col("gram").alias(name), F.col("cnt").alias(as_))
    pairs = two.select("lang", F.col("gram").alias("pair"), "cnt", F.left("gram", F.lit(1)).alias("x"), F.right("gram", F.lit(1)).alias("y"))
    all_ = pairs.join(c("x", "cx"), ["lang", "x"]).join(c("y", "cy"), ["lang", "y"]).join(total(one, "s1"), "lang").join(total(two, "s2"), "lang")
    mi = F.log2((F.col("cnt") / F.col("s2")) / ((F.col("cx") / F.col("s1")) * (F.col("cy") / F.col("s1"))))
    return all_.select("lang", "pair", F.round(mi, profile.DIGITS).alias("mi"))


def mi_gaps(statements: DataFrame, grams: DataFrame) -> DataFrame:
    """lang, stmt_id, gap, mi of the pair around each gap; null for a pair never seen."""
    pairs = F.regexp_extract_all("text", F.lit("(?s)(?=(.{2}))."), F.lit(1))
    each = statements.select(*KEY, F.posexplode(pairs).alias("gap", "pair")).withColumn("gap", F.col("gap") + 1)
    return each.join(mutual_information(grams), ["lang", "pair"], "left").select(*KEY, "gap", "mi")


def mi_breaks(statements: DataFrame, grams: DataFrame, cut: float = 1.0, variant: str = "threshold") -> DataFrame:
    """Greedy merging of the pair with the highest mutual information first, while it is at least `cut`. Scores of pairs don't change by merging, so what stays apart are the gaps below the cut ("threshold"). "mutual_best": a gap is closed only if it is the best one for the symbols of both sides; ties close both."""
    rows = mi_gaps(statements, grams)
    if variant == "threshold":
        return rows.where(F.col("mi").isNull() | (F.col("mi") < cut)).select(*KEY, "gap")
    at = Window.partitionBy(*KEY).orderBy("gap")
    low = F.lit(float("-inf"))
    mine = F.coalesce("mi", low)
    best = (mine >= F.coalesce(F.lag(mine).over(at), low)) & (mine >= F.coalesce(F.lead(mine).over(at), low))
    return rows.withColumn("open", ~best | F.col("mi").isNull()).where("open").select(*KEY, "gap")


def mi_tokens(statements: DataFrame, grams: DataFrame, cut: float = 1.0, variant: str = "threshold") -> DataFrame:
    """The tokens of a variant of `mi_breaks`: pairs are looked up in arrays as long as they are few enough to be broadcast, and joined otherwise."""
    held = apply.sliced(mutual_information(grams).select("lang", F.lit(2).alias("n"), F.col("pair").alias("w"), F.lit("f").alias("dir"), F.col("mi").alias("v")), "p")
    if held is None:
        return segment.tokens(statements, mi_breaks(statements, grams, cut, variant))
    pairs = statements.sparkSession.sparkContext.broadcast({lang: (s[2].keys, s[2].forward) for lang, s in held.items()})

    def score(lang: str, t: kernels.Texts) -> np.ndarray:
        keys, mi = pairs.value.get(lang, (np.zeros(0, np.uint64), np.zeros(0)))
        mine, own = kernels.gram_keys(t.points, 2), np.full(len(t.points), -np.inf)
        if len(keys) and len(mine):
            at = np.minimum(np.searchsorted(keys, mine), len(keys) - 1)
            own[:-1] = np.where(keys[at] == mine, mi[at], -np.inf)
        own[t.first + t.size - 1] = -np.inf
        if variant == "threshold":
            return (own < cut).astype(float)
        best = (own >= np.append(-np.inf, own[:-1])) & (own >= np.append(own[1:], -np.inf))
        return (~best | np.isneginf(own)).astype(float)

    return apply.token_rows(statements, {}, score=score)


def merged(t: kernels.Texts, merges) -> tuple[np.ndarray, list[str]]:
    """Texts as numbers of tokens with 0 after each text, and the token of each number, once pairs of tokens were merged everywhere, one merge after the other."""
    there = np.flatnonzero(np.bincount(t.points))
    number = np.zeros(int(there[-1]) + 1 if len(there) else 0, np.int64)
    number[there] = np.arange(1, len(there) + 1)
    names = ["", *map(chr, there.tolist())]
    of = {x: k for k, x in enumerate(names)}
    now = np.insert(number[t.points], np.cumsum(t.size), 0)
    for x, y in merges:
        if not (x in of and y in of):
            continue
        at = np.flatnonzero((now[:-1] == of[x]) & (now[1:] == of[y]))
        if x == y and len(at):  # of places in a row every other one
            begins = np.diff(at, prepend=-2) > 1
            at = at[(at - np.maximum.accumulate(np.where(begins, at, 0))) % 2 == 0]
        if len(at):
            if x + y not in of:
                of[x + y] = len(names)
                names.append(x + y)
            now[at] = of[x + y]
            now = np.delete(now, at + 1)
    return now, names


def counted(numbers: np.ndarray, below: int) -> tuple[np.ndarray, np.ndarray]:
    """The distinct ones of numbers that are smaller than `below`, and how often each occurs."""
    if below > 1 << 22:
        return np.unique(numbers, return_counts=True)
    found = np.bincount(numbers, minlength=1)
    there = np.flatnonzero(found)
    return there, found[there]


def merge_counts(lines: DataFrame, merges: dict[str, list[tuple[str, str]]]) -> DataFrame:
    """lang, x, y, c: how often each token (y is null) and each pair of neighbouring tokens occurs after the merges of its language. Batches are counted in arrays, so a row for each distinct pair of a batch is shuffled."""

    def run(batches):
        for batch in batches:
            for g, _, texts in apply.pieces(batch, "lang", "line"):
                now, names = merged(kernels.texts_of(texts), merges.get(g, ()))
                size, table = len(names), pa.array(names, pa.string())
                single = np.bincount(now, minlength=size)
                one = np.flatnonzero(single[1:]) + 1
                pairs = (now[:-1] * size + now[1:])[(now[:-1] > 0) & (now[1:] > 0)]
                two, many = counted(pairs, size * size)
                x = pa.concat_arrays([table.take(pa.array(one)), table.take(pa.array(two // size))])
                y = pa.concat_arrays([pa.nulls(len(one), pa.string()), table.take(pa.array(two % size))])
                yield pa.RecordBatch.from_arrays([pa.array([g] * len(x), pa.string()), x, y, pa.array(np.concatenate([single[one], many]).astype(np.int64))], ["lang", "x", "y", "c"])

    return lines.mapInArrow(run, "lang string, x string, y string, c long").groupBy("lang", "x", "y").agg(F.sum("c").alias("c"))


def merged_lines(lines: DataFrame, merges: dict[str, list[tuple[str, str]]]) -> DataFrame:
    """lang, toks: lines as arrays of tokens after the merges of their language; null for a null line."""

    def run(batches):
        for batch in batches:
            lists: list = [None if x is None else [] for x in batch.column("line").to_pylist()]
            for g, rows, texts in apply.pieces(batch, "lang", "line"):
                now, names = merged(kernels.texts_of(texts), merges.get(g, ()))
                toks, ends = [names[k] for k in now.tolist()], np.flatnonzero(now == 0).tolist()
                for i, a, b in zip(rows, [0, *(e + 1 for e in ends[:-1])], ends, strict=True):
                    lists[i] = toks[a:b]
            yield pa.RecordBatch.from_arrays([batch.column("lang"), pa.array(lists, pa.list_(pa.string()))], ["lang", "toks"])

    return lines.select("lang", "line").mapInArrow(run, "lang string, toks array<string>")


def mi_merges(lines: DataFrame, rounds: int, keep=kept, least: int = 2) -> tuple[list[tuple[str, str, str]], DataFrame]:
    """Re-estimated variant: in each round and language the pair of neighbouring tokens with the highest mutual information, of those that occur at least `least` times, is merged everywhere, and all is counted anew. Of equally informative pairs the more frequent comes first, then the smaller. Gives the merges (lang, x, y) and lines as token arrays. A round reads the lines once and makes the merges so far in arrays; `keep` writes its counts, a row for each distinct token and pair, and reads them back."""
    told = lines.select("lang", "line").where(F.col("lang").isNotNull())
    done: list[tuple[str, str, str]] = []
    merges: dict[str, list[tuple[str, str]]] = {}
    for _ in range(rounds):
        counts = keep(merge_counts(told, merges))
        one, two = counts.where("y is null").select("lang", "x", "c"), counts.where("y is not null")
        total = lambda t, name: F.broadcast(t.groupBy("lang").agg(F.sum("c").alias(name)))  # noqa: E731  a row for each language
        of = lambda name, as_: one.select("lang", F.col("x").alias(name), F.col("c").alias(as_))
        rated = two.where(F.col("c") >= least).join(of("x", "cx"), ["lang", "x"]).join(of("y", "cy"), ["lang", "y"]).join(total(one, "s1"), "lang").join(total(two, "s2"), "lang")
        mi = F.round(F.log2((F.col("c") / F.col("s2")) / ((F.col("cx") / F.col("s1")) * (F.col("cy") / F.col("s1")))), profile.DIGITS)
        best = rated.groupBy("lang").agg(F.min(F.struct((-mi).alias("mi"), (-F.col("c")).alias("c"), "x", "y")).alias("b")).select("lang", "b.x", "b.y")
        found = best.orderBy("lang").collect()  # a row for each language
        if not found:
            break
        done += [(r.lang, r.x, r.y) for r in found]
        merges = {g: [(x, y) for lang, x, y in done if lang == g] for g in {r[0] for r in done}}
    untold = lines.where(F.col("lang").isNull()).select("lang", F.split("line", "").alias("toks"))
    return done, merged_lines(told, merges).unionByName(untold)


def learn_lexicon(lines: DataFrame, least: int = 2) -> DataFrame:
    """lang, word, freq of the reference tokens of lines that occur at least `least` times."""
    words = lines.select("lang", F.explode(F.regexp_extract_all("line", F.lit(REFERENCE), F.lit(0))).alias("word"))
    return words.groupBy("lang", "word").agg(F.count("*").alias("freq")).where(F.col("freq") >= least)


def with_delimiters(lexicon: DataFrame, marks: str = " .,;:!?\"'()[]{}-", freq: int = 1) -> DataFrame:
    """The lexicon with delimiters as entries where it lacks them."""
    extra = lexicon.select("lang").distinct().select("lang", F.explode(F.array(*map(F.lit, marks))).alias("word"), F.lit(freq).cast("long").alias("freq"))
    return lexicon.unionByName(extra).groupBy("lang", "word").agg(F.max("freq").alias("freq"))


def without_words(lexicon: DataFrame, percent: int) -> DataFrame:
    """The lexicon without about so many percent of its words, chosen by the first byte of a digest of the word."""
    return lexicon.where(F.left(F.md5("word"), F.lit(2)) >= f"{first_byte(percent):02x}")


def first_byte(percent: int) -> int:
    """The least first byte of the digests of words that stay."""
    return round(256 * percent / 100)


def rank_of(by: str, alpha: float = 1.0):
    """How good an entry is, to be the next token, rounded so that engines agree; of equally good ones the longer is taken."""
    n = F.length("word")
    return {"length": n.cast("double"), "frequency": F.col("freq").cast("double"), "blend": F.round(F.pow(n.cast("double"), F.lit(alpha)) * F.ln(1 + F.col("freq")), profile.DIGITS)}[by]


def walked(t: kernels.Texts, step: np.ndarray) -> np.ndarray:
    """Where the tokens begin if a token of step[i] symbols begins at symbol i, from each text's first symbol on."""
    out, steps = [], step.tolist()
    for first, size in zip(t.first.tolist(), t.size.tolist(), strict=True):
        at, end = first, first + size
        while at < end:
            out.append(at)
            at += steps[at]
    return np.array(out, np.int64)


def lexicon_entries(lexicon: DataFrame, by: str, alpha: float) -> DataFrame:
    """lang, word, n, rank, byte: the entries, their lengths, how good they are, and the first byte of the word's digest."""
    each = lexicon.where(F.length("word") > 0).groupBy("lang", "word").agg(F.max("freq").alias("freq"))
    return each.select("lang", "word", F.length("word").alias("n"), rank_of(by, alpha).alias("rank"), F.conv(F.left(F.md5("word"), F.lit(2)), 16, 10).cast("int").alias("byte"))


def lexicon_blocks(entries: DataFrame, most: int, blocks: int) -> list | None:
    """Broadcasts of the entries by language and length, as sorted hashes, ranks and bytes; more than `most` are dealt into blocks by a hash of the word, which come to the driver one by one. None if that takes more than `blocks`."""
    rows = entries.limit(most + 1).toArrow() if blocks else None
    if rows is not None and rows.num_rows > most:
        rows, entries = None, kept(entries)
        number = -(-entries.count() // most)
        blocks = 0 if number > blocks else number
    if not blocks:
        return None
    parts = [rows] if rows is not None else (entries.where(F.pmod(F.xxhash64("word"), F.lit(blocks)) == k).toArrow() for k in range(blocks))
    out = []
    for part in parts:
        by_lang: dict[str, dict[int, tuple]] = {}
        for (lang, n), some in grouped(part):
            keys = kernels.string_hashes(some["word"].to_pylist())
            order = np.argsort(keys)
            by_lang.setdefault(lang, {})[n] = (keys[order], some["rank"].to_numpy()[order], some["byte"].to_numpy().astype(np.uint8)[order])
        out.append(entries.sparkSession.sparkContext.broadcast(by_lang))
    return out


def lexicon_steps(held: list, lang: str, t: kernels.Texts, bytes_: tuple[int, ...] = (0,)) -> list[np.ndarray]:
    """For each byte, how long the best entry at each symbol is, of those whose own byte is not below; 1 where there is none."""
    total, own = len(t.points), [h.value.get(lang, {}) for h in held]
    steps, best = [np.ones(total, np.int64) for _ in bytes_], [np.full(total, -np.inf) for _ in bytes_]
    left, spans = t.left, kernels.SpanHash(t.points)
    for n in sorted({n for o in own for n in o}):
        every = np.flatnonzero(left >= n)
        h = spans.of(every, every + n)
        for keys, rank, byte in (o[n] for o in own if n in o):
            at = np.minimum(np.searchsorted(keys, h), len(keys) - 1)
            hit = keys[at] == h
            start, at = every[hit], at[hit]
            for step, top, least in zip(steps, best, bytes_, strict=True):
                better = (rank[at] >= top[start]) & (byte[at] >= least)
                step[start[better]], top[start[better]] = n, rank[at[better]]
    return steps


def lexicon_tokens(statements: DataFrame, lexicon: DataFrame, by: str = "length", alpha: float = 1.0, most: int = LEXICON_ROWS, blocks: int = LEXICON_BLOCKS) -> DataFrame:
    """lang, stmt_id, tok_no, token: at each place the entry that is longest ("length"), most frequent ("frequency"), or best by length to the power alpha times the logarithm of one plus frequency ("blend"); ties go to the longer. A symbol that starts no entry is a token.

    The lexicon is broadcast as sorted hashes and ranks in up to `blocks` blocks of `most` entries; a larger one is joined with the spans of the statements."""
    entries = lexicon_entries(lexicon, by, alpha)
    held = lexicon_blocks(entries, most, blocks)
    if held is None:
        return lexicon_tokens_joined(statements, entries)

    def score(lang: str, t: kernels.Texts) -> np.ndarray:
        out = np.zeros(len(t.points))
        begins = walked(t, lexicon_steps(held, lang, t)[0])
        out[begins[begins > 0] - 1] = 1.0
        return out

    return apply.token_rows(statements, {}, score=score).drop("start", "len")


def missing_tokens(statements: DataFrame, lexicon: DataFrame, percents: tuple[int, ...], most: int = LEXICON_ROWS, blocks: int = LEXICON_BLOCKS) -> DataFrame:
    """lang, percent, token: the tokens by the longest entry at each place of a lexicon without so many percent of its words, see `without_words`, for each of some percents. Spans are looked up once in the whole lexicon."""
    held = lexicon_blocks(lexicon_entries(lexicon, "length", 1.0), most, blocks)
    if held is None:
        each = [lexicon_tokens_joined(statements, lexicon_entries(without_words(lexicon, p), "length", 1.0)).select("lang", F.lit(p).alias("percent"), "token") for p in percents]
        return reduce(DataFrame.unionByName, each)
    least = tuple(map(first_byte, percents))

    def run(batches):
        for batch in batches:
            for g, rows, texts in apply.pieces(batch, "lang", "text"):
                t = kernels.texts_of(texts)
                for percent, step in zip(percents, lexicon_steps(held, g, t, least), strict=True):
                    begins = walked(t, step)
                    of = np.searchsorted(t.first, begins, side="right") - 1
                    lang = batch.column("lang").take(pa.array(np.array(rows, np.int64)[of]))
                    yield pa.RecordBatch.from_arrays([lang, pa.array(np.full(len(begins), percent, np.int32)), kernels.token_array(texts, t, begins)], ["lang", "percent", "token"])

    return statements.select("lang", "text").mapInArrow(run, "lang string, percent int, token string")


def grouped(rows: pa.Table):
    """The rows of each language and length of entry."""
    rows = rows.sort_by([("lang", "ascending"), ("n", "ascending")])
    names = list(zip(rows["lang"].to_pylist(), rows["n"].to_pylist(), strict=True))
    at = 0
    while at < len(names):
        to = at
        while to < len(names) and names[to] == names[at]:
            to += 1
        yield names[at], rows.slice(at, to - at)
        at = to


def lexicon_tokens_joined(statements: DataFrame, entries: DataFrame) -> DataFrame:
    """As lexicon_tokens for a lexicon too large to broadcast: spans of the lengths that entries have are joined with the entries, and each statement is cut by the best lengths at its places. entries: lang, word, n, rank."""
    sizes = [r.n for r in entries.select("n").distinct().orderBy("n").collect()]  # lengths of words: a few dozen numbers
    found = F.array(*(F.regexp_extract_all("text", F.lit(rf"(?s)(?=(.{{{n}}}))."), F.lit(1)) for n in sizes))
    spans = statements.select(*KEY, F.explode(found).alias("ws")).select(*KEY, F.posexplode("ws").alias("at", "word"))
    best = spans.join(entries, ["lang", "word"]).groupBy(*KEY, "at").agg(F.max(F.struct("rank", "n")).alias("b"))
    steps = best.groupBy(*KEY).agg(F.collect_list(F.struct("at", F.col("b.n").alias("n"))).alias("steps"))
    both = statements.select(*KEY, "text").join(steps, list(KEY), "left")

    def run(batches):
        for batch in batches:
            starts = []
            for text, steps in zip(batch.column("text").to_pylist(), batch.column("steps").to_pylist(), strict=True):
                t = kernels.texts_of([text] if text else [])
                step = np.ones(len(t.points), np.int64)
                for s in steps or ():
                    step[s["at"]] = s["n"]
                starts.append(walked(t, step).tolist())
            yield pa.RecordBatch.from_arrays([batch.column("lang"), batch.column("stmt_id"), batch.column("text"), pa.array(starts, pa.list_(pa.int32()))], ["lang", "stmt_id", "text", "starts"])

    kind = {f.name: f.dataType.simpleString() for f in both.schema}
    cut = both.mapInArrow(run, f"lang string, stmt_id {kind['stmt_id']}, text string, starts array<int>")
    gaps = cut.select(*KEY, F.explode("starts").alias("gap")).where("gap > 0")
    return segment.tokens(statements, gaps).drop("start", "len")


def hybrid_breaks(freedom_breaks: DataFrame, lexicon_rows: DataFrame) -> DataFrame:
    """Breaks by freedom, but for those inside a lexicon token of two symbols or more. lexicon_rows: the tokens of `lexicon_tokens`, which make up the statements, so a break stays if a lexicon token ends there or if it lies in no longer one."""
    spans = evaluate.token_spans(lexicon_rows).where("len > 1")
    inside = spans.select(*KEY, F.explode(F.sequence(F.col("start"), F.col("start") + F.col("len") - 2)).alias("gap"))
    return freedom_breaks.join(inside, [*KEY, "gap"], "left_anti")


def hybrid_tokens(statements: DataFrame, freedom_tokens: DataFrame, lexicon_rows: DataFrame) -> DataFrame:
    """The tokens of the hybrid. freedom_tokens: with start, as `segment.run` gives them."""
    cuts = freedom_tokens.where("start > 1").select(*KEY, (F.col("start") - 1).alias("gap"))
    return segment.tokens(statements, hybrid_breaks(cuts, lexicon_rows))


def hybrid_run(statements: DataFrame, grams: DataFrame, config: segment.Config, lexicon: DataFrame, most: int = LEXICON_ROWS, blocks: int = LEXICON_BLOCKS) -> DataFrame:
    """The tokens of the hybrid, where a break by freedom stays if a token by the longest entries ends there too: in arrays if model and lexicon are few enough to be broadcast."""
    model = apply.slices(grams, config) if config.in_arrays else None
    held = lexicon_blocks(lexicon_entries(lexicon, "length", 1.0), most, blocks) if model is not None else None
    if held is None:
        return hybrid_tokens(statements, segment.run(statements, grams, config), lexicon_tokens(statements, lexicon))
    free = apply.scorer(statements.sparkSession.sparkContext.broadcast(model), config)

    def score(lang: str, t: kernels.Texts) -> np.ndarray:
        ends = np.zeros(len(t.points), bool)
        begins = walked(t, lexicon_steps(held, lang, t)[0])
        ends[begins[begins > 0] - 1] = True
        return (ends & (free(lang, t) > config.threshold)).astype(float)

    return apply.token_rows(statements, {}, score=score)


def p_tokens(statements: DataFrame, grams: DataFrame, offshoot: str = "raw", threshold: float = 0.4) -> DataFrame:
    """Segmentation by probability or an offshoot of it."""
    return segment.run(statements, grams, segment.Config("p", offshoot, (1,), 0.0, threshold))


def cp_tokens(statements: DataFrame, grams: DataFrame, offshoot: str = "raw", threshold: float = 0.4, kind: str = "symbol", rank: int = 1, rule: str = "threshold") -> DataFrame:
    """Segmentation by conditional probability or an offshoot of it, of the next symbol or ("gram") of the next gram of the same length; rule "local_max": at its local maxima."""
    return segment.run(statements, grams, segment.Config("cp", offshoot, (rank,), 0.0, threshold, kind=kind, rule=rule))
