"""Language-model scores of whole texts: causal self-attention over subword ids, mixed with the corpus's word counts.

All is learned from every training text. Counts of words, of subword pieces, of the pieces around a piece (for the classes)
and of pieces after a piece are distributed sums of tables of a fixed size. The attention weights are fitted in numpy: the
texts' pieces lie in units of about STEPS batches of windows or more; after STEPS steps on one of them, each unit fits the weights to a part of its windows,
the results are averaged, and the next of ROUNDS goes on from there, so that after the last each window was used. Texts
too few for two units are fitted on the driver, several times over until there are STEPS steps. The model
predicts a piece in two steps: a class from the attention over up to CONTEXT + STRIDE pieces before, then the piece in its
class by its count after the piece before, backed off to its corpus count. Texts are scored in overlapping windows: each window scores STRIDE pieces and sees CONTEXT pieces before
them, so each piece is scored once; windows are batched and masked. How texts are dealt into units depends on the number of
shuffle partitions, and so, slightly, do the weights.

A word's probability is a mixture of that of its pieces and of its share of the training tokens; a text's is the mean over
the mixtures with the parts in MIXED. `base_score` is the add-one unigram model over words.

Texts are dealt into blocks by a hash and read once: a block's words are cut, hashed and spelled, and what scoring needs of
them is kept in packed arrays, so no text is moved or spelled again. A block sends its distinct words, by 64-bit hash, to be
counted, in arrays by range of hashes, and gets back the counts of its own words only, in the order of their hashes, so the
vocabulary is never on one machine.

Nulls and odd input: a null text is empty and consists of its end only. Rows without an id are held-out or not by the
empty text's checksum, as `learn` says. Repeated rows count and are scored as often as they occur. With nothing to learn
from all pieces are equally likely. Whitespace other than the separators of words is part of words.
"""

from __future__ import annotations

import pickle
from itertools import chain
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .kernel import cut_batches, hash_strings, ranges, release, released, segment_sum, words_of
from .tables import keep

CONTEXT, STRIDE, SIZE, CLASSES, FREQUENT = 8, 24, 16, 64, 30
PREVIOUS, BACK_OFF, MIXED = 256, 10.0, (0.1, 0.3, 0.6, 0.9)
STEPS, BATCH, RATE, SEED, ROUNDS, SINCE = 1000, 96, 0.02, 7, 4, 0.6
BLOCK_BYTES, WORDS, WINDOWS = 12 << 20, 200_000, 512
SPELLED = 200_000
START, END = 1, 2


class Model(NamedTuple):
    embed: np.ndarray  # by piece id
    place: np.ndarray  # by place in a window
    query: np.ndarray
    key: np.ndarray
    out: np.ndarray  # of (piece, attended) to classes
    bias: np.ndarray
    cls: np.ndarray  # class by piece id
    prev: np.ndarray  # group by piece id, for a piece that stands before another
    within: np.ndarray  # log probability of a piece in its class, by the group of the piece before


def windows_of(lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For sequences of these lengths, laid end to end: of each window its sequence and its first scored place there."""
    n = -(-lengths // STRIDE)
    return np.repeat(np.arange(len(lengths)), n), ranges(np.zeros(len(n), np.int64), n) * STRIDE


#: The largest exponent of a place that a scored place sees, and of one that it doesn't.
MOST = np.where(np.arange(CONTEXT + STRIDE) <= np.arange(CONTEXT, CONTEXT + STRIDE)[:, None], 30, -1e9).astype(np.float32)
LEAST = np.float32(1e-30)


class Laid(NamedTuple):
    """Sequences end to end, cut into windows. `ids` and `target` have a row for each place: what a window that begins there reads, and what it scores."""

    first: np.ndarray  # place of each window's first scored piece
    before: np.ndarray  # how many pieces its sequence has before that
    left: np.ndarray  # and from there on
    ids: np.ndarray
    target: np.ndarray


def laid(inputs: np.ndarray, target: np.ndarray, lengths: np.ndarray) -> Laid:
    """Windows over pieces that follow `inputs`; target: what is to be predicted at each place."""
    seq, at = windows_of(lengths)
    first = (np.cumsum(lengths) - lengths)[seq] + at
    ids = np.concatenate([np.full(CONTEXT, START, inputs.dtype), inputs, np.full(STRIDE, START, inputs.dtype)])
    target = np.concatenate([target, np.zeros(STRIDE, target.dtype)])
    view = np.lib.stride_tricks.sliding_window_view
    return Laid(first, at, lengths[seq] - at, view(ids, CONTEXT + STRIDE), view(target, STRIDE))


PLACES = np.arange(-CONTEXT, STRIDE)


def gathered(w: Laid, pick) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Input ids of the picked windows, which places are inside the sequence, what the scored places are to predict, and each window's first scored place."""
    first, left = w.first[pick], w.left[pick]
    inside = (PLACES >= -w.before[pick][:, None]) & (PLACES < left[:, None])
    ids = w.ids[first]
    ids[~inside] = START
    return ids, inside, w.target[first], first


ONES = {n: np.ones((n, 1), np.float32) for n in (CONTEXT + STRIDE, CLASSES)}


def forward(m: Model, ids: np.ndarray, inside: np.ndarray):
    """Class logits of the scored places of windows, and what the backward pass needs. Exponents are limited, so no maximum is sought."""
    n = len(ids)
    x = np.take(m.embed, ids, axis=0, mode="clip")  # without a check of each id, which are all there
    x += m.place
    # A column of ones makes the bias part of the product.
    both = np.ones((n, STRIDE, 2 * SIZE + 1), np.float32)
    both[..., :SIZE] = x[:, CONTEXT:]
    flat = both.reshape(-1, 2 * SIZE + 1)
    # Products with a shared matrix are one product of all rows; query and key meet nowhere but in their product.
    q = (flat[:, :SIZE] @ (m.query @ m.key.T)).reshape(n, STRIDE, SIZE)
    # The second half of these rows is the backward pass's.
    pairs = np.empty((n, 2 * STRIDE, CONTEXT + STRIDE), np.float32)
    s = np.matmul(q, x.transpose(0, 2, 1), out=pairs[:, :STRIDE])
    np.minimum(s, MOST, out=s)
    # Places after the end are hidden by the order already, those before the beginning are all the context of first windows.
    s[np.flatnonzero(~inside[:, 0]), :, :CONTEXT] = -1e9
    np.exp(s, out=s)
    total = np.maximum(np.matmul(s, ONES[CONTEXT + STRIDE]), LEAST)
    np.divide(np.matmul(s, x), total, out=both[..., SIZE:-1])
    logits = flat @ np.concatenate([m.out, m.bias[None]])
    np.clip(logits, -60, 60, out=logits)
    return logits, (x, q, pairs, total, both)


def log_probs(m: Model, sequence: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Natural log probability of each piece of sequences laid end to end, each given those before it."""
    out = np.zeros(len(sequence), np.float64)
    if not len(sequence):
        return out
    inputs = inputs_of(sequence, lengths)
    w = laid(inputs, m.cls.astype(np.int16)[sequence], lengths)
    for a in range(0, len(w.first), WINDOWS):
        ids, inside, target, first = gathered(w, slice(a, a + WINDOWS))
        logits, _ = forward(m, ids, inside)
        chosen = logits[np.arange(len(logits)), target.ravel()]
        np.exp(logits, out=logits)
        scored = inside[:, CONTEXT:]
        out[(first[:, None] + np.arange(STRIDE))[scored]] = (chosen - np.log(logits @ ONES[CLASSES])[:, 0])[scored.ravel()]
    return out + m.within[m.prev[inputs], sequence]


def inputs_of(sequence: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """The piece before each piece of sequences laid end to end, START before the first of a sequence."""
    inputs = np.empty_like(sequence)
    inputs[1:] = sequence[:-1]
    inputs[(np.cumsum(lengths) - lengths)[lengths > 0]] = START
    return inputs


def buckets_of(counts: np.ndarray) -> np.ndarray:
    """Which of 64 sorts of neighbour a piece is: the most frequent are alone."""
    size = len(counts)
    out = FREQUENT + np.arange(size) % 34
    top = np.lexsort((np.arange(size), -counts))[:FREQUENT]
    out[top] = np.arange(len(top))
    return out


def neighbours(inputs: np.ndarray, sequence: np.ndarray, bucket: np.ndarray) -> np.ndarray:
    """How often each piece (column) has a neighbour of each sort: 64 rows for those before it, 64 for those after it."""
    size = len(bucket)
    before = np.bincount(bucket[inputs] * size + sequence, minlength=64 * size)
    return np.concatenate([before, np.bincount(bucket[sequence] * size + inputs, minlength=64 * size)]).reshape(128, size)


def transitions(inputs: np.ndarray, sequence: np.ndarray, prev: np.ndarray) -> np.ndarray:
    """How often each piece (column) comes after each group of pieces (row)."""
    return np.bincount(prev[inputs] * len(prev) + sequence, minlength=PREVIOUS * len(prev)).reshape(PREVIOUS, len(prev))


def classes_of(around: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """A class for each piece id: the most frequent are alone, the others are grouped by their neighbours, and those in no training text make one class."""
    size = len(counts)
    order = np.lexsort((np.arange(size), -counts))
    out = np.full(size, CLASSES - 1)
    top = order[:FREQUENT][counts[order[:FREQUENT]] > 0]
    out[top] = np.arange(len(top))
    rest = order[FREQUENT:][counts[order[FREQUENT:]] > 0]
    groups = CLASSES - 1 - FREQUENT
    if len(rest):
        v = np.log1p(around[:, rest].T).astype(np.float32)
        v /= np.linalg.norm(v, axis=1, keepdims=True) + 1e-9
        centres = v[:groups].copy()
        for _ in range(8):
            near = (v @ centres.T).argmax(1)
            for g in np.unique(near):
                c = v[near == g].sum(0)
                centres[g] = c / (np.linalg.norm(c) + 1e-9)
        out[rest] = FREQUENT + near
    return out.astype(np.int64)


def previous_of(counts: np.ndarray, cls: np.ndarray) -> np.ndarray:
    """The pieces most often before others are groups of their own, the others are grouped by class."""
    half = PREVIOUS // 2
    often = counts.copy()
    often[START], often[END] = counts[END], 0
    prev = half + cls % half
    top = np.lexsort((np.arange(len(cls)), -often))[:half]
    prev[top] = np.arange(len(top))
    return prev


def untrained(counts: np.ndarray, cls: np.ndarray, prev: np.ndarray, after: np.ndarray, seed: int) -> Model:
    """A model with all counts in it, and attention weights as they are before any step."""
    rng, size, f = np.random.default_rng(seed), len(counts), np.float32
    mass = counts + 0.5
    alone = mass / np.bincount(cls, mass, CLASSES)[cls]
    within = np.empty((PREVIOUS, size), f)
    for g in range(PREVIOUS):
        within[g] = np.log((after[g] + BACK_OFF * alone) / (np.bincount(cls, after[g], CLASSES) + BACK_OFF)[cls])
    bias = np.log(np.bincount(cls, mass, CLASSES) / mass.sum() + 1e-6).astype(f) if counts.any() else np.zeros(CLASSES, f)
    return Model(
        rng.normal(0, 0.3, (size, SIZE)).astype(f), rng.normal(0, 0.1, (CONTEXT + STRIDE, SIZE)).astype(f), rng.normal(0, 0.3, (SIZE, SIZE)).astype(f),
        rng.normal(0, 0.3, (SIZE, SIZE)).astype(f), np.zeros((2 * SIZE, CLASSES), f), bias, cls, prev, within,
    )


WEIGHTS = ("embed", "place", "query", "key", "out", "bias")


def gradients(m: Model, ids: np.ndarray, inside: np.ndarray, target: np.ndarray) -> tuple[np.ndarray, dict[str, np.ndarray]]:
    """Of the mean loss over the scored places of windows: the pieces whose embeddings it depends on, and the gradients of these embeddings and of the other weights."""
    n, f = len(ids), np.float32
    logits, (x, q, pairs, total, both) = forward(m, ids, inside)
    s, d_s, flat = pairs[:, :STRIDE], pairs[:, STRIDE:], both.reshape(-1, 2 * SIZE + 1)
    g = np.exp(logits, out=logits)
    scored = inside[:, CONTEXT:].reshape(-1, 1)
    share = scored / f(max(1, np.count_nonzero(scored)))
    g *= share / (g @ ONES[CLASSES])
    g.reshape(-1)[np.arange(0, g.size, CLASSES) + target.ravel()] -= share[:, 0]
    d_both = (g @ m.out.T).reshape(n, STRIDE, 2 * SIZE)
    # What comes back from the weighted mean and from the weights: of both the sum over places is one product.
    values = np.empty((n, 2 * STRIDE, SIZE), f)
    d_o, values[:, STRIDE:] = values[:, :STRIDE], q
    np.divide(d_both[..., SIZE:], total, out=d_o)  # so the weights in s need not be divided
    np.matmul(d_o, x.transpose(0, 2, 1), out=d_s)
    d_s -= np.einsum("ijk,ijk->ij", d_o, both[..., SIZE:-1])[..., None]
    d_s *= s
    d_x = np.matmul(pairs.transpose(0, 2, 1), values)
    r = np.matmul(d_s, x).reshape(-1, SIZE)
    joint = flat[:, :SIZE].T @ r  # of the product of query and key
    own = (r @ (m.key @ m.query.T)).reshape(n, STRIDE, SIZE)
    own += d_both[..., :SIZE]
    d_x[:, CONTEXT:] += own  # d_x is zero outside the sequence: nothing is scored there, and nothing sees it
    # Rows of a piece are put side by side and added up, two numbers at once. Ids below 2^16 are sorted by their digits.
    flat_ids = ids.ravel()
    by_piece = np.argsort(flat_ids.astype(np.uint16) if len(m.embed) <= 1 << 16 else flat_ids, kind="stable")
    sorted_ids = flat_ids[by_piece]
    first_of = np.append(0, 1 + np.flatnonzero(sorted_ids[1:] != sorted_ids[:-1]))
    embed = np.add.reduceat(np.take(d_x.reshape(-1, SIZE), by_piece, axis=0, mode="clip").view(np.complex64), first_of, axis=0).view(f)
    ends = (g.T @ flat).T
    place = (np.ones((1, n), f) @ d_x.reshape(n, -1)).reshape(m.place.shape)
    return sorted_ids[first_of], {"embed": embed, "place": place, "query": joint @ m.key, "key": joint.T @ m.query, "out": ends[:-1], "bias": ends[-1]}


def train(m: Model, sequence: np.ndarray, lengths: np.ndarray, order: np.ndarray, since: float = 0.0, until: float = 1.0) -> Model:
    """m after steps of BATCH windows each, in the given order; since and until: the shares of all the training that are done before and after, as the rate falls."""
    f, small = np.float32, WEIGHTS[1:]
    w = laid(inputs_of(sequence, lengths), m.cls.astype(np.int16)[sequence], lengths)
    steps = -(-len(order) // BATCH)
    # All weights but the embeddings lie in one row, with their two means in the next rows; the means of an embedding are one row.
    sizes = np.cumsum([getattr(m, k).size for k in small])
    rest = np.zeros((3, sizes[-1]), f)
    rest[0] = np.concatenate([getattr(m, k).ravel() for k in small])
    means = np.zeros((len(m.embed), 2, SIZE), f)
    m = m._replace(embed=m.embed.copy(), **{k: part.reshape(getattr(m, k).shape) for k, part in zip(small, np.split(rest[0], sizes[:-1]), strict=True)})

    def moved(p, a, b, d, t):
        a *= f(0.9)
        a += f(0.1) * d
        b *= f(0.99)
        b += f(0.01) * d * d
        p -= f(rate / (1 - 0.9**t)) * a / (np.sqrt(b / f(1 - 0.99**t)) + f(1e-7))

    for t in range(1, steps + 1):
        ids, inside, target, _ = gathered(w, order[(t - 1) * BATCH : t * BATCH])
        used, d = gradients(m, ids, inside, target)
        rate = RATE * (1 - 0.9 * (since + (until - since) * t / steps))
        moved(*rest, np.concatenate([d[k].ravel() for k in small]), t)
        own, mean = (np.take(a, used, axis=0, mode="clip") for a in (m.embed, means))  # only the embeddings of pieces in the batch move
        moved(own, mean[:, 0], mean[:, 1], d["embed"], t)
        m.embed[used], means[used] = own, mean
    return m._replace(**{k: getattr(m, k).copy() for k in WEIGHTS})


def passes(windows: int, most: int, rng: np.random.Generator) -> np.ndarray:
    """`most` window numbers: each window as often as any other, or once more."""
    return np.concatenate([np.zeros(0, np.int64), *(rng.permutation(windows) for _ in range(-(-most // windows) if windows else 0))])[:most]


def with_mean(m: Model, counts: np.ndarray) -> Model:
    """Pieces in no training text have the mean embedding of the others."""
    seen = counts > 0
    seen[START] = True
    return m._replace(embed=np.where(seen[:, None], m.embed, m.embed[seen].mean(0)).astype(np.float32))


def fit(sequences: list[np.ndarray], counts: np.ndarray, steps: int = STEPS, seed: int = SEED) -> Model:
    """Fits a model to sequences of piece ids at hand; counts: of every piece in them."""
    lengths = np.array([len(s) for s in sequences], np.int64)
    sequence = np.concatenate([*sequences, np.zeros(0, np.int64)]).astype(np.int64)
    inputs = inputs_of(sequence, lengths)
    cls = classes_of(neighbours(inputs, sequence, buckets_of(counts)), counts)
    prev = previous_of(counts, cls)
    m = untrained(counts, cls, prev, transitions(inputs, sequence, prev), seed)
    if not len(sequence):
        return m
    order = passes(int((-(-lengths // STRIDE)).sum()), steps * BATCH, np.random.default_rng(seed))
    return with_mean(train(m, sequence, lengths, order), counts)


class Coder:
    """Piece ids of words, each with the blank before it. A worker keeps the first SPELLED words' ids from task to task, since frequent words are in every block."""

    known: dict[str, bytes] = {}
    proto: bytes | None = None

    def __init__(self, proto: bytes):
        import sentencepiece

        self.sp = sentencepiece.SentencePieceProcessor(model_proto=proto)
        if Coder.proto != proto:
            Coder.known, Coder.proto = {}, proto
        self.known = Coder.known

    def words(self, words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """All words' ids end to end, and where each word's begin; one place more at the end."""
        words = words.to_pylist()
        coded = list(map(self.known.get, words))
        new = [k for k, c in enumerate(coded) if c is None]
        spelled = self.sp.encode([words[k] for k in new], num_threads=1)
        flat = np.fromiter(chain.from_iterable(spelled), np.int32, sum(map(len, spelled))).tobytes()
        at = 0
        for k, c in zip(new, spelled, strict=True):
            coded[k], at = flat[at : at + 4 * len(c)], at + 4 * len(c)
        for k in new[: max(0, SPELLED - len(self.known))]:
            if len(words[k]) <= 100:
                self.known[words[k]] = coded[k]
        size = np.fromiter(map(len, coded), np.int64, len(coded)) // 4
        return np.frombuffer(b"".join(coded), np.int32).astype(np.int64), np.concatenate([[0], np.cumsum(size)])


def with_ends(offsets: np.ndarray, codes: np.ndarray, end: int) -> tuple[np.ndarray, np.ndarray]:
    """Words with the code of the end after each text's."""
    return offsets + np.arange(len(offsets)), np.insert(codes, offsets[1:], end)


def piece_stream(offsets, codes, ids, begin) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Piece ids of texts end to end, the pieces of each word, the pieces of each text."""
    ids, begin = np.append(ids, np.array(END, ids.dtype)), np.append(begin, len(ids) + 1)
    offsets, codes = with_ends(offsets, codes, len(begin) - 2)
    size = np.diff(begin)[codes]
    return ids[ranges(begin[:-1][codes], size)], size, segment_sum(size, offsets)


def mixtures(spelled: np.ndarray, share: np.ndarray) -> list[np.ndarray]:
    """Log probabilities of words by each of MIXED, from that of their pieces and their share of the training tokens."""
    e, low = np.exp(spelled), np.flatnonzero(spelled < -600)
    out = [np.log(p * e + (1 - p) * share) for p in MIXED]
    for p, logs in zip(MIXED, out, strict=True):  # where nothing would be left of e
        logs[low] = np.logaddexp(spelled[low] + np.log(p), np.log(share[low]) + np.log1p(-p))
    return out


class Totals(NamedTuple):
    tokens: int  # training tokens, ends too
    types: int  # distinct ones
    texts: int  # training texts, the count of the end


def in_blocks(docs: DataFrame, learn: Column, id_col: str, text: str) -> DataFrame:
    """block, blocks, id, learn, t: docs dealt into blocks of about BLOCK_BYTES of text; blocks: how many there are."""
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(learn, F.lit(False)).alias("learn"), F.coalesce(F.col(text).cast("string"), F.lit("")).alias("t"))
    size = rows.agg(F.coalesce(F.sum(F.octet_length("t").cast("long")), F.lit(0)).alias("n")).first().n
    blocks = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-size // BLOCK_BYTES))
    return rows.withColumn("block", F.pmod(F.xxhash64("id", "t"), F.lit(blocks)).cast("int")).withColumn("blocks", F.lit(blocks)).repartition(blocks, "block")


def pack(*arrays: np.ndarray) -> bytes:
    """Arrays of integers, compressed by planes of their bytes."""
    planes = lambda a: np.ascontiguousarray(a).view(np.uint8).reshape(len(a), a.itemsize).T.tobytes()
    return pickle.dumps([(a.dtype.str, len(a), pa.compress(planes(a), "zstd", asbytes=True)) for a in arrays])


def unpack(packed: bytes) -> list[np.ndarray]:
    out = []
    for kind, n, z in pickle.loads(packed):
        width = np.dtype(kind).itemsize
        planes = np.frombuffer(pa.decompress(z, decompressed_size=n * width, codec="zstd", asbytes=True), np.uint8)
        out.append(np.ascontiguousarray(planes.reshape(width, n).T).reshape(-1).view(kind))
    return out


def gather(blocks: DataFrame, proto) -> DataFrame:
    """kind, block, key, c, s, n, w: of each block its distinct words by range of hashes (kind 0; key: the range; n: their hashes in order and counts in training texts), its pieces (kind 1; n: with their counts in training texts), the pieces of these texts end to end (kind 2, in s; c: how many windows), and all that its texts are scored by (kind 3, in w; see `scored_from`)."""

    def count(table: pa.Table) -> pa.Table:
        coder, block, ranges_of = Coder(proto.value), table.column("block")[0].as_py(), table.column("blocks")[0].as_py()
        ranges_of = max(min(ranges_of, 64), ranges_of // 8)
        keys, counts, pieces, streams, windows, texts = [], [], None, [], [], []
        table = table.sort_by([("id", "ascending"), ("t", "ascending")])  # the order of rows in a block is not fixed otherwise
        for batch in cut_batches(table.combine_chunks().to_batches(), "t", 2 * BLOCK_BYTES):
            w = words_of(batch.column("t"))
            learn = batch.column("learn").to_numpy(zero_copy_only=False)
            c = np.bincount(w.codes[np.repeat(learn, np.diff(w.offsets))], minlength=len(w.distinct))
            ids, begin = coder.words(w.distinct)
            ids = ids.astype(unit_type(coder.sp.get_piece_size()))
            got = np.bincount(ids, np.repeat(c, np.diff(begin)), coder.sp.get_piece_size()).astype(np.int64)
            got[END] += learn.sum()
            pieces = got if pieces is None else pieces + got
            there = np.bincount(w.codes, minlength=len(w.distinct)) > 0
            keys.append(hash_strings(w.distinct)[there])
            counts.append(c[there])
            whole = (w.codes.astype(np.int32), np.diff(w.offsets), ids, np.diff(begin), batch.column("id").fill_null(0).to_numpy(), batch.column("id").is_valid().cast(pa.int8()).to_numpy())
            texts.append((batch.num_rows, there, pack(*whole)))
            parts, windows_here, row = [], 0, 0
            while row < batch.num_rows:
                to = max(row + 1, int(np.searchsorted(w.offsets, w.offsets[row] + WORDS, side="right")) - 1)
                size, mine = np.diff(w.offsets[row : to + 1]), learn[row:to]
                own = w.codes[w.offsets[row] : w.offsets[to]][np.repeat(mine, size)]
                stream, _, lengths = piece_stream(np.concatenate([[0], np.cumsum(size[mine])]), own, ids, begin)
                parts.append(stream.tobytes())
                windows_here += int((-(-lengths // STRIDE)).sum())
                row = to
            streams.append(b"".join(parts))
            windows.append(windows_here)
        key, at = np.unique(np.concatenate(keys), return_inverse=True)
        c = np.bincount(at, np.concatenate(counts), len(key)).astype(np.int64)
        bounds = np.searchsorted((key >> np.uint64(32)) * np.uint64(ranges_of) >> np.uint64(32), np.arange(ranges_of + 1, dtype=np.uint64))
        rows = [(0, r, b - a, None, pack(key[a:b], c[a:b]), None) for r, (a, b) in enumerate(zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)) if b > a]
        some = np.flatnonzero(pieces)
        rows.append((1, 0, len(some), None, pack(some, pieces[some]), None))
        rows += [(2, k, n, stream, None, None) for k, (n, stream) in enumerate(zip(windows, streams, strict=True))]
        done = 0
        for k, (n, there, packed) in enumerate(texts):
            place = np.zeros(len(there), np.int32)
            place[there] = at[done : done + there.sum()]
            done += there.sum()
            rows.append((3, k, n, None, None, pickle.dumps((pack(place), packed))))
        release()
        kind, k, c, s, n, w = zip(*rows, strict=True)
        return pa.table({"kind": pa.array(kind, pa.int8()), "block": pa.array([block] * len(rows), pa.int32()), "key": pa.array(k, pa.int64()), "c": pa.array(c, pa.int64()), "s": pa.array(s, pa.binary()), "n": pa.array(n, pa.binary()), "w": pa.array(w, pa.binary())})

    return blocks.groupBy("block").applyInArrow(count, "kind byte, block int, key long, c long, s binary, n binary, w binary")


def scored_from(w: bytes) -> tuple[np.ndarray, ...]:
    """Of texts that were gathered at once: the place of each distinct word's hash among those of the block, each word's code, how many words a text has, the pieces of the distinct words, how many each has, the texts' ids, and whether there is one."""
    place, packed = pickle.loads(w)
    return (*unpack(place), *unpack(packed))


def counted_words(found: DataFrame) -> DataFrame:
    """block, part, n, v, w: for each block and range of hashes the counts in all training texts of the block's words, in the order of their hashes (w). Rows of block -1 have a range's training tokens (n) and how many distinct ones there are (v)."""

    def add(table: pa.Table) -> pa.Table:
        both = [unpack(n) for n in table.column("n").to_pylist()]
        key, at = np.unique(np.concatenate([k for k, _ in both]), return_inverse=True)
        c = np.zeros(len(key), np.int64)
        np.add.at(c, at, np.concatenate([n for _, n in both]))
        ends = np.cumsum([len(k) for k, _ in both])
        packed = [pack(x) for x in np.split(c[at], ends[:-1])]
        rows, part = len(both) + 1, table.column("key")[0].as_py()
        release()
        return pa.table({
            "block": pa.array([*table.column("block").to_pylist(), -1], pa.int32()), "part": pa.array([part] * rows, pa.int64()),
            "n": pa.array([0] * (rows - 1) + [int(c.sum())], pa.int64()), "v": pa.array([0] * (rows - 1) + [int((c > 0).sum())], pa.int64()), "w": pa.array([*packed, None], pa.binary()),
        })

    return found.where("kind = 0").select("key", "block", "n").groupBy("key").applyInArrow(add, "block int, part long, n long, v long, w binary")


def unit_type(size: int) -> str:
    """How pieces of a vocabulary of this size are kept."""
    return "<u2" if size <= 1 << 16 else "<i4"


def unit_of(s: bytes, size: int) -> tuple[np.ndarray, np.ndarray]:
    """The pieces of a unit's texts and the length of each text; END is the last piece of a text and nowhere else."""
    sequence = np.frombuffer(s, unit_type(size))
    return sequence, np.diff(np.flatnonzero(sequence == END), prepend=-1)


def summed(units: DataFrame, table_of) -> dict[int, np.ndarray]:
    """The sums over all units (block, key, s) of table_of(units of a task), rows of numbers by their place. The tables have a fixed size; a task adds up its own, and rows meet one by one."""

    @released
    def own(batches):
        rows = table_of((r["block"], r["key"], r["s"]) for batch in batches for r in batch.select(["block", "key", "s"]).to_pylist())
        for k, row in enumerate(rows):
            v = row.astype(np.float64)
            if v.any():
                yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([len(v)], pa.int32()), pa.array([pa.compress(v.tobytes(), "zstd", asbytes=True)], pa.binary())], ["k", "n", "v"])

    def unpacked(n, v):
        return np.frombuffer(pa.decompress(v, decompressed_size=8 * n, codec="zstd", asbytes=True), np.float64)

    def add(table):
        total = 0
        for n, v in sorted(zip(table.column("n").to_pylist(), table.column("v").to_pylist(), strict=True)):
            total = total + unpacked(n, v)
        return pa.table({"k": table.column("k")[:1], "n": table.column("n")[:1], "v": pa.array([pa.compress(total.tobytes(), "zstd", asbytes=True)], pa.binary())})

    shape = "k int, n int, v binary"
    return {r.k: unpacked(r.n, bytes(r.v)) for r in units.mapInArrow(own, shape).groupBy("k").applyInArrow(add, shape).collect()}  # as many rows as the table has


def counted(units: DataFrame, count, rows: int, size: int) -> np.ndarray:
    """The sum of count(inputs, sequence) over all units, a table of rows by pieces."""

    def table_of(some):
        total = None
        for _, _, s in some:
            sequence, lengths = unit_of(s, size)
            got = count(inputs_of(sequence, lengths), sequence)
            total = got if total is None else np.add(total, got, out=total)
        return () if total is None else total

    out = np.zeros((rows, size), np.float32 if rows > 128 else np.float64)
    for k, row in summed(units, table_of).items():
        out[k] = row
    return out


def counted_pieces(found: DataFrame, size: int) -> np.ndarray:
    """How often each piece is in training texts."""

    def table_of(some):
        total = np.zeros((1, size))
        for _, _, n in some:
            pieces, c = unpack(n)
            total[0, pieces] += c
        return total

    return summed(found.where("kind = 1").select("block", "key", F.col("n").alias("s")), table_of).get(0, np.zeros(size))


def train_units(m: Model, units: DataFrame, counts: np.ndarray) -> Model:
    """m fitted to all units: in each round each unit goes on from the mean of the round before, with other windows. A piece's embedding is a mean by its number of places. STEPS steps on one unit come first, since means of weights that lie far apart are worth little."""
    sc, size = units.sparkSession.sparkContext, len(counts)
    at = units.agg(F.min(F.struct("block", "key")).alias("u")).first().u
    sequence, lengths = unit_of(bytes(units.where((F.col("block") == at.block) & (F.col("key") == at.key)).first().s), size)
    m = train(m, sequence, lengths, passes(int((-(-lengths // STRIDE)).sum()), STEPS * BATCH, np.random.default_rng(SEED)))
    for r in range(ROUNDS):
        now = sc.broadcast(m._replace(within=np.zeros((0, 0), np.float32)))

        def table_of(some, r=r, now=now):
            total = np.zeros((SIZE + 2, max(size, 1 + sum(getattr(now.value, k).size for k in WEIGHTS[1:]))))
            for block, key, s in some:
                sequence, lengths = unit_of(s, size)
                order = np.random.default_rng((SEED, block, key)).permutation(int((-(-lengths // STRIDE)).sum()))[r::ROUNDS]
                if not len(order):
                    continue
                got = train(now.value, sequence, lengths, order, SINCE + (1 - SINCE) * r / ROUNDS, SINCE + (1 - SINCE) * (r + 1) / ROUNDS)
                often = np.bincount(inputs_of(sequence, lengths), minlength=size)
                total[:SIZE, :size] += got.embed.T * often
                total[SIZE, :size] += often
                rest = np.concatenate([[1.0], *(getattr(got, k).ravel() for k in WEIGHTS[1:])])
                total[SIZE + 1, : len(rest)] += len(order) * rest
            return total

        found = summed(units, table_of)
        if SIZE + 1 not in found:  # no unit had a window left
            continue
        often, rest, at = found[SIZE][:size], found[SIZE + 1], 1
        embed = np.stack([found[j][:size] if j in found else np.zeros(size) for j in range(SIZE)], 1) / np.maximum(often, 1)[:, None]
        new = {"embed": np.where(often[:, None] > 0, embed, m.embed).astype(np.float32)}
        for k in WEIGHTS[1:]:
            was = getattr(m, k)
            new[k] = (rest[at : at + was.size] / rest[0]).astype(np.float32).reshape(was.shape)
            at += was.size
        m = m._replace(**new)
    return m


def learned(found: DataFrame, counts: np.ndarray) -> Model:
    """The model of all training texts; found: what gather gives, kept, counts: of every piece in them."""
    units = found.where("kind = 2 and c > 0").select("block", "key", "c", "s")
    has = units.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("windows"), F.count("*").alias("n")).first()
    groups = has.windows // (STEPS * BATCH)
    if groups < 2:  # few enough for the driver
        parts = [unit_of(bytes(r.s), len(counts)) for r in units.orderBy("block", "key").collect()]
        return fit([x for sequence, lengths in parts for x in np.split(sequence, np.cumsum(lengths)[:-1])], counts)
    if groups < has.n:

        def one(table: pa.Table) -> pa.Table:
            table = table.sort_by([("block", "ascending"), ("key", "ascending")])
            return pa.table({"block": table.column("g")[:1], "key": pa.array([0], pa.int64()), "s": pa.array([b"".join(table.column("s").to_pylist())], pa.binary())})

        units = keep(units.select((F.col("block") % groups).cast("int").alias("g"), "block", "key", "s").groupBy("g").applyInArrow(one, "block int, key long, s binary"))
    size, bucket = len(counts), buckets_of(counts)
    cls = classes_of(counted(units, lambda i, s: neighbours(i, s, bucket), 128, size), counts)
    prev = previous_of(counts, cls)
    m = untrained(counts, cls, prev, counted(units, lambda i, s: transitions(i, s, prev), PREVIOUS, size), SEED)
    return with_mean(train_units(m, units, counts), counts)


def score(docs: DataFrame, learn: Column, model_proto: bytes, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """id, n_tokens, n_known, train_tokens, base_score, score, n_pieces of every row of docs, learning from those where `learn` holds."""
    sc = docs.sparkSession.sparkContext
    proto = sc.broadcast(model_proto)
    blocks = in_blocks(docs, learn, id_col, text)
    found = keep(gather(blocks, proto))
    counts = keep(counted_words(found))
    coder = Coder(model_proto)
    piece_counts = counted_pieces(found, coder.sp.get_piece_size())
    words = counts.where("block < 0").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.coalesce(F.sum("v"), F.lit(0)).alias("v")).first()
    ends = int(piece_counts[END])
    totals = Totals(words.n + ends, words.v + (ends > 0), ends)
    held = sc.broadcast((learned(found, piece_counts), totals))

    def run(table: pa.Table, known: pa.Table) -> pa.Table:
        model, n = held.value
        parts = sorted(zip(known.column("part").to_pylist(), known.column("w").to_pylist(), strict=True))
        c_of = np.concatenate([*(unpack(w)[0] for _, w in parts), np.zeros(1, np.int64)])  # one more for words that aren't there
        under, out = n.tokens + n.types + 1, []
        for _, w in sorted(zip(table.column("key").to_pylist(), table.column("w").to_pylist(), strict=True)):
            place, codes_of, words, ids, size_of, doc, valid = scored_from(w)
            c, begin, at = np.append(c_of[place], n.texts), np.append(0, np.cumsum(size_of)), np.append(0, np.cumsum(words))
            share, base = np.maximum(c, 1e-300) / max(n.tokens, 1), np.log10((c + 1) / under)
            row = 0
            # Pieces are scored for some texts at a time.
            while row < len(words):
                to = max(row + 1, int(np.searchsorted(at, at[row] + WORDS, side="right")) - 1)
                part, own = at[row : to + 1] - at[row], codes_of[at[row] : at[to]]
                offsets, codes = with_ends(part, own, len(place))
                stream, size, lengths = piece_stream(part, own, ids, begin)
                spelled = segment_sum(log_probs(model, stream, lengths), np.concatenate([[0], np.cumsum(size)]))
                parts = [segment_sum(p, offsets) for p in mixtures(spelled, share[codes])]
                mixed = np.logaddexp.reduce(parts) - np.log(len(MIXED))
                out.append([pa.array(doc[row:to], mask=valid[row:to] == 0), np.diff(offsets), segment_sum((c > 0).astype(np.int64)[codes], offsets), np.full(to - row, n.tokens), segment_sum(base[codes], offsets), mixed / np.log(10), lengths])
                row = to
        return pa.concat_tables(pa.table([pa.array(x) for x in o], schema=RESULT) for o in out)

    def guarded(table: pa.Table, known: pa.Table) -> pa.Table:
        try:
            return run(table, known) if table.num_rows else RESULT.empty_table()
        finally:
            release()

    texts, own = found.where("kind = 3").select("block", "key", "w"), counts.where("block >= 0").select("block", "part", "w")
    return texts.groupBy("block").cogroup(own.groupBy("block")).applyInArrow(guarded, "id long, n_tokens long, n_known long, train_tokens long, base_score double, score double, n_pieces long")


RESULT = pa.schema([("id", pa.int64()), *((c, pa.int64()) for c in ("n_tokens", "n_known", "train_tokens")), ("base_score", pa.float64()), ("score", pa.float64()), ("n_pieces", pa.int64())])
