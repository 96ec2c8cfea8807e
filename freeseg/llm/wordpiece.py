"""Greedy longest-match-first word-piece lengths in linear time.

The vocabulary is a trie with failure links. Beside each failure link stands the number of pieces that are complete
when it is followed, so a word is one walk over its characters that only adds counts; no piece is ever built. Words are
counted once for each distinct word of a batch.

Nulls and odd input: a null or empty text has 0 words and 0 tokens. A word in which some place matches no piece is one
unknown token. Text is split at ASCII white space, then each punctuation mark or symbol stands alone. Words have no
length limit.
"""

from __future__ import annotations

import unicodedata
from collections import deque
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .kernel import cut_batches, released, segment_sum, words_of

#: Distinct words whose counts a worker keeps between batches.
CACHE = 150_000


class Automaton(NamedTuple):
    """children: by node and character; fail: where to go on when no child fits, -1 for nowhere; pops: pieces completed by going there. Node 0 starts a word, node 1 goes on inside one."""

    children: list[dict[str, int]]
    fail: list[int]
    pops: list[int]


def build(first: list[str], inner: list[str]) -> Automaton:
    """first: pieces that start a word; inner: pieces that continue one."""
    children: list[dict[str, int]] = [{}, {}]
    final = [False, False]
    for root, pieces in ((0, first), (1, inner)):
        for piece in pieces:
            at = root
            for ch in piece:
                if ch not in children[at]:
                    children.append({})
                    final.append(False)
                    children[at][ch] = len(children) - 1
                at = children[at][ch]
            final[at] |= at > 1
    fail, pops = [-1] * len(children), [0] * len(children)
    todo = deque([0, 1])
    while todo:
        u = todo.popleft()
        for ch, v in children[u].items():
            if final[v]:
                fail[v], pops[v] = 1, 1
            else:
                z, n = fail[u], pops[u]
                while z >= 0 and ch not in children[z]:
                    n += pops[z]
                    z = fail[z]
                if z >= 0:
                    fail[v], pops[v] = children[z][ch], n
            todo.append(v)
    return Automaton(children, fail, pops)


def count_pieces(word: str, a: Automaton) -> int:
    """Number of pieces of a word, 0 if it can't be split into pieces."""
    children, fail, pops = a
    u = n = 0
    for ch in word:
        while ch not in children[u]:
            n += pops[u]
            u = fail[u]
            if u < 0:
                return 0
        u = children[u][ch]
    while u != 1:
        n += pops[u]
        u = fail[u]
        if u < 0:
            return 0
    return n


def is_mark(ch: str) -> bool:
    return unicodedata.category(ch)[0] in "PS"


def split_marks(word: str) -> list[str]:
    """A blank-free word as runs of other characters and single marks."""
    if word.isalnum():
        return [word]
    out, run = [], ""
    for ch in word:
        if is_mark(ch):
            out += [run] * bool(run) + [ch]
            run = ""
        else:
            run += ch
    return out + [run] * bool(run)


def vocabulary(pieces: list[str], start: str = "▁") -> tuple[list[str], list[str]]:
    """Pieces of a vocabulary that marks word starts, as those that start a word and those that continue one. Marks and single characters may start a word too."""
    first = [p[1:] for p in pieces if p.startswith(start) and len(p) > 1 and start not in p[1:]]
    inner = [p for p in pieces if p and start not in p]
    first += [p for p in inner if len(p) == 1]
    return sorted(set(first)), sorted(set(inner))


def read_vocabulary(model_file: str) -> tuple[list[str], list[str]]:
    """From a sentencepiece model file on the driver."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=model_file)
    return vocabulary([sp.id_to_piece(k) for k in range(sp.get_piece_size()) if not (sp.is_byte(k) or sp.is_control(k) or sp.is_unknown(k))])


class _Counts(dict):
    def __init__(self, a: Automaton):
        super().__init__()
        self.a = a

    def __missing__(self, word: str) -> tuple[int, int, int]:
        parts = split_marks(word)
        counts = [count_pieces(p, self.a) for p in parts]
        bad = counts.count(0)
        self[word] = out = (len(parts), sum(counts) + bad, bad)
        return out


def token_counts(docs: DataFrame, first: list[str], inner: list[str], text: str = "text") -> DataFrame:
    """docs with n_words, n_tokens and n_unknown; columns of those names are replaced. The broadcast automaton is as large as the vocabulary."""
    held = docs.sparkSession.sparkContext.broadcast(build(first, inner))
    new = ["n_words", "n_tokens", "n_unknown"]
    keep = [c for c in docs.columns if c not in new]
    schema = T.StructType([docs.schema[c] for c in keep] + [T.StructField(c, T.LongType()) for c in new])

    @released
    def run(batches):
        known = _Counts(held.value)
        for batch in cut_batches(batches, text):
            w = words_of(batch.column(text), "")
            if len(known) > CACHE:
                known.clear()
            per_word = np.array([known[x] for x in w.distinct.to_pylist()], np.int64).reshape(-1, 3)
            sums = segment_sum(per_word[w.codes], w.offsets)
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), *(pa.array(sums[:, k]) for k in range(3))], [*keep, *new])

    return docs.select(*keep).mapInArrow(run, schema)
