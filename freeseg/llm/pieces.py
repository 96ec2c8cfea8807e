"""Encoding and decoding with a sentencepiece vocabulary: the segmentation with the highest total score.

An Aho-Corasick automaton over the pieces reads a text once. At each character its output links give every piece that
ends there, and each relaxes the best score of that place. A character that no piece covers is written as byte pieces.
No piece holds a blank after another character, so the best segmentation of a text is that of its blank-led chunks, one
after the other; chunks are encoded once each and kept in a bounded cache.

Nulls and odd input: a null text is encoded as an empty one, without pieces. Blanks become U+2581 and one is put before
the text; decoding undoes both, so a text comes back as it was, except that a U+2581 in it comes back as a blank. Ties
go to the longer last piece. Repeated rows are encoded alike.
"""

from __future__ import annotations

import re
from array import array

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .kernel import cut_batches, released

BLANK = "▁"
#: Added to the lowest score for each byte of a character that no piece covers.
BYTE_PENALTY = 10.0
#: Distinct chunks that a worker keeps.
CACHE = 120_000
CHUNK = re.compile(f"{BLANK}*[^{BLANK}]+|{BLANK}+")
#: For vocabularies without a line feed in any piece: a line feed is bytes whatever stands beside it, so it is a chunk too.
LINE_CHUNK = re.compile(f"{BLANK}*[^{BLANK}\n]+|{BLANK}+|\n")


def read_pieces(model_file: str) -> list[tuple[str, float, str]]:
    """(piece, score, kind) by id from a model file on the driver; kind: normal, byte or other."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=model_file)
    kind = lambda k: "byte" if sp.is_byte(k) else "other" if sp.is_control(k) or sp.is_unknown(k) or sp.is_unused(k) else "normal"
    return [(sp.id_to_piece(k), sp.get_score(k), kind(k)) for k in range(sp.get_piece_size())]


class Codec:
    def __init__(self, pieces: list[tuple[str, float, str]]):
        self.automaton = ahocorasick.Automaton()
        self.bytes_of: list[bytes] = []
        self.byte_id: dict[int, int] = {}
        self.unknown = next((k for k, (_, _, kind) in enumerate(pieces) if kind == "other"), 0)
        low, lines = 0.0, False
        self.whole = True  # chunks can be encoded apart
        for k, (piece, score, kind) in enumerate(pieces):
            if kind == "byte":
                self.byte_id[int(piece[3:5], 16)] = k
                self.bytes_of.append(bytes([int(piece[3:5], 16)]))
            elif kind == "normal" and piece:
                self.automaton.add_word(piece, (len(piece), score, k))
                self.bytes_of.append(piece.replace(BLANK, " ").encode())
                low = min(low, score)
                lines |= "\n" in piece
                self.whole &= BLANK not in piece.lstrip(BLANK)
            else:
                self.bytes_of.append(b"")
        if len(self.automaton):
            self.automaton.make_automaton()
        self.byte_score = low - BYTE_PENALTY
        self.chunks = CHUNK if lines else LINE_CHUNK
        self.known: dict[str, tuple[bytes, bytes]] = {}

    def best(self, chunk: str) -> list[int]:
        """Ids of the best segmentation, by dynamic programming over the places of a chunk."""
        n = len(chunk)
        score, back = [0.0] * (n + 1), [(1, -1)] * (n + 1)
        found: list[list] = [[] for _ in range(n + 1)]
        if len(self.automaton):
            for end, value in self.automaton.iter(chunk):
                found[end + 1].append(value)
        for end in range(1, n + 1):
            top, longest, via, single = -np.inf, 0, -1, False
            for length, s, k in found[end]:
                s += score[end - length]
                if s > top or (s == top and length > longest):
                    top, longest, via = s, length, k
                if length == 1:
                    single = True
            if not single:  # bytes are always worse than a piece of one character
                raw = chunk[end - 1].replace(BLANK, " ").encode("utf-8", "surrogatepass")
                s = score[end - 1] + self.byte_score * len(raw)
                if s > top:
                    top, longest, via = s, 1, -1
            score[end], back[end] = top, (longest, via)
        out, end = [], n
        while end:
            length, k = back[end]
            if k >= 0:
                out.append(k)
            else:
                raw = chunk[end - 1].replace(BLANK, " ").encode("utf-8", "surrogatepass")
                out += [self.byte_id.get(b, self.unknown) for b in reversed(raw)]
            end -= length
        return out[::-1]

    def encode(self, text: str | None) -> np.ndarray:
        """Ids of a text as 32-bit integers."""
        return self.coded(text)[0]

    def coded(self, text: str | None) -> tuple[np.ndarray, str]:
        """Ids of a text as 32-bit integers, and the text that they spell. Pieces spell the same wherever they stand, so a chunk's ids are decoded once, when they are found."""
        if not text:
            return np.zeros(0, np.int32), ""
        text = BLANK + text.replace(" ", BLANK)
        if not self.whole:
            ids = self.best(text)
            return np.array(ids, np.int32), self.decode(ids)
        known, parts, spelled = self.known, [], []
        for chunk in self.chunks.findall(text):
            both = known.get(chunk)
            if both is None:
                if len(known) >= CACHE:
                    known.clear()
                ids = self.best(chunk)
                both = array("i", ids).tobytes(), b"".join(map(self.bytes_of.__getitem__, ids))
                if len(chunk) <= 100:
                    known[chunk] = both
            parts.append(both[0])
            spelled.append(both[1])
        return np.frombuffer(b"".join(parts), np.int32), b"".join(spelled).decode("utf-8", "surrogatepass")[1:]

    def decode(self, ids) -> str:
        raw = b"".join(map(self.bytes_of.__getitem__, ids))
        return raw.decode("utf-8", "surrogatepass")[1:] if raw else ""


#: A worker keeps one codec, so that its chunks stay known from task to task.
_codecs: dict[str, Codec] = {}


def encode(docs: DataFrame, pieces: list[tuple[str, float, str]], text: str = "text", ids: str = "piece_ids") -> DataFrame:
    """docs with the ids of each text's pieces as an array and `decodes`, whether they decode to the text; columns of those names are replaced."""
    spark = docs.sparkSession
    held, key = spark.sparkContext.broadcast(pieces), str(hash(tuple(pieces)))
    keep = [c for c in docs.columns if c not in (ids, "decodes")]
    schema = T.StructType([docs.schema[c] for c in keep] + [T.StructField(ids, T.ArrayType(T.IntegerType())), T.StructField("decodes", T.BooleanType())])

    @released
    def run(batches):
        if key not in _codecs:
            _codecs.clear()
            _codecs[key] = Codec(held.value)
        codec = _codecs[key]
        for batch in cut_batches(batches, text, 2 << 20):
            texts = batch.column(text).to_pylist()
            both = [codec.coded(t) for t in texts]
            coded, right = [ids for ids, _ in both], [back == (t or "").replace(BLANK, " ") for (_, back), t in zip(both, texts, strict=True)]
            offsets = np.concatenate([[0], np.cumsum([len(c) for c in coded])]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(coded) if coded else np.zeros(0, np.int32)))
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), lists, pa.array(right)], [*keep, ids, "decodes"])

    return docs.select(*keep).mapInArrow(run, schema)


def decode(coded: DataFrame, pieces: list[tuple[str, float, str]], ids: str = "piece_ids", text: str = "text") -> DataFrame:
    """coded with the text that its ids spell; a column of that name is replaced. Null ids decode to null."""
    held = coded.sparkSession.sparkContext.broadcast(pieces)
    keep = [c for c in coded.columns if c != text]
    schema = T.StructType([coded.schema[c] for c in keep] + [T.StructField(text, T.StringType())])

    @released
    def run(batches):
        codec = Codec(held.value)
        for batch in batches:
            out = [None if x is None else codec.decode(x) for x in batch.column(ids).to_pylist()]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), pa.array(out, pa.string())], [*keep, text])

    return coded.mapInArrow(run, schema)
