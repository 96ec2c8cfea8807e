"""Document fingerprints: a Merkle tree over sections, paragraphs and pieces of paragraphs.

Paragraphs are lines. A section ends after an empty paragraph or one whose digest is a multiple of SECTION, so sections
keep their borders when text is put in elsewhere. A paragraph's pieces end after a word whose hash is a multiple of
PIECE; in texts of SHORT_WORDS words or fewer its words are leaves too. The root is a digest of the sections' digests, those of their paragraphs' digests, and those of the text: equal
texts have equal roots, and different ones have different roots as surely as the digest can tell. The fingerprint is
the tree as a string, with a fixed number of characters for each node: 64 for the root, 8 for a section or paragraph, 4 for a piece or word.

Two trees are compared from the roots down, and only where digests differ: equal sections are set against each other, then
equal paragraphs of the sections that are left, then equal leaves of the paragraphs that are left. What no equal node covers are the branches that
differ; `differences` gives their paragraphs, and `likeness` is the share of leaves below equal nodes.

Nulls and odd input: a null text is an empty one. `with_next` orders rows by id, null ids first, rows with the same id by
text; after the last comes the first. A text without words has no leaves: its likeness is 1 to equal texts, else 0.
"""

from __future__ import annotations

import base64
import hashlib
from collections import defaultdict
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .kernel import BATCH_BYTES, hash_strings, mix, released, words_of

SECTION, PIECE, SHORT_WORDS = 4, 6, 96
#: Bytes of text that one task orders and compares, and ranges of ids for each task.
TASK_BYTES, RANGES = 64 << 20, 16


class Paragraph(NamedTuple):
    digest: bytes  # 6 bytes
    pieces: bytes  # 3 for each
    words: bytes  # 3 for each, in short texts only


class Section(NamedTuple):
    digest: bytes
    paragraphs: list[Paragraph]


class Tree(NamedTuple):
    root: str
    sections: list[Section]
    short: bool

    @property
    def fingerprint(self) -> str:
        code = lambda x: base64.urlsafe_b64encode(x).decode()
        line = lambda p: code(p.digest + p.pieces) + ("/" + code(p.words) if self.short else "")
        return self.root + "".join(f";{code(x.digest)}:{','.join(map(line, x.paragraphs))}" for x in self.sections)


def _three(x: np.ndarray) -> bytes:
    """The upper three bytes of 64-bit numbers."""
    return np.ascontiguousarray((x >> np.uint64(40)).astype("<u4").view(np.uint8).reshape(-1, 4)[:, :3]).tobytes()


def trees(texts: list[str]) -> list[Tree]:
    lists = pc.split_pattern(pa.array(texts, pa.string()), "\n")
    paragraphs, starts = lists.flatten(), lists.offsets.to_pylist()
    w = words_of(paragraphs, "")
    words = hash_strings(w.distinct)[w.codes]
    if len(words):
        ends = words % np.uint64(PIECE) == 0
        ends[w.offsets[1:][w.offsets[1:] > w.offsets[:-1]] - 1] = True
        first = np.concatenate([[0], np.flatnonzero(ends)[:-1] + 1])
        place = np.arange(len(words)) - np.repeat(first, np.diff(np.append(first, len(words))))
        pieces = _three(np.add.reduceat(mix(words + place.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)), first))
        piece_at = np.searchsorted(first, w.offsets).tolist()
    else:
        pieces, piece_at = b"", [0] * len(w.offsets)
    leaves, word_at, out = _three(mix(words)), w.offsets.tolist(), []
    bodies = paragraphs.cast(pa.binary()).to_pylist()
    for a, b in zip(starts[:-1], starts[1:], strict=True):
        sections, nodes, section, full = [], [], [], []
        short = word_at[b] - word_at[a] <= SHORT_WORDS
        for p in range(a, b):
            digest = hashlib.blake2b(bodies[p], digest_size=16).digest()
            full.append(digest)
            section.append(Paragraph(digest[:6], pieces[3 * piece_at[p] : 3 * piece_at[p + 1]], leaves[3 * word_at[p] : 3 * word_at[p + 1]] if short else b""))
            if p == b - 1 or not bodies[p] or not digest[0] % SECTION:
                node = hashlib.blake2b(b"".join(full), digest_size=16).digest()
                nodes.append(node)
                sections.append(Section(node[:6], section))
                section, full = [], []
        out.append(Tree(hashlib.blake2b(b"".join(nodes), digest_size=32).hexdigest(), sections, short))
    return out


def _unmatched(a: list, b: list, key) -> tuple[list, list, list]:
    """The members of a that have no equal one left in b, those of b that have none in a, and those of a that have."""
    there = defaultdict(list)
    for y in b:
        there[key(y)].append(y)
    only, both = [], []
    for x in a:
        mine = there.get(key(x))
        if mine:
            mine.pop()
            both.append(x)
        else:
            only.append(x)
    return only, [y for ys in there.values() for y in ys], both


class Comparison(NamedTuple):
    likeness: float
    differs: list[tuple[int, int]]  # (section, paragraph) of the first tree without an equal one


def compare(a: Tree, b: Tree) -> Comparison:
    """Descends both trees at once where their digests differ."""
    if a.root == b.root:
        return Comparison(1.0, [])
    at = 2 if a.short and b.short else 1  # words or pieces
    size = lambda x: sum(len(p[at]) for p in x.paragraphs)
    mine, theirs, same = _unmatched(list(enumerate(a.sections)), list(enumerate(b.sections)), lambda x: x[1].digest)
    shared = sum(size(x) for _, x in same)
    here = [(i, j, p) for i, x in mine for j, p in enumerate(x.paragraphs)]
    there = [(0, 0, p) for _, x in theirs for p in x.paragraphs]
    total = 2 * shared + sum(len(p[at]) for _, _, p in here) + sum(len(p[at]) for _, _, p in there)
    here, there, same = _unmatched(here, there, lambda x: x[2].digest)
    shared += sum(len(p[at]) for _, _, p in same)
    # Leaves of the paragraphs that differ, as bags.
    shared += 3 * _common(*(np.frombuffer(b"".join(p[at] for _, _, p in side), np.dtype("V3")) for side in (here, there)))
    return Comparison(2 * shared / total if total else 0.0, [(i, j) for i, j, _ in here])


def _common(a: np.ndarray, b: np.ndarray) -> int:
    """Size of the intersection of two bags of three bytes each."""
    wide = lambda x: np.pad(x.view(np.uint8).reshape(-1, 3), ((0, 0), (0, 1))).view("<u4").ravel()
    if not len(a) or not len(b):
        return 0
    x, n = np.unique(wide(a), return_counts=True)
    y, m = np.unique(wide(b), return_counts=True)
    _, i, j = np.intersect1d(x, y, assume_unique=True, return_indices=True)
    return int(np.minimum(n[i], m[j]).sum())


def parse(fingerprint: str) -> Tree:
    """The tree that a fingerprint says."""
    decode, sections, short = base64.urlsafe_b64decode, [], False
    for part in fingerprint[64:].split(";")[1:]:
        digest, _, body = part.partition(":")
        lines = []
        for line in body.split(","):
            own, mark, words = line.partition("/")
            raw = decode(own)
            short |= bool(mark)
            lines.append(Paragraph(raw[:6], raw[6:], decode(words)))
        sections.append(Section(decode(digest), lines))
    return Tree(fingerprint[:64], sections, short)


def likeness(a: str, b: str) -> float:
    """Likeness of two fingerprints, 0 to 1."""
    return compare(parse(a), parse(b)).likeness


def differences(a: str, b: str) -> list[tuple[int, int]]:
    """(section, paragraph) of the paragraphs of a that b lacks; what has an equal digest in b is not gone into."""
    return compare(parse(a), parse(b)).differs


def edit(text: str, following: str) -> str:
    """text whose last half, rounded down, is replaced by as much of the beginning of another text, or by all of it."""
    n = len(text) // 2
    return text[: len(text) - n] + following[:n]


def in_order(docs: DataFrame, id_col: str = "doc_id", text: str = "text", buckets: int | None = None) -> DataFrame:
    """bucket, tail, id, text: rows dealt by ranges of ids and sorted, and at the end of each range, marked as tail, the rows with the id that comes next. One shuffle of the texts; the first id of each range comes to the driver."""
    spark = docs.sparkSession
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text).cast("string"), F.lit("")).alias("text"))
    size = rows.agg(F.coalesce(F.sum(F.octet_length("text").cast("long")), F.lit(0)).alias("n")).first().n
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-size // TASK_BYTES))
    buckets = buckets or RANGES * parts
    cuts = rows.approxQuantile("id", [k / buckets for k in range(1, buckets)], 0.2 / buckets) if buckets > 1 else []
    bounds = spark.sparkContext.broadcast(np.unique(np.array(cuts, np.float64)))

    def bucket_of(ids: pa.Array) -> np.ndarray:
        at = np.searchsorted(bounds.value, ids.fill_null(0).to_numpy(zero_copy_only=False).astype(np.float64), side="right")
        return np.where(ids.is_null().to_numpy(zero_copy_only=False), 0, at)

    @released
    def firsts(batches):
        for batch in batches:
            ids = batch.column(0)
            yield pa.RecordBatch.from_arrays([pa.array(bucket_of(ids)), ids], ["bucket", "id"])

    lead = rows.select("id").mapInArrow(firsts, "bucket long, id long").groupBy("bucket").agg(F.min("id").alias("id"), F.bool_or(F.col("id").isNull()).alias("null_id")).collect()
    lead = sorted((r.bucket, None if r.null_id else r.id) for r in lead)
    #: Of each range, its first id and the range before, the last before the first.
    before = {b: (first, lead[k - 1][0]) for k, (b, first) in enumerate(lead)}

    @released
    def deal(batches):
        for batch in batches:
            ids = batch.column(0)
            at = bucket_of(ids)
            yield pa.RecordBatch.from_arrays([pa.array(at), pa.array([False] * len(ids)), ids, batch.column(1)], ["bucket", "tail", "id", "text"])
            extra = [(i, before[b][1]) for i, (b, x) in enumerate(zip(at.tolist(), ids.to_pylist(), strict=True)) if b in before and before[b][0] == x]
            if extra:
                pick = pa.array([i for i, _ in extra])
                yield pa.RecordBatch.from_arrays([pa.array([b for _, b in extra]), pa.array([True] * len(extra)), ids.take(pick), batch.column(1).take(pick)], ["bucket", "tail", "id", "text"])

    dealt = rows.mapInArrow(deal, "bucket long, tail boolean, id long, text string")
    return dealt.repartition(parts, "bucket").sortWithinPartitions("bucket", "tail", "id", "text")


def neighbours(batches):
    """Lists of (id, text) with the text that follows each, from the sorted rows of `in_order`."""
    held, size, bucket, done = [], 0, None, True
    for batch in batches:
        for b, tail, i, t in zip(*(batch.column(c).to_pylist() for c in ("bucket", "tail", "id", "text")), strict=True):
            if b != bucket:
                bucket, done = b, False
            if tail:
                if not done and held:
                    yield held, t
                held, size, done = [], 0, True
                continue
            if size >= BATCH_BYTES // 2:
                yield held, t
                held, size = [], 0
            held.append((i, t))
            size += len(t)


FIELDS = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double, n_sections long, n_paragraphs long, edited_paragraphs array<int>"


def fingerprints(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs with the `fingerprint` of each text; a column of that name is replaced."""
    keep = [c for c in docs.columns if c != "fingerprint"]
    schema = T.StructType([docs.schema[c] for c in keep] + [T.StructField("fingerprint", T.StringType())])

    @released
    def run(batches):
        for batch in batches:
            made = trees([x or "" for x in batch.column(text).to_pylist()])
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), pa.array([x.fingerprint for x in made])], [*keep, "fingerprint"])

    return docs.select(*keep).mapInArrow(run, schema)


def compare_edits(docs: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """FIELDS of each row: its fingerprint, that of its text with the last half replaced by the next row's beginning, how like they are, and the paragraphs (from 0) of the edited text that the row's own tree lacks."""
    names = [x.split()[0] for x in FIELDS.split(", ")]

    @released
    def run(batches):
        for rows, after in neighbours(batches):
            texts = [t for _, t in rows] + [after]
            edited = [edit(a, b) for a, b in zip(texts, texts[1:], strict=False)]
            own, other = trees(texts), trees(edited)
            changes = [compare(b, a) for a, b in zip(own, other, strict=False)]
            begins = [np.concatenate([[0], np.cumsum([len(x.paragraphs) for x in t.sections])]) for t in other]
            cols = [
                pa.array([i for i, _ in rows], pa.int64()), pa.array([len(t) for _, t in rows], pa.int64()), pa.array([hashlib.sha256(t.encode()).hexdigest() for t in edited]),
                pa.array([t.fingerprint for t in own[:-1]]), pa.array([t.fingerprint for t in other]),
                pa.array([c.likeness for c in changes]), pa.array([compare(a, b).likeness for a, b in zip(own, own[1:], strict=False)]),
                pa.array([len(t.sections) for t in own[:-1]], pa.int64()), pa.array([t.count("\n") + 1 for _, t in rows], pa.int64()),
                pa.array([[int(at[i]) + j for i, j in c.differs] for at, c in zip(begins, changes, strict=True)], pa.list_(pa.int32())),
            ]
            yield pa.RecordBatch.from_arrays(cols, names)

    return in_order(docs, id_col, text).mapInArrow(run, FIELDS)
