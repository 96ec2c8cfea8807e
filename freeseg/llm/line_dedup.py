"""Line dedup by a log-template tree of fixed depth.

A line's words lead it to a leaf: first its number of words, then its first DEPTH words, where words with a digit count
as variable. In a leaf a line joins the first template of which at least SIMILAR of the words are equal, and turns the
others into variable fields; else it is a template of its own. A template that recurs across documents is boilerplate:
its first line, by document id and line number, stays and all others are dropped.

Each task adds up its lines by form (a line with variable words masked) before anything is shuffled, so a line that
stands in a third of all documents is a few rows. Leaves are then dealt out by hash, and a leaf is read in sorted order
and clustered as a whole by one task, whatever its size; from MOST_FORMS forms on its templates are found by an index, with the
same result. Forms to drop are broadcast if they are few, else joined.

Lines of LONG words or more recur if they stand in two documents, those of SHORT to LONG - 1 words if they do in
SHORT_DOCS; shorter lines are never dropped. Documents are told apart: a form carries the keys of up to SHORT_DOCS of its
documents, the smallest, so a template's forms together tell exactly whether it has as many.

Nulls and odd input: a null text has no lines and stays null. Blank lines stay. Rows without an id come before others.
A row is known by its id and a hash of its text, so repeated rows are one document: the same lines stay in each.
Columns besides those named are passed through.
"""

from __future__ import annotations

from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .kernel import cut_batches, hash_strings, mix, released, words_of
from .tables import BROADCAST_ROWS, keep

DEPTH, SIMILAR, LONG, SHORT, SHORT_DOCS, MOST_FORMS = 3, 0.8, 8, 3, 10, 2000
LEAST_ID = -(1 << 63)
#: Bytes of text whose forms one task clusters.
TASK_BYTES = 32 << 20


class Lines(NamedTuple):
    """Lines of some texts: of text i those from starts[i] to starts[i + 1], with number of words, form, leaf, and 16 bits of each word in body from body_at[j] on (0: variable)."""

    starts: np.ndarray
    n: np.ndarray
    form: np.ndarray
    leaf: np.ndarray
    body: np.ndarray
    body_at: np.ndarray


def lines_of(texts: pa.Array, depth: int = DEPTH) -> Lines:
    lists = pc.split_pattern(texts.fill_null(""), "\n")
    w = words_of(lists.flatten(), "")
    words = hash_strings(w.distinct)
    digit = pc.match_substring_regex(w.distinct, r"\d").to_numpy(zero_copy_only=False)
    words = np.where(digit, np.uint64(0), words | np.uint64(1))[w.codes]
    size = np.diff(w.offsets)
    place = np.arange(len(words)) - np.repeat(w.offsets[:-1], size)
    salted = mix(words + place.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    total = np.concatenate([[np.uint64(0)], np.cumsum(salted)])
    count = mix(size.astype(np.uint64))
    form = mix(total[w.offsets[1:]] - total[w.offsets[:-1]] + count)
    head = np.minimum(w.offsets[:-1] + depth, w.offsets[1:])
    leaf = mix(total[head] - total[w.offsets[:-1]] + count * np.uint64(3))
    body = ((words >> np.uint64(20)) & np.uint64(0xFFFF)).astype(np.uint16)
    body[(words != 0) & (body == 0)] = 1
    return Lines(lists.offsets.to_numpy().astype(np.int64), size, form.view(np.int64), leaf.view(np.int64), body, w.offsets)


def row_keys(ids: pa.Array, texts: pa.Array) -> tuple[list[int], list[int]]:
    """Id (the least number for null) and text hash of each row, which tell rows apart and order them."""
    return ids.fill_null(LEAST_ID).to_pylist(), [xxhash.xxh3_64_intdigest(x or b"") - (1 << 63) for x in texts.cast(pa.binary()).to_pylist()]


FORM = "leaf long, body binary, form long, id long, h long, line long, docs binary"
KEY = np.dtype([("id", ">u8"), ("h", ">u8")])
FORM_COLUMNS = [x.split()[0] for x in FORM.split(", ")]


def forms(docs: DataFrame, depth: int = DEPTH) -> DataFrame:
    """FORM for each form of each batch of docs (id, t): its first place, and the keys of its first SHORT_DOCS documents."""

    @released
    def run(batches):
        for batch in cut_batches(batches, "t"):
            ids, hashes = row_keys(batch.column("id"), batch.column("t"))
            x = lines_of(batch.column("t"), depth)
            order = sorted(range(len(ids)), key=lambda i: (ids[i], hashes[i]))
            keys = np.empty(len(ids), KEY)  # as bytes they sort as ids and hashes do
            keys["id"], keys["h"] = (np.array(c, np.int64).view(np.uint64) + np.uint64(1 << 63) for c in (ids, hashes))
            raw_keys = keys.tobytes()
            seen: dict[int, list] = {}
            for i in order:
                key, mine = raw_keys[16 * i : 16 * i + 16], set()
                a = int(x.starts[i])
                for j, (form, n) in enumerate(zip(x.form[a : x.starts[i + 1]].tolist(), x.n[a : x.starts[i + 1]].tolist(), strict=True)):
                    if n < SHORT:
                        continue
                    old = seen.get(form)
                    if old is None:
                        seen[form] = [a + j, ids[i], hashes[i], j, key]
                    elif form not in mine and len(old[4]) < 16 * SHORT_DOCS and old[4][-16:] != key:
                        old[4] += key
                    mine.add(form)
            if not seen:
                continue
            at = np.array([v[0] for v in seen.values()])
            raw, begin, end = x.body.tobytes(), x.body_at[at].tolist(), x.body_at[at + 1].tolist()
            *rest, docs_of = zip(*(v[1:] for v in seen.values()), strict=True)
            yield pa.RecordBatch.from_arrays(
                [pa.array(x.leaf[at]), pa.array([raw[2 * a : 2 * b] for a, b in zip(begin, end, strict=True)], pa.binary()), pa.array(list(seen), pa.int64()), *(pa.array(c, pa.int64()) for c in rest), pa.array(docs_of, pa.binary())], FORM_COLUMNS
            )

    return docs.mapInArrow(run, FORM)


def cluster(bodies: list[np.ndarray], similar: float = SIMILAR) -> list[int]:
    """The template of each of a leaf's lines, all of one length, in the given order."""
    n = len(bodies[0])
    index = Index(bodies, similar) if len(bodies) >= MOST_FORMS else None
    templates = np.zeros((min(len(bodies), 64), n), np.uint16)
    fixed = np.zeros_like(templates, bool)
    used, out = 0, []
    for body in bodies:
        some = slice(0, used) if index is None else index.candidates(body)
        if used and (index is None or len(some)):
            same = ((templates[some] == body) & fixed[some]).sum(1)
            best = int(same.argmax())
            if same[best] >= similar * n:
                best = best if index is None else int(some[best])
                fixed[best] &= templates[best] == body
                out.append(best)
                continue
        if used == len(templates):
            templates, fixed = np.concatenate([templates, np.zeros_like(templates)]), np.concatenate([fixed, np.zeros_like(fixed)])
        templates[used], fixed[used] = body, body != 0
        if index is not None:
            index.add(body, used)
        out.append(used)
        used += 1
    return out


class Index:
    """Finds all templates that a body can join. If at most m of its words may differ, then of m + 1 parts of the places one is equal."""

    def __init__(self, bodies: list[np.ndarray], similar: float):
        n, first = len(bodies[0]), bodies[0]
        alike = np.ones(n, bool)
        for body in bodies:
            alike &= body == first
        # Places that are alike in all bodies say nothing, and if variable they differ always.
        differ = n - next((k for k in range(n + 1) if k >= similar * n), n + 1) - int((alike & (first == 0)).sum())
        self.parts = np.array_split(np.flatnonzero(~alike), differ + 1) if differ >= 0 else []
        self.lists: list[dict[bytes, list[int]]] = [{} for _ in self.parts]

    def candidates(self, body: np.ndarray) -> np.ndarray:
        return np.array(sorted({k for part, at in zip(self.parts, self.lists, strict=True) for k in at.get(body[part].tobytes(), ())}), np.int64)

    def add(self, body: np.ndarray, k: int) -> None:
        for part, at in zip(self.parts, self.lists, strict=True):
            if body[part].all():  # a variable word is equal to none
                at.setdefault(body[part].tobytes(), []).append(k)


def keys_of(docs: bytes) -> list[bytes]:
    return [docs[k : k + 16] for k in range(0, len(docs), 16)]


DROP = "form long, id long, h long, line long"


def recurring(found: DataFrame, similar: float = SIMILAR, tasks: int = 0) -> DataFrame:
    """DROP: the forms of templates that recur across documents, with the place of the template's line that stays. Leaves are dealt out to `tasks` tasks, or as many as the session's partitions if these are more."""
    parts = max(tasks, int(found.sparkSession.conf.get("spark.sql.shuffle.partitions")))

    def decide(group: list[list]):
        """Rows of distinct forms: body, form, first place, keys of documents."""
        which = cluster([g[0] for g in group], similar) if len(group) > 1 else [0]
        by: dict[int, list[list]] = {}
        for k, g in zip(which, group, strict=True):
            by.setdefault(k, []).append(g)
        for members in by.values():
            first, docs = min(g[2] for g in members), set().union(*(keys_of(g[3]) for g in members))
            if len(docs) >= (2 if len(members[0][0]) >= LONG else SHORT_DOCS):
                for g in members:
                    yield (g[1], *first)

    @released
    def run(batches):
        group, leaf, out = [], None, []

        def flush():
            nonlocal out
            batch = pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], ["form", "id", "h", "line"])
            out = []
            return batch

        for batch in batches:
            for at, body, form, i, h, line, docs in zip(*(batch.column(c).to_pylist() for c in FORM_COLUMNS), strict=True):
                body = np.frombuffer(body, np.uint16)
                first = (i, h, line)
                if at == leaf and group[-1][1] == form:
                    g = group[-1]
                    g[2] = min(g[2], first)
                    if g[3] != docs:
                        g[3] = b"".join(sorted({*keys_of(g[3]), *keys_of(docs)})[:SHORT_DOCS])
                    continue
                if group and at != leaf:
                    out += decide(group)
                    group = []
                leaf = at
                group.append([body, form, first, docs])
            if len(out) >= 5000:
                yield flush()
        if group:
            out += decide(group)
        if out:
            yield flush()

    return found.repartition(parts, "leaf").sortWithinPartitions("leaf", "body", "form").mapInArrow(run, DROP)


def _cleaned(texts: list[str | None], gone: list[set[int]]) -> list[str | None]:
    return [t if not g or t is None else "\n".join(x for k, x in enumerate(t.split("\n")) if k not in g) for t, g in zip(texts, gone, strict=True)]


NEW = ["n_lines", "dropped_lines"]


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text: str = "text", depth: int = DEPTH, similar: float = SIMILAR, most: int = BROADCAST_ROWS) -> DataFrame:
    """docs with the text without dropped lines, n_lines (before) and dropped_lines (line numbers from 0); columns of those names are replaced."""
    cols = [c for c in docs.columns if c not in NEW]
    docs = docs.select(*cols)
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text).cast("string").alias("t"))
    size = rows.agg(F.coalesce(F.sum(F.octet_length("t").cast("long")), F.lit(0)).alias("n")).first().n
    drop = keep(recurring(forms(rows, depth), similar, -(-size // TASK_BYTES)))
    schema = T.StructType([*docs.schema.fields, T.StructField("n_lines", T.LongType()), T.StructField("dropped_lines", T.ArrayType(T.IntegerType()))])

    def finish(batch, gone):
        texts = batch.column(text).to_pylist()
        made = [pa.array(_cleaned(texts, gone), pa.string()), pa.array([0 if t is None else t.count("\n") + 1 for t in texts], pa.int64()), pa.array([sorted(g) for g in gone], pa.list_(pa.int32()))]
        return pa.RecordBatch.from_arrays([made[0] if c == text else batch.column(c) for c in cols] + made[1:], [*cols, *NEW])

    if drop.count() <= most:
        got = drop.toArrow().sort_by("form")
        held = docs.sparkSession.sparkContext.broadcast(tuple(got.column(c).to_numpy() for c in ("form", "id", "h", "line")))

        @released
        def apply(batches):
            form, fid, fh, fline = held.value
            for batch in cut_batches(batches, text):
                ids, hashes = row_keys(batch.column(id_col).cast(pa.int64()), batch.column(text))
                x = lines_of(batch.column(text), depth)
                at = np.minimum(np.searchsorted(form, x.form), max(len(form) - 1, 0))
                hit = np.flatnonzero((form[at] == x.form) & (x.n >= SHORT)) if len(form) else np.zeros(0, np.int64)
                gone = [set() for _ in ids]
                for j, i, k in zip(hit.tolist(), (np.searchsorted(x.starts, hit, side="right") - 1).tolist(), at[hit].tolist(), strict=True):
                    line = j - int(x.starts[i])
                    if (ids[i], hashes[i], line) != (fid[k], fh[k], fline[k]):
                        gone[i].add(line)
                yield finish(batch, gone)

        return docs.mapInArrow(apply, schema)

    @released
    def places(batches):
        for batch in cut_batches(batches, "t"):
            ids, hashes = row_keys(batch.column("id"), batch.column("t"))
            x = lines_of(batch.column("t"), depth)
            at = np.flatnonzero(x.n >= SHORT)
            i = np.searchsorted(x.starts, at, side="right") - 1
            yield pa.RecordBatch.from_arrays([pa.array(x.form[at]), pa.array(np.array(ids)[i]), pa.array(np.array(hashes)[i]), pa.array(at - x.starts[i])], ["form", "i", "k", "l"])

    hits = rows.mapInArrow(places, "form long, i long, k long, l long").join(drop, "form").where("i <> id or k <> h or l <> line")
    lists = hits.groupBy("i", "k").agg(F.collect_set(F.col("l").cast("int")).alias("__gone"))

    @released
    def keyed(batches):
        for batch in cut_batches(batches, text):
            ids, hashes = row_keys(batch.column(id_col).cast(pa.int64()), batch.column(text))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(ids, pa.int64()), pa.array(hashes, pa.int64())], [*cols, "__i", "__k"])

    @released
    def apply_lists(batches):
        for batch in batches:
            yield finish(batch, [set(g or ()) for g in batch.column("__gone").to_pylist()])

    key = T.StructType([*docs.schema.fields, T.StructField("__i", T.LongType()), T.StructField("__k", T.LongType())])
    with_lists = docs.mapInArrow(keyed, key).join(lists, (F.col("__i") == F.col("i")) & (F.col("__k") == F.col("k")), "left").select(*cols, "__gone")
    return with_lists.mapInArrow(apply_lists, schema)


def clean(docs: DataFrame, id_col: str = "doc_id", text: str = "text", **how) -> DataFrame:
    """docs with recurring lines dropped, without the documents of which no word is left; columns as they were."""
    clash = {c: f"__own_{c}" for c in docs.columns if c in NEW}
    done = dedup_lines(docs.withColumnsRenamed(clash), id_col, text, **how)
    left = done.where((F.size("dropped_lines") == 0) | F.col(text).rlike(r"[^\x20\x09-\x0D]")).drop(*NEW)
    return left.withColumnsRenamed({b: a for a, b in clash.items()}).select(*docs.columns)


def digest_rows(done: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """id, n_lines, dropped_lines, and bytes and SHA-256 of the text that is left."""
    body = F.coalesce(F.col(text), F.lit(""))
    return done.select(id_col, "n_lines", "dropped_lines", F.octet_length(body).cast("long").alias("kept_bytes"), F.sha2(body, 256).alias("kept_sha256"))
