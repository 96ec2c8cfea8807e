"""Benchmark decontamination by templates.

Words are made canonical: lower case without the marks around them, numbers, units and names replaced by typed
placeholders. Windows of `width` canonical words of the benchmark items are kept by hash; the windows of every text are
looked up among them. A text holds an item if it holds at least `cover` of the item's windows, or ENOUGH in a row, and the names
agree: each name in the item stands for one in the text, and the other way round. Numbers and units are free, as two that
are equal in the item need not be so in the text. An item is so found with other numbers or names too. A capital at the beginning of
a sentence may be a name's or not, so windows are looked up by both readings.

A window of placeholders alone would stand for any list of numbers or names; it is taken literally, by its words as they stand.

The benchmark is the query set. It is taken in blocks of bounded size, each broadcast and matched in one pass over
the texts; no text is shuffled. Between blocks the rows are written to the shared folder, so one block is held at a time.

Nulls and odd input: null and empty texts hold nothing. Items with fewer words than `width` are one window; an item with
fewer than `least` words is found only where a text is that item as a whole, up to case and marks; items without a word are in no text. Repeated items are reported under each of their ids; items without an id are
left out. With an empty benchmark nothing is found.
"""

from __future__ import annotations

import re
from collections import defaultdict
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .kernel import cut_batches, hash_strings, mix, ranges, released, words_of
from .tables import keep as kept
from .toxicity import MARKS

WIDTH, COVER, LEAST, ENOUGH, BLOCK_BYTES = 8, 0.5, 4, 16, 16 << 20
#: Words that are units of measure.
UNITS = frozenset(
    "mm cm m km in ft yd mi mg g kg t oz lb lbs ml cl l s sec secs min mins h hr hrs hour hours minute minutes second seconds day days week weeks "
    "month months year years meter meters metre metres kilometer kilometers kilometre kilometres mile miles foot feet inch inches gram grams "
    "kilogram kilograms pound pounds ounce ounces liter liters litre litres dollar dollars euro euros cent cents percent usd eur gbp kmh mph kwh w kw v".split()
)
NUMBER = re.compile(r"[$€£]?[+-]?\d[\d.,:/]*(%|[a-zµ°]{1,3})?")
WORD, NUM, UNIT, NAME = 0, 1, 2, 3
SLOT = np.array([0, 0x51ED270B, 0x6C8E9CF5, 0x3C6EF372], np.uint64)
LITERAL = np.uint64(0x2545F4914F6CDD1D)


class Canonical(NamedTuple):
    """Canonical words of some texts: hashes, kinds (WORD, NUM, UNIT, NAME) and hashes of the words as they stood. begins: capitals at the beginning of a sentence, which are taken as no names here."""

    offsets: np.ndarray
    hashes: np.ndarray
    kinds: np.ndarray
    raw: np.ndarray
    begins: np.ndarray


def canonical(texts: pa.Array) -> Canonical:
    w = words_of(texts, "")
    words = w.distinct.to_pylist()
    bare = [x.strip(MARKS) for x in words]
    low = [x.lower() for x in bare]
    raw = hash_strings(pa.array(low, pa.string()))
    kind, capital, ends = np.zeros(len(words), np.int8), np.zeros(len(words), bool), np.zeros(len(words), bool)
    for k, (word, x, y) in enumerate(zip(words, bare, low, strict=True)):
        if x:
            if x[0].isdigit() or word[0] in "$€£+-":
                if NUMBER.fullmatch(y):
                    kind[k] = NUM
            elif y in UNITS and x == y:
                kind[k] = UNIT
            capital[k] = x[0].isupper() and x[1:] != x[1:].upper()
        ends[k] = word[-1:] in ".!?:" or (word[-1:] in "\"')”»" and word[-2:-1] in ".!?:")
    full = np.array([bool(x) for x in bare], bool)[w.codes]
    starts = np.zeros(len(w.codes), bool)
    if len(w.codes):
        starts[1:] = ends[w.codes[:-1]]
        starts[w.offsets[:-1][w.offsets[:-1] < w.offsets[1:]]] = True
    kinds = kind[w.codes]
    begins = (kinds == WORD) & capital[w.codes] & starts
    kinds[(kinds == WORD) & capital[w.codes] & ~starts] = NAME
    raws = raw[w.codes]
    hashes = np.where(kinds == WORD, raws, SLOT[kinds])
    offsets = np.concatenate([[0], np.cumsum(full)])[w.offsets]
    return Canonical(offsets, hashes[full], kinds[full], raws[full], begins[full])


def readings(c: Canonical, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Places and hashes of windows, and whether they are of the reading that takes capitals at the beginning of a sentence as names; of that only windows that differ and still hold a word."""
    at, h = windows(c, width)
    words = np.concatenate([[0], np.cumsum((c.kinds == WORD) & ~c.begins)])
    names = np.concatenate([[0], np.cumsum(c.begins)])
    differ = at[(names[at + width] > names[at]) & (words[at + width] > words[at])]
    other = np.where(c.begins, SLOT[NAME], c.hashes)
    return np.concatenate([at, differ]), np.concatenate([h, hashed(other, differ, width)]), np.repeat([False, True], [len(at), len(differ)])


def hashed(words: np.ndarray, at: np.ndarray, width: int) -> np.ndarray:
    """Hashes of the windows that begin at the given places."""
    h = np.zeros(len(at), np.uint64)
    for j in range(width):
        h = h * np.uint64(0x9E3779B97F4A7C15) + words[at + j]
    return mix(h)


def windows(c: Canonical, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Places where a window of that many words begins, and the windows' hashes; those of windows of placeholders alone are of their words as they stand."""
    size = np.diff(c.offsets)
    at = ranges(c.offsets[:-1], np.maximum(size - width + 1, 0))
    h = hashed(c.hashes, at, width)
    words = np.concatenate([[0], np.cumsum(c.kinds == WORD)])
    bare = np.flatnonzero(words[at + width] == words[at])
    h[bare] = hashed(c.raw, at[bare], width) ^ LITERAL
    return at, h


def wholes(c: Canonical, least: int) -> list[tuple[int, bytes]]:
    """Number and words of the texts that have a word, but fewer than `least`."""
    size = np.diff(c.offsets)
    return [(int(i), c.raw[c.offsets[i] : c.offsets[i + 1]].tobytes()) for i in np.flatnonzero((size > 0) & (size < least))]


class Block(NamedTuple):
    """Some items. tables: by window width the sorted distinct hashes, and for each the (item, place, reading) from first to first of the next. short: the items with fewer than `least` words, by their words."""

    ids: list[int]
    words: Canonical
    least: int
    short: dict[bytes, list[int]]
    totals: np.ndarray
    tables: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]


def build_block(ids: list[int], texts: list[str], width: int = WIDTH, least: int = LEAST) -> Block:
    c = canonical(pa.array(texts, pa.string()))
    size = np.diff(c.offsets)
    tables = {}
    for n in sorted({min(width, int(x)) for x in size if x >= least}):
        at, h, named = readings(c, n)
        item = np.searchsorted(c.offsets, at, side="right") - 1
        own = np.minimum(size[item], width) == n
        at, h, item, named = at[own], h[own], item[own], named[own]
        order = np.argsort(h, kind="stable")
        distinct, first = np.unique(h[order], return_index=True)
        tables[n] = (distinct, np.append(first, len(order)), item[order], (at - c.offsets[item])[order], named[order])
    short: dict[bytes, list[int]] = defaultdict(list)
    for i, words in wholes(c, least):
        short[words].append(ids[i])
    return Block(ids, c, least, dict(short), np.maximum(size - width + 1, 1), tables)


def find(texts: pa.Array, block: Block, cover: float = COVER) -> list[list[tuple[int, float, bool]]]:
    """For each text (item id, share of its windows found, whether slot values differ) of the items that it holds."""
    out: list[list[tuple[int, float, bool]]] = [[] for _ in range(len(texts))]
    c = canonical(texts)
    if block.short:
        for d, words in wholes(c, block.least):
            out[d] += [(i, 1.0, False) for i in block.short.get(words, ())]
    hits: dict[tuple[int, int], list[tuple[int, int, int, bool]]] = defaultdict(list)
    for n, (distinct, first, item, place, named) in block.tables.items():
        at, h, mine = readings(c, n)
        seen = np.zeros(1 << 20, bool)
        seen[distinct >> np.uint64(44)] = True
        some = np.flatnonzero(seen[h >> np.uint64(44)])
        k = np.minimum(np.searchsorted(distinct, h[some]), len(distinct) - 1)
        right = distinct[k] == h[some]
        some, k = some[right], k[right]
        doc = np.searchsorted(c.offsets, at[some], side="right") - 1
        for d, p, j, m in zip(doc.tolist(), at[some].tolist(), k.tolist(), mine[some].tolist(), strict=True):
            for x in range(first[j], first[j + 1]):
                hits[d, int(item[x])].append((int(place[x]), p, n, m or bool(named[x])))
    for (d, i), found in sorted(hits.items()):
        least = cover * block.totals[i]
        if len({x[0] for x in found}) < min(least, ENOUGH):
            continue
        shift: dict[int, list[tuple[int, int, int, bool]]] = defaultdict(list)
        for x in found:
            shift[x[1] - x[0]].append(x)
        # Runs with the same shift are one copy of a passage; each has to agree with itself, by both readings or at least by the plain one.
        places: set[int] = set()
        differs, row = False, 0
        for run in shift.values():
            for some in (run, [x for x in run if not x[3]]):
                there, back, fine, changed = {}, {}, True, False
                for p, q, n, _ in some:
                    for j in range(n):
                        a, b = block.words.offsets[i] + p + j, q + j
                        u, v = int(block.words.raw[a]), int(c.raw[b])
                        changed |= u != v
                        # A place of like hashes that are no words', or of unlike words, is a slot.
                        if block.words.kinds[a] == NAME or (block.words.kinds[a] == WORD and u != v):
                            fine &= there.setdefault(u, v) == v and back.setdefault(v, u) == u
                if fine:
                    mine = sorted({x[0] for x in some})
                    places.update(mine)
                    differs |= changed
                    row = max([row, *np.diff(np.flatnonzero(np.diff(mine, prepend=-2, append=1 << 40) != 1)).tolist()])
                    break
        share = len(places) / block.totals[i]
        if places and (share >= cover or row >= ENOUGH):
            out[d].append((block.ids[i], float(share), differs))
    return out


def item_blocks(items: DataFrame, id_col: str, text: str, block_bytes: int = BLOCK_BYTES):
    """The items in blocks of about `block_bytes` of text, each by an aggregate-free scan of its share."""
    rows = items.where(F.col(id_col).isNotNull() & F.col(text).isNotNull()).select(F.col(id_col).cast("long").alias("id"), F.col(text).alias("t"))
    size = rows.agg(F.coalesce(F.sum(F.octet_length("t")), F.lit(0)).alias("n")).first().n
    n = max(1, -(-size // block_bytes))
    for k in range(n):
        got = rows.where(F.pmod(F.xxhash64("id", "t"), F.lit(n)) == k).toArrow()
        order = sorted(zip(got.column("id").to_pylist(), got.column("t").to_pylist(), strict=True))
        yield [x for x, _ in order], [x for _, x in order]


def scan(docs: DataFrame, items: DataFrame, text: str = "text", item_id: str = "item_id", item_text: str = "text", width: int = WIDTH, cover: float = COVER, least: int = LEAST, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """docs with `item_ids` (sorted), `coverage` (largest share found, 0 for none) and `reparameterised`; columns of those names are replaced."""
    sc = docs.sparkSession.sparkContext
    new = ["item_ids", "coverage", "reparameterised"]
    keep = [c for c in docs.columns if c not in new]
    schema = T.StructType([docs.schema[c] for c in keep] + [T.StructField("item_ids", T.ArrayType(T.LongType())), T.StructField("coverage", T.DoubleType()), T.StructField("reparameterised", T.BooleanType())])
    out = docs.select(*keep)
    for number, (ids, texts) in enumerate(item_blocks(items, item_id, item_text, block_bytes)):
        if number:
            out = kept(out)
        held = sc.broadcast(build_block(ids, texts, width, least))

        @released
        def run(batches, held=held, again=number > 0):
            for batch in cut_batches(batches, text):
                found = find(batch.column(text), held.value, cover)
                old = [batch.column(c).to_pylist() for c in new] if again else [[[]] * len(found), [0.0] * len(found), [False] * len(found)]
                ids = [sorted({*a, *(x for x, _, _ in f)}) for a, f in zip(old[0], found, strict=True)]
                share = [max([a, *(x for _, x, _ in f)]) for a, f in zip(old[1], found, strict=True)]
                other = [a or any(x for _, _, x in f) for a, f in zip(old[2], found, strict=True)]
                yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), pa.array(ids, pa.list_(pa.int64())), pa.array(share, pa.float64()), pa.array(other, pa.bool_())], [*keep, *new])

        out = out.mapInArrow(run, schema)
    return out


def clean(docs: DataFrame, items: DataFrame, **how) -> DataFrame:
    """The rows that hold no item, columns as they were."""
    new = {"item_ids": "__item_ids", "coverage": "__coverage", "reparameterised": "__reparameterised"}
    clash = [c for c in docs.columns if c in new]
    aside = docs.withColumnsRenamed({c: f"__own_{c}" for c in clash})
    left = scan(aside, items, **how).where(F.size("item_ids") == 0).drop(*new)
    return left.withColumnsRenamed({f"__own_{c}": c for c in clash}).select(*docs.columns)
