"""MinHash near-duplicates from bottom-k sketches of one hash function.

A document's set is its distinct shingles, 64-bit hashes of `width` words; its sketch is the smallest of them. Documents
with equal sets are one class, and only classes are compared.

Candidates come from inverted lists of retained values, the LISTED smallest. Two sets whose Jaccard similarity is at
least `threshold` share at least `least_shared` of these, but for a chance below MISS. So if each document's are ordered
from the rarest to the most frequent, the two share one of the first  LISTED - least_shared + 1,  and only these are listed:
frequent shingles hardly ever make lists. A list holds documents of like set sizes only, since others can't be similar.
Of two sketches' union the K smallest estimate the similarity and filter pairs; the full sets then decide.

No list is expanded into all its pairs. First each member meets the list's head, the document with the fewest values of
its own, as an unedited original has; the links found make components. Then only lists with several components are left. In
long lists with a large component those outside it are compared with its members, in blocks and by full sets, at once
for all the lists they share. Others that share an open list meet where their estimate lets them pass inside the
join, long lists dealt out in blocks. A link between documents that are in one component
already would change nothing, so none that matters is lost.

Nulls and odd input: null and empty texts have no shingles and are linked with nothing. A text of fewer than `width`
words is one shingle. A row without an id is linked with nothing and stays. Rows that share an id are one document,
linked by any of their texts. Repeated rows are in one class. Other columns are not read.
"""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .kernel import cut_batches, hash_strings, mix, ranges, released, words_of
from .tables import components, hinted, keep

LISTED, K, MISS, BLOCK, SMALL, BITS, LONG, LARGE = 64, 64, 1e-7, 256, 2 << 20, 256, 16, 12
MARKS = [f"m{j}" for j in range(BITS // 64)]


def least_shared(k: int, threshold: float) -> int:
    """The most retained values that two similar sketches of k values share but for a chance below MISS."""
    chance = 0.0
    for x in range(k + 1):
        chance += math.comb(k, x) * threshold**x * (1 - threshold) ** (k - x)
        if chance > MISS:
            return max(1, x)
    return k


def shingle_sets(texts: pa.Array, width: int) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text."""
    w = words_of(texts)
    words, size = hash_strings(w.distinct), np.diff(w.offsets)
    at = ranges(w.offsets[:-1], np.maximum(size - width + 1, 0))
    h = np.full(len(at), width, np.uint64)
    for j in range(width):
        h = h * np.uint64(0x9E3779B97F4A7C15) + words[w.codes[at + j]]
    h = mix(h).view(np.int64)
    ends = np.cumsum(np.maximum(size - width + 1, 0))
    out = []
    for i, n in enumerate(size.tolist()):
        if n >= width:
            out.append(np.unique(h[ends[i] - (n - width + 1) : ends[i]]))
        elif n:
            one = np.array([n], np.uint64)
            for x in words[w.codes[w.offsets[i] : w.offsets[i + 1]]]:
                one = one * np.uint64(0x9E3779B97F4A7C15) + x
            out.append(mix(one).view(np.int64))
        else:
            out.append(np.zeros(0, np.int64))
    return out


def sketches(docs: DataFrame, id_col: str, text: str, width: int) -> DataFrame:
    """id, n (size of the set), key (128-bit digest of the set, null if empty), low (the K smallest, sorted), MARKS (BITS bits, one set for each of them)."""

    def lists(parts, kind):
        offsets = np.concatenate([[0], np.cumsum([len(x) for x in parts])]).astype(np.int32)
        return pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(parts).astype(kind)))

    def marks(part):
        bits = np.zeros(BITS, bool)
        bits[part & (BITS - 1)] = True
        return np.packbits(bits).view(np.int64)

    @released
    def run(batches):
        for batch in cut_batches(batches, "t", SMALL):
            sets = shingle_sets(batch.column("t"), width)
            bits = np.array([marks(s[:K]) for s in sets], np.int64).reshape(-1, len(MARKS))
            keys = [xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None for s in sets]
            yield pa.RecordBatch.from_arrays(
                [batch.column("id"), pa.array([len(s) for s in sets], pa.int64()), pa.array(keys, pa.binary()), lists([s[:K] for s in sets], np.int64), *(pa.array(bits[:, j]) for j in range(len(MARKS)))],
                ["id", "n", "key", "low", *MARKS],
            )

    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text).cast("string").alias("t"))
    return rows.mapInArrow(run, "id long, n long, key binary, low array<long>, " + ", ".join(f"{m} long" for m in MARKS))


def needed(a: str, b: str, num: int, den: int):
    """The fewest sketch values that aliases a and b have to share."""
    most, shared = F.greatest(f"{a}.n", f"{b}.n"), least_shared(K, num / den)
    # A set of up to K shingles is its own sketch.
    return F.when(most <= K, F.floor(most * num / den)).otherwise(F.least(F.lit(shared), F.floor(F.least(f"{a}.n", f"{b}.n") * shared / K)))


def lost():
    """How many values of a sketch fall on the bit of another of its values."""
    return F.least(F.col("n"), F.lit(K)) - reduce(lambda p, q: p + q, [F.bit_count(m) for m in MARKS])


def sized_bits(a: str, b: str, num: int, den: int):
    """The cheap part of `alike`: sizes, and shared bits. Each shared value is a shared bit but for those that fall on another's; of a part of a sketch no more do so than of the whole, whose number is `lost`. So no pair is missed by it."""
    bits = reduce(lambda p, q: p + q, [F.bit_count(F.col(f"{a}.{m}").bitwiseAND(F.col(f"{b}.{m}"))) for m in MARKS])
    return (F.least(f"{a}.n", f"{b}.n") * den >= F.greatest(f"{a}.n", f"{b}.n") * num) & (bits >= needed(a, b, num, den) - F.least(f"{a}.lost", f"{b}.lost"))


def alike(a: str, b: str, num: int, den: int):
    """Whether sizes and sketches of aliases a and b allow a similarity of num / den: the K smallest of the union estimate it, with room for chance. Cheaper bounds come first."""
    sa, sb, most, need = F.col(f"{a}.sketch"), F.col(f"{b}.sketch"), F.greatest(f"{a}.n", f"{b}.n"), needed(a, b, num, den)
    both = F.array_intersect(sa, sb)
    union = F.slice(F.sort_array(F.array_union(sa, sb)), 1, K)
    return sized_bits(a, b, num, den) & (F.size(both) >= need) & ((most <= K) | (F.size(F.array_intersect(union, both)) >= need))


def full_sets(ids: DataFrame, docs: DataFrame, id_col: str, text: str, width: int) -> DataFrame:
    """id, s: the sets of the documents with the given ids, as bytes of sorted hashes."""
    names = hinted(keep(ids.select("id").distinct()))
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text).cast("string").alias("t")).join(names, "id", "left_semi")

    @released
    def sets(batches):
        for batch in cut_batches(batches, "t", SMALL):
            got = [s.tobytes() for s in shingle_sets(batch.column("t"), width)]
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(got, pa.binary())], ["id", "s"])

    return keep(rows.mapInArrow(sets, "id long, s binary"))


def against_members(few: pa.Table, members: pa.Table, num: int, den: int) -> pa.Table:
    """Links (a, b) of the few (id, s) to the members (id, s, inner), by counts over an inverted list of all their shingles. Inner members are linked with each other already; of links that join nothing new none is given."""
    ids, sets = members.column("id").to_pylist(), [np.frombuffer(s, np.int64) for s in members.column("s").to_pylist()]
    inner = members.column("inner").to_pylist()
    size = np.array([len(s) for s in sets], np.int64)
    values = np.concatenate(sets) if sets else np.zeros(0, np.int64)
    order = np.argsort(values, kind="stable")
    owner = np.repeat(np.arange(len(sets)), size)[order]
    distinct, start = np.unique(values[order], return_index=True)
    count = np.diff(np.append(start, len(values)))
    root: dict = {}

    def find(x):
        while (up := root.setdefault(x, x)) != x:
            x = up
        return x

    found = []
    for i, s in zip(few.column("id").to_pylist(), few.column("s").to_pylist(), strict=True):
        mine = np.frombuffer(s, np.int64)
        at = np.searchsorted(distinct, mine)
        at = at[(at < len(distinct)) & (distinct[np.minimum(at, len(distinct) - 1)] == mine)] if len(distinct) else at[:0]
        both = np.bincount(owner[ranges(start[at], count[at])], minlength=len(sets))
        for j in np.flatnonzero((both > 0) & (den * both >= num * (len(mine) + size - both))).tolist():
            x, y = find(i), find("inner" if inner[j] else ids[j])
            if x != y:
                root[x] = y
                found.append((min(i, ids[j]), max(i, ids[j])))
    return pa.table({"a": pa.array([x for x, _ in found], pa.int64()), "b": pa.array([y for _, y in found], pa.int64())})


def confirmed(pairs: DataFrame, docs: DataFrame, id_col: str, text: str, width: int, num: int, den: int) -> DataFrame:
    """The pairs (a, b) whose full sets have a Jaccard similarity of num / den or more. Sets are made for the documents of pairs only."""
    held = full_sets(pairs.select(F.explode(F.array("a", "b")).alias("id")), docs, id_col, text, width)

    @released
    def right(batches):
        for batch in batches:
            ok = []
            for x, y in zip(batch.column("x").to_pylist(), batch.column("y").to_pylist(), strict=True):
                x, y = np.frombuffer(x, np.int64), np.frombuffer(y, np.int64)
                both = len(np.intersect1d(x, y, assume_unique=True))
                ok.append(both > 0 and den * both >= num * (len(x) + len(y) - both))
            yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b")], ["a", "b"]).filter(pa.array(ok, pa.bool_()))

    with_a = pairs.join(held.select(F.col("id").alias("a"), F.col("s").alias("x")), "a")
    both = with_a.join(held.select(F.col("id").alias("b"), F.col("s").alias("y")), "b").select("a", "b", "x", "y")
    return both.mapInArrow(right, "a long, b long").distinct()


def listed(classes: DataFrame, num: int, den: int) -> DataFrame:
    """v, size, g, id, n, own: the retained values, from the rarest, that have to be listed for no similar pair to be missed, each under its size group g and the next. own: how many of the document's retained values no other has. Values of one class only are left out."""
    shared = least_shared(LISTED, num / den)
    each = classes.select("id", "n", F.least(F.size("low"), F.lit(LISTED)).alias("s"), F.explode(F.slice("low", 1, LISTED)).alias("v"))
    often = each.groupBy("v").agg(F.count("*").alias("c")).where("c > 1")
    # Sets of up to LISTED * num / den shingles, and any that are similar to them, are listed as a whole.
    whole = F.col("s") <= LISTED * num // den
    need = F.when(whole, F.ceil(F.col("s") * num / den)).otherwise(F.lit(shared))
    mine = each.join(often, "v").groupBy("id", "n", "s").agg(F.array_sort(F.collect_list(F.struct("c", "v"))).alias("l"))
    own = F.col("s") - F.size("l")
    first = mine.select("id", "n", own.alias("own"), F.explode(F.slice("l", F.lit(1), F.greatest(F.lit(0), F.size("l") - need + 1).cast("int"))).alias("x"))
    group = F.floor(F.log(F.col("n").cast("double")) / math.log(1.0001 * den / num)).cast("int")
    return first.select(F.col("x.v").alias("v"), group.alias("g"), F.explode(F.array(group, group + 1)).alias("size"), "id", "n", "own")


def links(docs: DataFrame, classes: DataFrame, id_col: str, text: str, width: int, num: int, den: int) -> DataFrame:
    """Enough of the links (a, b) between classes for their components to be right. classes: id, n, low, MARKS."""
    at = ["v", "size"]
    # Sets of so few shingles that only an equal one is similar enough are in no list.
    alone = max(n for n in range(den + 1) if n * den < num * (n + 1) or not n)
    some = classes.where(F.col("n") > alone)
    posts = keep(listed(some, num, den))
    # A list without a document of its own size group says nothing that the next smaller one of its value doesn't say.
    heads = posts.groupBy(*at).agg(F.min(F.struct("own", "id", "n")).alias("h"), F.count("*").alias("m"), F.max("g").alias("top")).where("m > 1 and top = size").select(*at, F.col("h.id").alias("a"), F.col("h.n").alias("an"))
    sized = F.least("n", "an") * den >= F.greatest("n", "an") * num
    pairs = posts.join(heads, (posts.v == heads.v) & (posts.size == heads.size) & (F.col("id") != F.col("a")) & sized).select(F.least("a", "id").alias("a"), F.greatest("a", "id").alias("b")).distinct()
    # A sketch is the upper halves of the values.
    sketch = some.select("id", "n", F.transform("low", lambda x: F.shiftright(x, 32).cast("int")).alias("sketch"), *MARKS, lost().alias("lost"))
    side = lambda t, as_, name: t.withColumnRenamed("id", as_).alias(name)
    # Bits travel with all pairs, sketches only with those that pass by them.
    bits = sketch.drop("sketch")
    pairs = pairs.join(side(bits, "a", "x"), "a").join(side(bits, "b", "y"), "b").where(sized_bits("x", "y", num, den)).select("a", "b")
    a, b = side(sketch, "a", "x"), side(sketch, "b", "y")
    near = keep(pairs.join(a, "a").join(b, "b").where(alike("x", "y", num, den)).select("a", "b").distinct())
    first = keep(confirmed(near, docs, id_col, text, width, num, den))

    parts = keep(components(first))
    placed = posts.join(parts.withColumnRenamed("node", "id"), "id", "left").select(*at, "g", "id", F.coalesce("component", "id").alias("part"))
    sizes = placed.groupBy(*at, "part").agg(F.count("*").alias("c"), F.max("g").alias("top"))
    sizes = sizes.groupBy(*at).agg(F.max(F.struct("c", "part")).alias("x"), F.sum("c").alias("m"), F.count("*").alias("parts"), F.max("top").alias("top"))
    open_ = sizes.where("parts > 1 and top = size").select(*at, F.col("x.part").alias("main"), "m", F.when(F.col("m") >= LONG, F.col("x.c")).otherwise(0).alias("c"))
    rest = keep(placed.join(open_, at))

    # In long lists those outside a large component meet all its members and each other, set against set, in blocks of both.
    large = rest.where((F.col("c") >= LARGE) & (F.col("part") != F.col("main"))).select(F.col("main").alias("component"), "id").distinct()
    second_side = parts.select("component", F.col("node").alias("id"), F.lit(True).alias("inner")).unionByName(large.withColumn("inner", F.lit(False)))
    parted = lambda t, n: t.groupBy("component").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias(n))
    blocks = keep(parted(large, "xs").join(parted(second_side, "ms"), "component"))
    spread = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    dealt = lambda n: F.pmod(F.xxhash64("id"), F.col(n)).cast("int")
    few = keep(large.join(blocks, "component").select("component", "id", F.lit(False).alias("inner"), spread("ms").alias("mb"), dealt("xs").alias("xb")))
    members = keep(second_side.join(blocks, "component").select("component", "id", "inner", dealt("ms").alias("mb"), spread("xs").alias("xb")))
    held = full_sets(few.select("id").unionByName(members.select("id")), docs, id_col, text, width)
    key = ["component", "mb", "xb"]
    sides = [t.join(held.select(F.col("id").alias("id"), F.col("s").alias("s")), "id").select(*(F.col(c).alias(c) for c in (*key, "id", "inner", "s"))).groupBy(*key) for t in (few, members)]
    second = sides[0].cogroup(sides[1]).applyInArrow(lambda x, y: against_members(x, y, num, den), "a long, b long")

    # Members of other open lists meet where their estimate allows it.
    wide = rest.where(F.col("c") < LARGE).withColumn("blocks", F.ceil(F.col("m") / BLOCK).cast("int"))
    # With all of its documents' values in such lists: a pair is looked at in the first list that it shares only.
    listed_in = wide.groupBy("id").agg(F.collect_set("v").alias("vs"))
    wide = keep(wide.join(bits.join(listed_in, "id"), "id"))
    all_ = wide.withColumn("block", dealt("blocks")).alias("y")
    some_ = wide.where("part <> main").withColumn("block", spread("blocks")).alias("x")
    once = (F.col("y.part") == F.col("y.main")) | (F.col("x.id") < F.col("y.id"))
    on = (F.col("x.v") == F.col("y.v")) & (F.col("x.size") == F.col("y.size")) & (F.col("x.block") == F.col("y.block")) & (F.col("x.part") != F.col("y.part")) & (F.col("x.size") == F.greatest("x.g", "y.g")) & once
    on = on & sized_bits("x", "y", num, den) & (F.array_min(F.array_intersect("x.vs", "y.vs")) == F.col("x.v"))
    more = some_.join(all_, on).select(F.least("x.id", "y.id").alias("a"), F.greatest("x.id", "y.id").alias("b")).distinct()
    more = more.join(near, ["a", "b"], "left_anti").join(a, "a").join(b, "b").where(alike("x", "y", num, den)).select("a", "b")
    more = keep(more)
    return first.unionByName(second).unionByName(confirmed(more, docs, id_col, text, width, num, den))


def groups(docs: DataFrame, id_col: str = "doc_id", text: str = "text", width: int = 5, num: int = 4, den: int = 5) -> DataFrame:
    """id, n_shingles, component_id (the smallest id reachable by links, its own for a document without any) for every row."""
    rows = keep(sketches(docs, id_col, text, width))
    full = rows.where("key is not null and id is not null")
    classes = keep(full.groupBy("key").agg(F.min("id").alias("id"), F.first("n").alias("n"), F.first("low").alias("low"), *(F.first(m).alias(m) for m in MARKS)))
    found = components(links(docs, classes, id_col, text, width, num, den))
    of_class = classes.join(found.withColumnRenamed("node", "id"), "id", "left").select("key", F.coalesce("component", "id").alias("component_id"))
    # A row without an id isn't sought; it has no component.
    out = rows.withColumn("sought", F.when(F.col("id").isNotNull(), F.col("key"))).join(of_class.withColumnRenamed("key", "sought"), "sought", "left")
    return out.select("id", F.col("n").alias("n_shingles"), F.coalesce("component_id", "id").alias("component_id"))


def dedup(docs: DataFrame, id_col: str = "doc_id", text: str = "text", **how) -> DataFrame:
    """The rows of docs without those that a row with a smaller id stands for; columns as they were. Of rows that share an id one stays."""
    found = keep(groups(docs, id_col, text, **how))
    gone = hinted(keep(found.where("id <> component_id").select(F.col("id").alias("__gone")).distinct()))
    left = docs.join(gone, F.col(id_col).cast("long") == F.col("__gone"), "left_anti")
    again = found.where("id is not null and n_shingles > 0").groupBy("id").agg(F.count("*").alias("c")).where("c > 1").limit(1).count()
    return left if not again else left.where(F.col(id_col).isNotNull()).dropDuplicates([id_col]).unionByName(left.where(F.col(id_col).isNull()))
