"""Long grams in packed arrays: counting them, and what they give to gaps, with a few bytes a gram on disk.

A gram of numbered symbols is a number of 64 bits, and sorted numbers with their counts are kept as compressed differences.
Grams are dealt out by their first two symbols, so a task has all that may follow a gram; what may precede it is what follows
in grams that are read backward. A gram that no test text holds is left out only once all counts that depend on it are made.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import chain
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import kernels

#: Symbols that are counted in arrays at once.
BATCH_SYMBOLS = 1_000_000
#: Distinct windows, of 16 bytes each, that a task holds before it lets go of their counts.
HELD_WINDOWS = 6_000_000
#: Parts that grams are dealt out to, and grams that a part of a model should have.
LEAST_PARTS, MOST_PARTS, PART_GRAMS = 32, 1024, 1_000_000
#: Grams that a task numbers at once.
BATCH_GRAMS = 1_000_000


def shrunk(numbers: np.ndarray) -> bytes:
    """Integers as compressed planes of their bytes."""
    raw = np.ascontiguousarray(numbers.astype(np.uint64).view(np.uint8).reshape(-1, 8).T).tobytes()
    return len(raw).to_bytes(8, "little") + pa.Codec("zstd", 1).compress(raw, asbytes=True)


def grown(data: bytes) -> np.ndarray:
    size = int.from_bytes(data[:8], "little")
    raw = np.frombuffer(pa.Codec("zstd").decompress(data[8:], size, asbytes=True), np.uint8) if size else np.zeros(0, np.uint8)
    return np.ascontiguousarray(raw.reshape(8, -1).T).view(np.uint64).ravel()


def shrunk_keys(keys: np.ndarray) -> bytes:
    """Ascending keys as their differences."""
    return shrunk(np.diff(keys, prepend=np.uint64(0)))


def grown_keys(data: bytes) -> np.ndarray:
    return np.cumsum(grown(data), dtype=np.uint64)


def part_of(first: np.ndarray, second: np.ndarray, parts: int) -> np.ndarray:
    """The part of grams that begin with these two symbols, 0 where there is none."""
    mixed = kernels.scrambled((first.astype(np.uint64) << np.uint64(21)) | second.astype(np.uint64))
    return (mixed % np.uint64(parts)).astype(np.uint16)


def dealt(part: np.ndarray):
    """Each part with its places in order."""
    order = np.argsort(part, kind="stable")
    at = part[order]
    first = np.flatnonzero(np.append(True, at[1:] != at[:-1])) if len(at) else []
    for a, b in zip(first, [*first[1:], len(at)], strict=True):
        yield int(at[a]), order[a:b]


def summed(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct keys in order, and the sums of their counts."""
    order = np.argsort(keys)
    keys, counts = keys[order], counts[order]
    first = np.flatnonzero(np.append(True, keys[1:] != keys[:-1])) if len(keys) else np.zeros(0, np.int64)
    return keys[first], np.add.reduceat(counts, first) if len(first) else counts


def count_grams(lines: DataFrame, n_max: int) -> DataFrame:
    """lang, n, gram, cnt for n from 1 to n_max, see `model.count_grams`: only the longest windows are shuffled, and single symbols; a task that has all windows with the same beginning takes the other grams from them."""
    parts = min(MOST_PARTS, max(LEAST_PARTS, int(lines.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    columns = ["lang", "part", "n", "symbols", "keys", "sizes", "counts"]

    def row(lang, part, n, symbols, keys, sizes, counts):
        return pa.RecordBatch.from_arrays([pa.array([x], t) for x, t in zip((lang, part, n, symbols, keys, sizes, shrunk(counts)), (pa.string(), pa.int32(), pa.int32(), pa.string(), pa.binary(), pa.binary(), pa.binary()), strict=True)], columns)

    def packed(held):
        """What a task holds, by parts."""
        symbols, bits = "".join(held.symbols), np.uint64(held.bits)
        point, mask = np.append(np.uint32(0), kernels.points(symbols)), np.uint64((1 << held.bits) - 1)
        while held.held:
            lang, (keys, counts) = held.held.popitem()
            one = (keys >> (bits * np.uint64(n_max - 1))).astype(np.int64)
            two = ((keys >> (bits * np.uint64(n_max - 2))) & mask).astype(np.int64)
            for part, at in dealt(part_of(point[one], point[two], parts)):
                yield row(lang, part, n_max, symbols, shrunk_keys(keys[at]), None, counts[at])
            total = np.bincount(one, counts, len(point)).astype(np.int64)
            seen = np.flatnonzero(total)
            for part, at in dealt(part_of(point[seen], np.zeros(len(seen)), parts)):
                yield row(lang, part, 1, symbols, shrunk_keys(seen[at].astype(np.uint64)), None, total[seen[at]])

    def spelled(lang, lines):
        """Of lines with too many symbols to be numbered."""
        w, c = kernels.count_windows(lines, n_max)
        one = np.array([ord(x[0]) for x in w], np.uint32)
        two = np.array([ord(x[1]) if len(x) > 1 else 0 for x in w], np.uint32)
        for part, at in dealt(part_of(one, two, parts)):
            some = [w[i] for i in at]
            yield row(lang, part, n_max, None, "".join(some).encode("utf-8", "surrogatepass"), shrunk(np.array([len(x) for x in some])), c[at])
        symbols, of = np.unique(one, return_inverse=True)
        total = np.bincount(of, c).astype(np.int64)
        for part, at in dealt(part_of(symbols, np.zeros(len(symbols)), parts)):
            yield row(lang, part, 1, None, "".join(map(chr, symbols[at])).encode("utf-8", "surrogatepass"), shrunk(np.ones(len(at))), total[at])

    def run(batches):
        held, own, size = kernels.WindowCounts(n_max), {}, 0
        for batch in chain(batches, [None]):
            if batch is not None:
                langs = batch.column("lang").dictionary_encode()
                at, texts = langs.indices.to_numpy(zero_copy_only=False), batch.column("line")
                for k, lang in enumerate(langs.dictionary.to_pylist()):
                    some = texts.filter(pa.array(at == k)).to_pylist()
                    own.setdefault(lang, []).extend(some)
                    size += sum(map(len, some))
            if batch is None or size > BATCH_SYMBOLS:
                for lang, some in own.items():
                    if not held.add(lang, some):
                        yield from packed(held)
                        held = kernels.WindowCounts(n_max)
                        if not held.add(lang, some):
                            yield from spelled(lang, some)
                own, size = {}, 0
            if batch is None or len(held) > HELD_WINDOWS:
                yield from packed(held)

    def rows(lang, n, grams, counts):
        return pa.RecordBatch.from_arrays([pa.array([lang], pa.string()).take(pa.array(np.zeros(len(grams), np.int32))), pa.array(np.full(len(grams), n, np.int32)), grams, pa.array(counts.astype(np.int64))], ["lang", "n", "gram", "cnt"])

    def merged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Of one language and part."""
        found = {1: [], n_max: []}
        lang = None
        for batch in batches:
            for x in batch.to_pylist():
                lang = x["lang"]
                found[x["n"]].append(x)
        for n, some in found.items():
            held = kernels.WindowCounts(n)
            held.bits = min(21, 64 // n_max)
            symbols = sorted(set().union(*(x["symbols"] or () for x in some)))
            if any(x["symbols"] is None for x in some) or len(symbols) >= 1 << held.bits:
                yield from apart(lang, n, some, held.bits)
                continue
            held.symbols = ["", *symbols]
            number = {x: k for k, x in enumerate(held.symbols)}
            mask, keys, counts = np.uint64((1 << held.bits) - 1), [], []
            for x in some:
                old, to = grown_keys(x["keys"]), np.array([0, *(number[s] for s in x["symbols"])], np.uint64)
                new = np.zeros(len(old), np.uint64)
                for j in range(n):
                    shift = np.uint64(held.bits * j)
                    new |= to[((old >> shift) & mask).astype(np.int64)] << shift
                keys.append(new)
                counts.append(grown(x["counts"]).astype(np.int64))
            if some:
                held.held[lang] = summed(np.concatenate(keys), np.concatenate(counts))
                for x in held.grams(least=min(2, n)):
                    yield rows(*x)

    def apart(lang, n, some, bits):
        """Of symbols that are too many to be numbered: by the grams' texts."""
        texts, counts = [], []
        for x in some:
            c = grown(x["counts"]).astype(np.int64)
            if x["symbols"] is None:
                flat, ends = x["keys"].decode("utf-8", "surrogatepass"), np.cumsum(grown(x["sizes"]).astype(np.int64)).tolist()
                texts += [flat[a:b] for a, b in zip([0, *ends[:-1]], ends, strict=True)]
            else:
                key, names = grown_keys(x["keys"]), ["", *x["symbols"]]
                codes = (key[:, None] >> (np.uint64(bits) * np.arange(n - 1, -1, -1).astype(np.uint64))) & np.uint64((1 << bits) - 1)
                texts += ["".join(names[k] for k in r) for r in codes.tolist()]
            counts.append(c)
        w, c = pa.array(texts, pa.string()), pa.array(np.concatenate(counts))
        for k in range(min(2, n), n + 1):
            whole = pc.greater_equal(pc.utf8_length(w), k)
            got = pa.table({"w": pc.utf8_slice_codeunits(w.filter(whole), 0, k), "c": c.filter(whole)}).group_by("w").aggregate([("c", "sum")]).combine_chunks()
            for part in got.to_batches():
                yield rows(lang, k, part.column("w"), part.column("c_sum").to_numpy())

    made = lines.select("lang", "line").where(F.col("lang").isNotNull() & F.col("line").isNotNull()).mapInArrow(run, "lang string, part int, n int, symbols string, keys binary, sizes binary, counts binary")
    return made.groupBy("lang", "part").applyInArrow(merged, "lang string, n int, gram string, cnt long")


class Alphabet(NamedTuple):
    """Symbols in order, numbered from 1, and how many bits a number has."""

    symbols: str
    bits: int

    def numbers(self, grams: pa.Array, n: int) -> np.ndarray:
        """The symbols' numbers of grams of n symbols, a row for each."""
        code = np.zeros(0x110000, np.uint8 if self.bits <= 8 else np.uint32)
        code[kernels.points(self.symbols)] = np.arange(1, len(self.symbols) + 1)
        return code[kernels.points("".join(grams.to_pylist()))].reshape(-1, n)

    def packed(self, numbers: np.ndarray) -> np.ndarray:
        key = np.zeros(len(numbers), np.uint64)
        for j in range(numbers.shape[1]):
            key = (key << np.uint64(self.bits)) | numbers[:, j].astype(np.uint64)
        return key

    def hashed(self, keys: np.ndarray, n: int, backward: bool) -> np.ndarray:
        """`kernels.gram_keys` of packed grams, which may be packed backward."""
        point, mask = np.append(np.uint32(0), kernels.points(self.symbols)).astype(np.uint64), np.uint64((1 << self.bits) - 1)
        flat = np.zeros(len(keys), np.uint64)
        for j in range(n):
            x = point[((keys >> np.uint64(self.bits * (j if backward else n - 1 - j))) & mask).astype(np.int64)]
            flat = kernels.next_key(flat, x, n)
        return flat


def alphabet(grams: DataFrame, seen: DataFrame, width: int) -> Alphabet | None:
    """Of all grams; None if grams of `width` symbols can't be packed."""
    bits = min(21, 64 // width)
    one = grams.select("n", "gram").unionByName(seen.select("n", "gram")).where("n = 1").select("gram").distinct().limit(1 << bits).collect()
    return None if len(one) >= 1 << bits else Alphabet("".join(sorted(r.gram for r in one)), bits)


VALUES = "lang string, base string, n int, dir string, keys binary, data array<binary>"


def values(grams: DataFrame, seen: DataFrame, known: Alphabet, bases, ranks, levels) -> DataFrame:
    """lang, base, n, dir, keys, data: what the windows of `seen` give to gaps at all levels, as `profile.level_values` does, in packed pieces; see `read`. seen: lang, n, gram. Forward and backward is one thing, with the grams read backward."""
    tops = {(r.lang, r.n): (r.most, r.rows) for r in grams.groupBy("lang", "n").agg(F.max("cnt").alias("most"), F.count("*").alias("rows")).collect()}
    parts = int(min(MOST_PARTS, max(LEAST_PARTS, sum(rows for _, rows in tops.values()) // PART_GRAMS)))
    top, kinds = ranks[-1] + 1, (pa.string(), pa.string(), pa.int32(), pa.int32(), pa.bool_(), pa.bool_(), pa.binary(), pa.binary())
    columns = ["lang", "dir", "part", "n", "is_edge", "is_seen", "keys", "counts"]

    def row(*x):
        return pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip(x, kinds, strict=True)], columns)

    def packed(own):
        for (lang, n, is_seen), some in own.items():
            codes = known.numbers(pa.concat_arrays([x for x, _ in some]), n)
            counts = np.concatenate([c for _, c in some])
            for way in "fb":
                turned = codes if way == "f" else codes[:, ::-1]
                key = known.packed(turned)
                order = np.argsort(key)
                key, c, one = key[order], counts[order], turned[order, 0]
                two = turned[order, 1] if n > 1 else np.zeros(len(key))
                for is_edge, second in ((False, two), (True, np.zeros(len(key))))[: 1 + (n == 2)]:  # the transitions of a single symbol go to where that is
                    for part, at in dealt(part_of(one, second, parts)):
                        yield row(lang, way, part, n, is_edge, is_seen, shrunk_keys(key[at]), None if is_seen else shrunk(c[at]))

    def run(batches):
        own, size = {}, 0
        for batch in chain(batches, [None]):
            if batch is not None:
                table = pa.Table.from_batches([batch])
                for x in table.group_by(["lang", "n", "is_seen"]).aggregate([]).to_pylist():
                    some = batch.filter(pc.and_(pc.and_(pc.equal(batch["lang"], x["lang"]), pc.equal(batch["n"], x["n"])), pc.equal(batch["is_seen"], x["is_seen"])))
                    own.setdefault((x["lang"], x["n"], x["is_seen"]), []).append((some["gram"], some["cnt"].to_numpy()))
                size += batch.num_rows
            if batch is None or size > BATCH_GRAMS:
                yield from packed(own)
                own, size = {}, 0

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Of one language, direction and part."""
        lang, way, held = None, None, {}
        for batch in batches:
            for x in batch.to_pylist():
                lang, way = x["lang"], x["dir"]
                held.setdefault((x["n"], x["is_edge"], x["is_seen"]), []).append((grown_keys(x["keys"]), None if x["is_seen"] else grown(x["counts"]).astype(np.int64)))
        none = np.zeros(0, np.uint64), np.zeros(0, np.int64)
        for k, some in held.items():
            keys = np.concatenate([x for x, _ in some])
            held[k] = (np.sort(keys), None) if k[2] else summed(keys, np.concatenate([c for _, c in some]))
        within = lambda keys, of: of[np.minimum(np.searchsorted(of, keys), len(of) - 1)] == keys if len(of) else np.zeros(len(keys), bool)

        def piece(base, n, keys, *data):
            return pa.RecordBatch.from_arrays([pa.array([lang]), pa.array([base]), pa.array([n], pa.int32()), pa.array([way]), pa.array([shrunk_keys(keys)], pa.binary()), pa.array([[shrunk(x) for x in data]], pa.list_(pa.binary()))], ["lang", "base", "n", "dir", "keys", "data"])

        for n in ranks:
            own, count = held.get((n, False, False), none)
            wanted = held.get((n, False, True), none)[0]
            if not len(own):
                continue
            most = tops[lang, n][0]
            if "p" in bases and way == "f":
                some = within(own, wanted)
                yield piece("p", n, own[some], count[some], np.full(some.sum(), most))
            edge, times = held.get((n + 1, n == 1, False), none)
            gram = edge >> np.uint64(known.bits)
            there = within(gram, own)
            edge, times, gram = edge[there], times[there], gram[there]
            if not len(edge):
                continue
            first = np.flatnonzero(np.append(True, gram[1:] != gram[:-1]))
            size = np.diff(np.append(first, len(gram)))
            whole = count[np.searchsorted(own, gram[first])]
            strongest = np.repeat(np.maximum.reduceat(times, first), size)
            of = np.repeat(whole, size)
            holds = [(times >= t * strongest) & (of >= t * most) for t in levels]
            if "tf" in bases:
                some = within(gram[first], wanted)
                yield piece("tf", n, gram[first][some], *(np.add.reduceat(h, first, dtype=np.int64)[some] for h in holds))
            if "cp" in bases:
                some = within(edge, held.get((n + 1, n == 1, True), none)[0])
                yield piece("cp", n, edge[some], times[some], of[some], *(h[some] for h in holds))

    each = grams.select("lang", "n", "gram", "cnt", F.lit(False).alias("is_seen")).unionByName(seen.select("lang", "n", "gram", F.lit(0).cast("long").alias("cnt"), F.lit(True).alias("is_seen")))
    sent = each.where((F.col("n") <= top) & F.col("lang").isNotNull()).mapInArrow(run, "lang string, dir string, part int, n int, is_edge boolean, is_seen boolean, keys binary, counts binary")
    return sent.groupBy("lang", "dir", "part").applyInArrow(made, VALUES)


def read(pieces: list[dict], known: Alphabet, base: str, n: int, level: int, theta: float) -> kernels.Slice:
    """The slice of a rank at the level of that number, from all pieces of its base and rank; windows without a value are left out."""
    place, ways = kernels.place_of(base, n), {}
    for x in pieces:
        keys, data = grown_keys(x["keys"]), x["data"]
        if base == "tf":
            v = grown(data[level]).astype(np.float64)
        else:
            part, whole = (grown(d).astype(np.float64) for d in data[:2])
            v = part / whole
            v[part < theta * whole if base == "p" else grown(data[2 + level]) == 0] = 0.0
        keys, v = known.hashed(keys[v != 0], place.width, x["dir"] == "b"), v[v != 0]
        for way in "fb" if base == "p" else x["dir"]:
            ways.setdefault(way, []).append((keys, v))
    every = np.unique(np.concatenate([np.zeros(0, np.uint64), *(k for some in ways.values() for k, _ in some)]))
    out = []
    for way in "fb":
        out.append(np.zeros(len(every)))
        for keys, v in ways.get(way, []):
            out[-1][np.searchsorted(every, keys)] = v
    return kernels.Slice(place, every, *out, kernels.Lookup(every))
