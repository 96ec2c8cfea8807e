"""The array engine: profiles, breaks and tokens of many texts at once in numpy.

Texts lie end to end, and a gap is kept at the symbol before it, so a batch is a few passes over flat arrays however long
its texts are. A model slice is sorted window keys with their values, so all gaps are looked up by one search. Results
equal those of the row engine.
"""

from __future__ import annotations

from typing import NamedTuple

import numpy as np
import pyarrow as pa

DIGITS = 9


def points(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)


def gram_keys(p: np.ndarray, n: int) -> np.ndarray:
    """A 64-bit key for each gram of n symbols; exact for up to three symbols, a hash beyond."""
    size = max(len(p) - n + 1, 0)
    key = np.zeros(size, np.uint64)
    for j in range(n):
        key = next_key(key, p[j : j + size].astype(np.uint64), n)
    return key


def next_key(key: np.ndarray, x: np.ndarray, n: int) -> np.ndarray:
    """The keys of grams of n symbols, as far as the symbols x."""
    return (key << np.uint64(21)) | x if n <= 3 else (key ^ x) * np.uint64(0x9E3779B97F4A7C15) + (key >> np.uint64(29))


class Place(NamedTuple):
    """Which window gives a gap its value: of `width` symbols, beginning so many symbols before the gap, forward and backward."""

    width: int
    forward: int
    backward: int


def place_of(base: str, n: int, kind: str = "symbol") -> Place:
    """Freedom and probability are those of the gram that ends (or begins) at the gap; conditional probability is that of the transition across it."""
    if base != "cp":
        return Place(n, n, 0)
    return Place(n + 1, n, 1) if kind == "symbol" else Place(2 * n, n, n)


class Slice(NamedTuple):
    """Values of one corpus and rank: sorted window keys and their forward and backward values; a row of values for each level if they are tables."""

    place: Place
    keys: np.ndarray
    forward: np.ndarray
    backward: np.ndarray
    lookup: Lookup | None = None  # of the keys, where many gaps are looked up


def make_slice(windows: list[str], forward, backward, place: Place | None = None) -> Slice:
    """forward and backward: by window, or tables of levels by windows. Without a place that of single grams is meant."""
    place = place or place_of("tf", len(windows[0]) if windows else 1)
    flat = points("".join(windows)).reshape(-1, place.width)
    keys = np.zeros(len(windows), np.uint64)
    if len(windows):
        keys = gram_keys(flat.ravel(), place.width)[:: place.width]
    order = np.argsort(keys)
    return Slice(place, keys[order], np.asarray(forward, np.float64)[..., order], np.asarray(backward, np.float64)[..., order])


class Texts(NamedTuple):
    """Texts of a symbol or more, end to end."""

    points: np.ndarray
    first: np.ndarray  # where each begins
    size: np.ndarray

    @property
    def left(self) -> np.ndarray:
        """Symbols from each on to the end of its text."""
        return np.repeat(self.first + self.size, self.size) - np.arange(len(self.points))


def texts_of(texts: list[str]) -> Texts:
    size = np.fromiter(map(len, texts), np.int64, len(texts))
    return Texts(points("".join(texts)), np.cumsum(size) - size, size)


def base(t: Texts, s: Slice, level: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Forward and backward values at the gaps; nan where the window doesn't fit and at the ends of texts, 0 for an unseen one."""
    total, w = len(t.points), s.place.width
    keys = gram_keys(t.points, w)
    if s.lookup is not None:
        at = s.lookup.of(keys)
        seen = at >= 0
    else:
        at = np.minimum(np.searchsorted(s.keys, keys), max(len(s.keys) - 1, 0))
        seen = s.keys[at] == keys if len(s.keys) else np.zeros(len(keys), bool)
    left = t.left
    done = np.repeat(t.size, t.size) - left
    out = []
    for values, back in ((s.forward, s.place.forward), (s.backward, s.place.backward)):
        values = values if level is None else values[level]
        start = np.arange(total) + 1 - back
        fits = (done + 1 >= back) & (left - 1 + back >= w) & (left > 1)
        v = np.full(total, np.nan)
        i = start[fits]
        v[fits] = np.where(seen[i], values[at[i]], 0.0) if len(s.keys) else 0.0
        out.append(v)
    return out[0], out[1]


def offshoot(t: Texts, v: np.ndarray, kind: str, direction: str) -> np.ndarray:
    """An offshoot of the values of one direction, the ends padded with their own value."""
    if kind == "raw":
        return v
    if kind == "variance":
        ok = ~np.isnan(v)
        with np.errstate(all="ignore"):
            mean = np.add.reduceat(np.where(ok, v, 0.0), t.first) / np.add.reduceat(ok.astype(np.int64), t.first)
        return v - np.repeat(mean, t.size)
    before, after = np.append(np.nan, v[:-1]), np.append(v[1:], np.nan)
    before, after = np.where(np.isnan(before), v, before), np.where(np.isnan(after), v, after)
    if kind == "derivative":
        return v - before if direction == "f" else v - after
    return (v - before) - (after - v)


def scaled(t: Texts, v: np.ndarray) -> np.ndarray:
    """v over its largest value in the text, rounded; 0 where that is not above 0."""
    most = np.repeat(np.fmax.reduceat(v, t.first), t.size)
    with np.errstate(all="ignore"):
        return np.where(np.isnan(v), np.nan, np.where(most > 0, round_half_up(v / most), 0.0))


def round_half_up(v: np.ndarray, digits: int = DIGITS) -> np.ndarray:
    """Rounds halves away from zero."""
    return np.copysign(np.floor(np.abs(v) * 10**digits + 0.5) / 10**digits, v)


def over_ranks(way: list[np.ndarray]) -> np.ndarray:
    """The mean over ranks of the values of one direction."""
    if len(way) == 1:
        return way[0]
    with np.errstate(all="ignore"):
        return round_half_up(sum(np.nan_to_num(x, nan=0.0) for x in way) / sum((~np.isnan(x)).astype(np.float64) for x in way))


def combined(forward: list[np.ndarray], backward: list[np.ndarray], combine: str = "max") -> np.ndarray:
    """The mean over ranks in each direction, then the directions together; minus infinity where there is no value."""
    f, b = over_ranks(forward), over_ranks(backward)
    if combine == "max":
        out = np.fmax(f, b)
    elif combine == "mean":
        out = round_half_up((np.where(np.isnan(f), b, f) + np.where(np.isnan(b), f, b)) / 2)
    else:
        out = f if combine == "forward" else b
    return np.where(np.isnan(out), -np.inf, out)


def local_maxima(forward: list[np.ndarray], backward: list[np.ndarray], combine: str, threshold: float) -> np.ndarray:
    """Infinity at the gaps where a direction has a local maximum above the threshold, above its left neighbour and not below its right one; minus infinity elsewhere."""
    out = np.full(len(forward[0]), -np.inf)
    for way in {"forward": (forward,), "backward": (backward,)}.get(combine, (forward, backward)):
        v = over_ranks(way)
        v = np.where(np.isnan(v), -np.inf, v)
        out[(v > np.append(-np.inf, v[:-1])) & (v >= np.append(v[1:], -np.inf)) & (v > threshold)] = np.inf
    return out


def backed_off(values: list[np.ndarray]) -> list[np.ndarray]:
    """Values of ascending ranks; where one is 0, as of an unseen window, that of the next lower rank that has one stands in."""
    out, lower = [], np.zeros(len(values[0])) if values else None
    for v in values:
        lower = np.where(v > 0, v, lower)
        out.append(np.where(np.isnan(v), np.nan, lower))
    return out


def scores(t: Texts, slices: dict[int, Slice], kind: str = "variance", combine: str = "max", scale: str = "sequence", local: float | None = None, backoff: tuple[int, ...] = ()) -> np.ndarray:
    """A score for each symbol, that of the gap after it; minus infinity at the ends of texts. scale: by the text's largest value, the slice's ("model"), or not at all ("none"). local: local maxima above it are breaks. backoff: the ranks that are meant, where slices also has the lower ones that unseen windows are taken for."""
    if not slices or not len(t.points):
        return np.full(len(t.points), -np.inf)
    order = sorted(slices)
    each = dict(zip("fb", zip(*(base(t, slices[n]) for n in order), strict=True), strict=True))
    ways: dict[str, list] = {"f": [], "b": []}
    for d, values in each.items():
        for n, v in zip(order, backed_off(values) if backoff else values, strict=True):
            if backoff and n not in backoff:
                continue
            made = offshoot(t, v, kind, d)
            if scale == "sequence":
                made = scaled(t, made)
            elif scale == "none":
                made = round_half_up(made)
            else:
                top = (slices[n].forward if d == "f" else slices[n].backward).max(initial=0.0)
                made = round_half_up(made / top) if top > 0 else np.where(np.isnan(made), np.nan, 0.0)
            ways[d].append(made)
    if local is not None:
        return local_maxima(ways["f"], ways["b"], combine, local)
    return combined(ways["f"], ways["b"], combine)


def spans(t: Texts, cut: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where the tokens begin and end, if there is a break after each symbol where `cut` holds, and after every text."""
    cut = cut.copy()
    cut[t.first + t.size - 1] = True
    ends = np.flatnonzero(cut) + 1
    return np.concatenate([[0], ends[:-1]]).astype(np.int64) if len(ends) else ends, ends


def byte_offsets(p: np.ndarray) -> np.ndarray:
    """Where each symbol begins in UTF-8, and where the last ends."""
    width = 1 + (p >= 0x80).astype(np.int32) + (p >= 0x800) + (p >= 0x10000)
    return np.concatenate([[0], np.cumsum(width)]).astype(np.int32)


def token_array(texts: list[str], t: Texts, starts: np.ndarray) -> pa.StringArray:
    """The tokens that begin at `starts`: they follow each other, so the texts' bytes are their bytes."""
    data = "".join(texts).encode()
    at = byte_offsets(t.points)
    offsets = np.append(at[starts], at[-1]).astype(np.int32)
    return pa.StringArray.from_buffers(len(starts), pa.py_buffer(offsets.tobytes()), pa.py_buffer(data))


def score(text: str, slices: dict[int, Slice], kind: str = "variance", combine: str = "max") -> np.ndarray:
    """Scores at the gaps of one text, the mean over the ranks of `slices`."""
    return scores(texts_of([text]), slices, kind, combine)[:-1] if len(text) > 1 else np.zeros(0)


def count_windows(lines: list[str], most: int) -> tuple[list[str], np.ndarray]:
    """The distinct windows of `most` symbols that begin at each place of the lines, fewer at a line's end, and how often each occurs.

    Symbols are numbered, 0 standing for what lies beyond a line, so a window is a number of a few bits a symbol; windows of more than 64 bits are renumbered symbol by symbol."""
    flat = np.concatenate([points(x + "\0" * most) for x in lines]) if lines else np.zeros(0, np.uint32)
    size = np.array([len(x) for x in lines], np.int64)
    if not size.sum():
        return [], np.zeros(0, np.int64)
    real = np.ones(len(flat), bool)
    ends = np.cumsum(size + most)
    real[(ends[:, None] - 1 - np.arange(most)).ravel()] = False
    alphabet, code = np.unique(flat[real], return_inverse=True)
    codes = np.zeros(len(flat), np.uint64)
    codes[real] = code + 1
    at = np.flatnonzero(real)
    base_ = np.uint64(len(alphabet) + 1)
    bits = int(base_ - np.uint64(1)).bit_length()
    key = codes[at]
    for j in range(1, most):
        if (j + 1) * bits > 64:
            key = np.unique(key, return_inverse=True)[1].astype(np.uint64)
        key = key * base_ + codes[at + j]
    _, first, count = np.unique(key, return_index=True, return_counts=True)
    rows = codes[at[first][:, None] + np.arange(most)]
    symbols = np.append("", [chr(x) for x in alphabet.tolist()])
    return ["".join(r) for r in symbols[rows].tolist()], count.astype(np.int64)


class WindowCounts:
    """Counts of windows over many batches of lines, by language: numbered symbols packed into 64 bits, 0 standing for what lies beyond a line, as sorted arrays into which each batch is merged."""

    def __init__(self, most: int):
        self.most, self.bits = most, min(21, 64 // most)
        self.code = np.zeros(0x110000, np.uint32)
        self.symbols = [""]
        self.held: dict[str, tuple[np.ndarray, np.ndarray]] = {}

    def __len__(self) -> int:
        return sum(len(k) for k, _ in self.held.values())

    def add(self, lang: str, lines: list[str]) -> bool:
        """Counts the windows of the lines, unless they have more symbols than can be numbered."""
        lines = [x for x in lines if x]
        if not lines:
            return True
        size, gap = np.fromiter(map(len, lines), np.int64, len(lines)), "\0" * self.most
        flat = points(gap.join(lines) + gap)
        real = np.ones(len(flat), bool)
        ends = np.cumsum(size + self.most)
        real[(ends[:, None] - 1 - np.arange(self.most)).ravel()] = False
        new = np.unique(flat[(self.code[flat] == 0) & real])
        if len(self.symbols) + len(new) > 1 << self.bits:
            return False
        self.code[new] = np.arange(len(self.symbols), len(self.symbols) + len(new))
        self.symbols += map(chr, new.tolist())
        codes = np.where(real, self.code[flat], 0).astype(np.uint64)
        codes = np.append(codes, np.zeros(self.most, np.uint64))
        key = np.zeros(len(flat), np.uint64)
        for j in range(self.most):
            key = (key << np.uint64(self.bits)) | codes[j : j + len(flat)]
        key = np.sort(key[real])
        first = np.flatnonzero(np.append(True, key[1:] != key[:-1]))
        keys, counts = key[first], np.diff(np.append(first, len(key)))
        if lang in self.held:
            old, of = self.held[lang]
            at = np.searchsorted(old, keys)
            known = old[np.minimum(at, len(old) - 1)] == keys
            of[at[known]] += counts[known]
            keys, counts = np.insert(old, at[~known], keys[~known]), np.insert(of, at[~known], counts[~known])
        self.held[lang] = keys, counts
        return True

    def grams(self, rows: int = 200_000, least: int = 1):
        """Language, length, grams and their counts of every length from `least` up to that of the windows, some rows at a time; afterwards nothing is held."""
        texts = [x.encode() for x in self.symbols]
        width = np.array([len(x) for x in texts])
        table = np.zeros((len(texts), 4), np.uint8)
        for k, x in enumerate(texts):
            table[k, : len(x)] = list(x)
        mask, held = np.uint64((1 << self.bits) - 1), self.held
        self.held = {}
        for lang, (keys, counts) in held.items():
            for n in range(self.most, least - 1, -1):
                key = keys >> np.uint64(self.bits * (self.most - n))
                first = np.flatnonzero(np.append(True, key[1:] != key[:-1]))
                total, key = np.add.reduceat(counts, first), key[first]
                whole = (key & mask) != 0
                total, key = total[whole], key[whole]
                for i in range(0, len(key), rows):
                    code = ((key[i : i + rows, None] >> (np.uint64(self.bits) * np.arange(n - 1, -1, -1).astype(np.uint64))) & mask).astype(np.int64)
                    w = width[code]
                    data = table[code][np.arange(4) < w[..., None]]
                    offsets = np.concatenate([[0], np.cumsum(w.sum(1))]).astype(np.int32)
                    yield lang, n, pa.StringArray.from_buffers(len(code), pa.py_buffer(offsets.tobytes()), pa.py_buffer(data.tobytes())), total[i : i + rows]


def cut(text: str, breaks: np.ndarray) -> list[str]:
    """The tokens between breaks, given as 1-based gaps."""
    ends = [0, *(int(x) for x in breaks), len(text)]
    return [text[a:b] for a, b in zip(ends[:-1], ends[1:], strict=True)] if text else []


def tokens(text: str, slices: dict[int, Slice], kind: str = "variance", threshold: float = 0.4, combine: str = "max") -> list[str]:
    return cut(text, np.flatnonzero(score(text, slices, kind, combine) > threshold) + 1)


MULTIPLIER = 0x9E3779B97F4A7C15
INVERSE = pow(MULTIPLIER, -1, 1 << 64)


def scrambled(x: np.ndarray) -> np.ndarray:
    """A bijective scramble of 64-bit integers."""
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


class SpanHash:
    """64-bit hashes of spans of flat symbols: equal for equal strings, wherever they stand; made from sums over prefixes."""

    def __init__(self, p: np.ndarray):
        size = len(p)
        powers = np.ones(size + 1, np.uint64)
        powers[1:] = MULTIPLIER
        self.back = np.ones(size + 1, np.uint64)
        self.back[1:] = INVERSE
        np.multiply.accumulate(powers, out=powers)
        np.multiply.accumulate(self.back, out=self.back)
        self.sums = np.zeros(size + 1, np.uint64)
        np.cumsum(scrambled(p.astype(np.uint64) + np.uint64(1)) * powers[:-1], out=self.sums[1:])

    def each(self, n: int) -> np.ndarray:
        """Those of the spans of n symbols at every place."""
        return scrambled((self.sums[n:] - self.sums[:-n]) * self.back[: len(self.sums) - n] ^ scrambled(np.array([n], np.uint64)))

    def of(self, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        return scrambled((self.sums[ends] - self.sums[starts]) * self.back[starts] ^ scrambled((ends - starts).astype(np.uint64)))


def string_hashes(strings: list[str]) -> np.ndarray:
    """The same hashes of whole strings of a symbol or more."""
    t = texts_of(strings)
    return SpanHash(t.points).of(t.first, t.first + t.size)


class Lookup:
    """Where 64-bit keys stand among distinct ones: buckets of about half a key, or a key if they are very many, a few steps in each."""

    MANY = 1 << 20

    def __init__(self, keys: np.ndarray):
        bits = max(1, (len(keys) << (len(keys) < self.MANY)).bit_length())
        self.shift = np.uint64(64 - bits)
        home = self.home(keys)
        order = np.argsort(home, kind="stable")
        self.keys, self.order = np.append(keys[order], np.uint64(0)), np.append(order, -1).astype(np.int32)
        size = np.bincount(home, minlength=1 << bits).astype(np.int32)
        self.start, self.most = np.append(np.int32(0), np.cumsum(size, dtype=np.int32)), int(size.max())

    def home(self, keys: np.ndarray) -> np.ndarray:
        return ((keys * np.uint64(MULTIPLIER)) >> self.shift).astype(np.int64)

    def of(self, keys: np.ndarray) -> np.ndarray:
        """The place of each key, -1 if it is none of them."""
        at = self.start[self.home(keys)]
        hit = self.keys[at] == keys
        out = np.where(hit, self.order[at], -1)
        rest = np.flatnonzero(~hit)
        for k in range(1, self.most):
            near = np.minimum(at[rest] + k, len(self.keys) - 1)
            hit = self.keys[near] == keys[rest]
            out[rest[hit]] = self.order[near[hit]]
            rest = rest[~hit]
        return out


class References:
    """Distinct reference tokens, found in texts by length; of those longer than LONG places are tried where their first symbols stand."""

    LONG = 64
    UPPER = np.uint64(44)

    def __init__(self, tokens: list[str], many: int | None = None):
        """many: so many of the first tokens are counted; of the others it is only kept whether they are found."""
        self.size, self.many = len(tokens), len(tokens) if many is None else many
        by: dict[int, list[int]] = {}
        for k, x in enumerate(tokens):
            by.setdefault(len(x), []).append(k)
        hashes = {n: string_hashes([tokens[k] for k in own]) for n, own in sorted(by.items()) if n}
        self.by = {n: (Lookup(h), np.array(by[n])) for n, h in hashes.items()}
        #: Whether any token of a length has these upper bits, for those that are looked for everywhere.
        self.bits = {n: np.bincount((h >> self.UPPER).astype(np.int64), minlength=1 << 20) > 0 for n, h in hashes.items() if n <= self.LONG}
        heads = {tokens[k][: self.LONG] for n, own in by.items() if n > self.LONG for k in own}
        self.heads = Lookup(np.unique(string_hashes(list(heads)))) if heads else None

    def found(self, t: Texts):
        """Length, beginnings and numbers of the tokens that stand anywhere in the texts, for each length."""
        spans_, left = SpanHash(t.points), t.left
        heads = None
        for n, (own, numbers) in self.by.items():
            if n > len(left):
                break
            if n <= self.LONG:
                h = spans_.each(n)
                at = np.flatnonzero(self.bits[n].take((h >> self.UPPER).astype(np.int64), mode="wrap") & (left[: len(h)] >= n))
                k = own.of(h[at])
            else:
                if heads is None:
                    at = np.flatnonzero(left > self.LONG)
                    heads = at[self.heads.of(spans_.of(at, at + self.LONG)) >= 0]
                at = heads[left[heads] >= n]
                k = own.of(spans_.of(at, at + n))
            hit = k >= 0
            if hit.any():
                yield n, at[hit], numbers[k[hit]]


class Bags:
    """Tokens of texts and the reference tokens among them, for all thresholds of a score at once.

    Where reference tokens stand is found once. What is given then is for each gap how many thresholds its score exceeds: a
    span is a token for thresholds from the largest of these numbers inside it up to the smaller one of its ends. Tokens are
    as many as breaks, less those of blanks alone."""

    def __init__(self, t: Texts, references: References):
        self.last = t.first + t.size - 1
        blank = np.flatnonzero(t.points == 32)
        new = np.diff(blank, prepend=-2) > 1
        #: The gaps before, in and after each run of blanks, run by run.
        self.gaps = np.insert(blank, np.flatnonzero(new), blank[new] - 1)
        self.runs = np.flatnonzero(new) + np.arange(new.sum())
        self.classes: list[tuple] = []
        by: dict[int, list] = {}
        for n, at, number in references.found(t):
            by.setdefault((n - 1).bit_length() - 1 if n > 1 else -1, []).append((n, at, number))
        for k, some in sorted(by.items()):
            at, number = (np.concatenate([x[j] for x in some]) for j in (1, 2))
            n = np.repeat([x[0] for x in some], [len(x[1]) for x in some])
            single = number >= references.many
            order = np.argsort(single, kind="stable")
            at, number, n = at[order], number[order], n[order]
            number[len(single) - single.sum() :] -= references.many
            self.classes.append((k, len(single) - int(single.sum()), at, at + n - 1 - (1 << k) if k >= 0 else None, at - 1, at + n - 1, number))

    def add(self, exceeded: np.ndarray, most: int, counts: np.ndarray, flags: np.ndarray | None = None) -> np.ndarray:
        """The number of tokens that aren't blank for each of `most` thresholds. To counts, reference tokens by most + 1 in a row, the tokens found are added where their thresholds begin, and taken off where they end. In flags, a number for each of those that aren't counted, a bit is set for each threshold (up to 32) at which they are found."""
        q = exceeded
        q[self.last] = most
        at_most = np.bincount(q, minlength=most + 1)
        if len(self.runs):
            around = q.take(self.gaps, mode="wrap")
            at_most = at_most - np.bincount(around, minlength=most + 1) + np.bincount(np.maximum.reduceat(around, self.runs), minlength=most + 1)
        inside, width, one = q, 0, counts.dtype.type(1)
        at = lambda v, i: v.take(i, mode="wrap")
        for k, several, a, b, before, after, number in self.classes:
            while width < k:
                inside = np.maximum(inside, np.append(inside[1 << width :], np.zeros(1 << width, q.dtype))[: len(q)])
                width += 1
            high = np.minimum(at(q, before), at(q, after))
            low = np.maximum(at(inside, a), at(inside, b)) if k >= 0 else np.zeros(len(a), q.dtype)
            is_token = np.flatnonzero(low < high)
            if several < len(number):
                single = is_token[np.searchsorted(is_token, several) :]
                is_token = is_token[: len(is_token) - len(single)]
                bits = (np.uint64(1) << at(high, single).astype(np.uint64)) - (np.uint64(1) << at(low, single).astype(np.uint64))
                np.bitwise_or.at(flags, at(number, single), bits.astype(np.uint32))
            row = at(number, is_token) * (most + 1)
            np.add.at(counts, row + at(low, is_token), one)
            np.subtract.at(counts, row + at(high, is_token), one)
        return at_most.sum() - np.cumsum(at_most)[:most]


def limits(thresholds: list[float]) -> list[float]:
    """For each threshold the smallest number that is above it when rounded."""
    out = []
    for x in thresholds:
        near = max(2 / 10**DIGITS, abs(x) * 1e-14)
        low, high = x - near, x + near
        while (mid := (low + high) / 2) not in (low, high):
            low, high = (low, mid) if round_half_up(np.float64(mid)) > x else (mid, high)
        out.append(high)
    return out


def exceeded(v: np.ndarray, least: list[float]) -> np.ndarray:
    """How many of the numbers each value reaches; none if there is no value."""
    out = np.zeros(len(v), np.uint8 if len(least) < 256 else np.int64)
    hit = np.empty(len(v), bool)
    for x in least:
        out += np.greater_equal(v, x, out=hit)
    return out


def rank_set_exceeded(forward: dict[int, np.ndarray], backward: dict[int, np.ndarray], sets: list[tuple[int, ...]], thresholds: list[float], combine: str = "max"):
    """For each set of ranks how many thresholds the combined score exceeds, see `combined`: without rounding means, whose comparison with a threshold is one with a limit."""
    above = [np.nextafter(x, np.inf) for x in thresholds]
    if combine != "max":
        for s in sets:
            yield exceeded(combined([forward[n] for n in s], [backward[n] for n in s], combine), above)
        return
    least, single, ways = limits(thresholds), {}, []
    several = {n for s in sets if len(s) > 1 for n in s}
    for way in (forward, backward):
        ways.append(({n: np.nan_to_num(way[n], nan=0.0) for n in several}, {n: ~np.isnan(way[n]) for n in several}))
    for s in sets:
        if len(s) == 1:
            n = s[0]
            if n not in single:
                single[n] = np.maximum(exceeded(forward[n], above), exceeded(backward[n], above))
            yield single[n].copy()
            continue
        out = None
        for values, there in ways:
            with np.errstate(all="ignore"):
                mean = sum(values[n] for n in s) / sum(there[n].astype(np.uint8) for n in s)
            own = exceeded(mean, least)
            out = own if out is None else np.maximum(out, own)
        yield out


def sweep(scores_: np.ndarray) -> list[tuple[int, int, float, float]]:
    """(start, length, low, high) of every span that is a token for some threshold t: for exactly those with low <= t < high.

    A span is a token while no gap inside exceeds t and the gaps at its ends do; the ends of the text always count as
    breaks. Spans nest, so there are fewer than twice as many as symbols."""
    size, inf = len(scores_) + 1, float("inf")
    out, stack = [], []  # stack: (start of span, score of the gap before it, largest score inside so far)
    values = [*scores_.tolist(), inf]
    stack.append([0, inf, -inf])
    for end in range(1, size + 1):
        right = values[end - 1]
        while True:
            start, left, inside = stack[-1]
            high = min(left, right)
            if inside < high:
                out.append((start, end - start, inside, high))
            if left <= right and len(stack) > 1:
                stack.pop()
                stack[-1][2] = max(stack[-1][2], inside, left)
            else:
                stack[-1][2] = max(inside, right)
                break
        if right < inf:
            stack.append([end, right, -inf])
    return out
