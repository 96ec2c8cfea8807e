"""The operators as plain loops over strings, to hold results against. Hashes stand only where they set an order."""

from __future__ import annotations

import itertools
import math
import re
from collections import Counter, defaultdict

import pyarrow as pa
import xxhash

from freeseg.llm import decontam, kernel
from freeseg.llm.toxicity import MARKS

SPACE = "[\x20\x09-\x0d]+"


def words(t):
    return [w for w in re.split(SPACE, t or "") if w]


def sixteen(masked):
    """The bytes by which the forms of a leaf are put in order."""
    h = kernel.hash_strings(pa.array([w or "0" for w in masked], pa.string()))
    out = [0 if w is None else max(1, (int(x) | 1) >> 20 & 0xFFFF) for w, x in zip(masked, h, strict=True)]
    return b"".join(x.to_bytes(2, "little") for x in out)


def line_templates(docs, depth=3, similar=0.8, long=8, short=3, short_docs=10):
    """docs: (id, text). Form -> (first place of its template, whether that recurs)."""
    places = defaultdict(list)
    for i, t in docs:
        key = (i if i is not None else -(1 << 63), xxhash.xxh3_64_intdigest((t or "").encode()) - (1 << 63))
        for k, line in enumerate((t or "").split("\n")):
            masked = tuple(None if re.search(r"\d", w) else w for w in words(line))
            if len(masked) >= short:
                places[masked].append((*key, k))
    leaves = defaultdict(list)
    for form in places:
        leaves[len(form), form[:depth]].append(form)
    out = {}
    for (n, _), forms in leaves.items():
        templates = []  # (words, which are fixed, forms)
        for form in sorted(forms, key=sixteen):
            same = [sum(f and a == b for a, b, f in zip(t, form, fixed, strict=True)) for t, fixed, _ in templates]
            best = max(range(len(same)), key=lambda k: same[k]) if same else None
            if best is not None and same[best] >= similar * n:
                t, fixed, members = templates[best]
                fixed[:] = [f and a == b for a, b, f in zip(t, form, fixed, strict=True)]
                members.append(form)
            else:
                templates.append((form, [w is not None for w in form], [form]))
        for _, _, members in templates:
            every = [p for f in members for p in places[f]]
            recurs = len({p[:2] for p in every}) >= (2 if n >= long else short_docs)
            for f in members:
                out[f] = (min(every), recurs)
    return out


def dropped_lines(docs):
    """docs: (id, text). The numbers of the lines that go, for each row."""
    found, out = line_templates(docs), []
    for i, t in docs:
        key = (i if i is not None else -(1 << 63), xxhash.xxh3_64_intdigest((t or "").encode()) - (1 << 63))
        gone = []
        for k, line in enumerate((t or "").split("\n")):
            masked = tuple(None if re.search(r"\d", w) else w for w in words(line))
            if masked in found and found[masked][1] and found[masked][0] != (*key, k):
                gone.append(k)
        out.append(gone)
    return out


def without_lines(docs):
    """docs: id -> text. The texts without the lines that go, but for those of which no word is left."""
    rows = sorted(docs.items())
    out = {}
    for (i, t), gone in zip(rows, dropped_lines(rows), strict=True):
        left = t if not gone else "\n".join(x for k, x in enumerate((t or "").split("\n")) if k not in gone)
        if not gone or words(left):
            out[i] = left
    return out


def shingles(t, width):
    w = words(re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    return {tuple(w[k : k + width]) for k in range(len(w) - width + 1)} if len(w) >= width else {tuple(w)} if w else set()


def representatives(docs, width=5, num=4, den=5):
    """docs: id -> text. The smallest id that each can reach by links."""
    sets, root = {i: shingles(t, width) for i, t in docs.items()}, {i: i for i in docs}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in itertools.combinations(sorted(sets), 2):
        x, y = sets[a], sets[b]
        if x and y and den * len(x & y) >= num * len(x | y):
            u, v = find(a), find(b)
            root[max(u, v)] = min(u, v)
    return {i: find(i) for i in docs}


def canonical(t):
    """(kind, canonical word, word as it stood, whether a capital that begins a sentence) of each word that is more than marks."""
    out, starts = [], True
    for word in words(t):
        bare = word.strip(MARKS)
        low = bare.lower()
        kind, capital = "word", False
        if bare:
            if bare[0].isdigit() or word[0] in "$€£+-":
                if decontam.NUMBER.fullmatch(low):
                    kind = "num"
            elif low in decontam.UNITS and bare == low:
                kind = "unit"
            capital = bare[0].isupper() and bare[1:] != bare[1:].upper()
        begins = kind == "word" and capital and starts
        if kind == "word" and capital and not starts:
            kind = "name"
        if bare:
            out.append((kind, low if kind == "word" else kind, low, begins))
        starts = word[-1:] in ".!?:" or (word[-1:] in "\"')”»" and word[-2:-1] in ".!?:")
    return out


def windows(c, width):
    """(place, key, whether names at sentence starts are read as names)."""
    out = []
    for k in range(len(c) - width + 1):
        w = c[k : k + width]
        if all(x[0] != "word" for x in w):
            out.append((k, ("as it stands", *(x[2] for x in w)), False))
            continue
        out.append((k, tuple((x[0], x[1]) for x in w), False))
        if any(x[3] for x in w) and any(x[0] == "word" and not x[3] for x in w):
            out.append((k, tuple(("name", "name") if x[3] else (x[0], x[1]) for x in w), True))
    return out


def holds(text, item, width=8, cover=0.5, least=4, enough=16):
    """(share, whether slots differ) if the text holds the item, else None."""
    d, c = canonical(text), canonical(item)
    if not c:
        return None
    if len(c) < least:
        return (1.0, False) if [x[2] for x in c] == [x[2] for x in d] else None
    n = min(width, len(c))
    total = max(1, len(c) - width + 1)
    there = defaultdict(list)
    for p, key, named in windows(c, n):
        there[key].append((p, named))
    hits = [(p, q, named or mine) for q, key, mine in windows(d, n) for p, named in there.get(key, ())]
    if len({p for p, _, _ in hits}) < min(cover * total, enough):
        return None
    runs, places, differs, row = defaultdict(list), set(), False, 0
    for p, q, named in hits:
        runs[q - p].append((p, q, named))
    for run in runs.values():
        for some in (run, [x for x in run if not x[2]]):
            pairs = [(c[p + j], d[q + j]) for p, q, _ in some for j in range(n)]
            slots = {(a[2], b[2]) for a, b in pairs if a[0] == "name" or (a[0] == "word" and a[2] != b[2])}
            if len({a for a, _ in slots}) == len(slots) == len({b for _, b in slots}):
                mine = sorted({p for p, _, _ in some})
                places |= set(mine)
                differs |= any(a[2] != b[2] for a, b in pairs)
                for _, g in itertools.groupby(enumerate(mine), key=lambda x: x[1] - x[0]):
                    row = max(row, len(list(g)))
                break
    share = len(places) / total
    return (share, differs) if places and (share >= cover or row >= enough) else None


def contaminated(docs, items):
    """docs, items: id -> text. The items that each text holds: id -> (ids, share, whether slots differ)."""
    out = {}
    for i, t in docs.items():
        found = {k: holds(t, x) for k, x in items.items()}
        found = {k: v for k, v in found.items() if v}
        out[i] = (sorted(found), max((v[0] for v in found.values()), default=0.0), any(v[1] for v in found.values()))
    return out


def grams(t, orders=(1, 2, 3, 4)):
    """The n-grams of characters of each word between blanks: single characters of the word, longer ones with its blanks."""
    out = []
    for w in words((t or "").lower()):
        x = f" {w} "
        for n in orders:
            for k in range(len(x) - n + 1):
                g = x[k : k + n]
                if n > 1 or g != " ":
                    out.append(g)
    return out


def languages(docs):
    """docs: id -> (text, lang). The likeliest language of each text by naive Bayes over its n-grams, None without a letter."""
    counts, texts = defaultdict(Counter), Counter()
    for t, lang in docs.values():
        if t is not None and lang is not None:
            counts[lang].update(grams(t))
            texts[lang] += 1
    size = 1 << 16
    total, names = {g: c.total() for g, c in counts.items()}, sorted(counts)
    out = {}
    for i, (t, _) in docs.items():
        if not any(ch.isalpha() for ch in t or ""):
            out[i] = None
            continue
        own = grams(t)
        z = {g: math.log(texts[g] / texts.total()) + sum(math.log((counts[g][x] + 0.5) / (total[g] + 0.5 * size)) for x in own) for g in names}
        out[i] = max(names, key=z.get)
    return out


__all__ = ["contaminated", "dropped_lines", "holds", "languages", "representatives", "without_lines"]
