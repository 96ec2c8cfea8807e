"""What the text operators share: Arrow batches cut to a bounded size, and their words as codes into the distinct words.

Most work on a text is done once for each distinct word of a batch, then spread over the batch by code.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator
from functools import wraps
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column
from pyspark.sql import functions as F

#: Bytes of text that a kernel handles at once; a longer text is a batch of its own.
BATCH_BYTES = 4 << 20


def release() -> None:
    """Gives the memory that this process no longer uses back to the system: idle workers wait beside the next stage's."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc has it
    if trim is not None:
        trim(0)


def released(run):
    """A task's function over batches that releases memory when it is done."""

    @wraps(run)
    def outer(batches):
        try:
            yield from run(batches)
        finally:
            release()

    return outer


def cut_batches(batches: Iterator[pa.RecordBatch], text: str, most: int = BATCH_BYTES) -> Iterator[pa.RecordBatch]:
    """The same rows in batches whose texts hold about `most` bytes at most, or one row."""
    for batch in batches:
        if not batch.num_rows:
            continue
        ends = np.cumsum(pc.binary_length(batch.column(text)).fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64))
        at = 0
        while at < batch.num_rows:
            before = ends[at - 1] if at else 0
            to = max(at + 1, int(np.searchsorted(ends, before + most, side="right")))
            yield batch.slice(at, to - at)
            at = to


class Words(NamedTuple):
    """Words of some texts: those of text i are distinct[codes[offsets[i]:offsets[i + 1]]]. distinct may hold an unused empty string."""

    offsets: np.ndarray
    codes: np.ndarray
    distinct: pa.Array


def words_of(texts: pa.Array, lower: str = "ascii") -> Words:
    """Words are runs of other characters than space, tab, line feed, vertical tab, form feed and carriage return. lower: "ascii" lower-cases A-Z, "utf8" all letters, "" none. A null text has no words."""
    texts = texts.fill_null("")
    if lower:
        texts = pc.ascii_lower(texts) if lower == "ascii" else pc.utf8_lower(texts)
    lists = pc.ascii_split_whitespace(texts)
    flat = lists.flatten().dictionary_encode()
    offsets = lists.offsets.to_numpy().astype(np.int64)
    codes = flat.indices.to_numpy(zero_copy_only=False)
    empty = pc.index(flat.dictionary, "").as_py()
    if empty >= 0:
        keep = codes != empty
        offsets = np.concatenate([[0], np.cumsum(keep)])[offsets]
        codes = codes[keep]
    return Words(offsets, codes, flat.dictionary)


def hash_strings(strings: pa.Array, seed: int = 0) -> np.ndarray:
    """64-bit hashes of the UTF-8 bytes."""
    one = xxhash.xxh3_64_intdigest
    return np.fromiter((one(x, seed) for x in strings.cast(pa.binary()).to_pylist()), np.uint64, len(strings))


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scramble of 64-bit integers."""
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def segment_sum(values: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Sums of values[offsets[i]:offsets[i + 1]], 0 where that is empty; each is summed on its own, so it doesn't depend on the others."""
    out = np.zeros((len(offsets) - 1, *values.shape[1:]), values.dtype if values.dtype.kind == "f" else np.int64)
    full = np.flatnonzero(offsets[1:] > offsets[:-1])
    if len(full):
        out[full] = np.add.reduceat(values, offsets[full], axis=0, dtype=out.dtype)
    return out


def ranges(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """starts[0], starts[0] + 1, ... for lengths[0] numbers, then those of starts[1] and so on."""
    ends = np.cumsum(lengths)
    return np.arange(ends[-1] if len(ends) else 0) + np.repeat(starts - (ends - lengths), lengths)


def remainder(id_col: str, of: int) -> Column:
    """crc32 of the id as text, modulo `of`; a null id counts as an empty text, whose remainder is 0."""
    return F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")) % F.lit(of)
