"""Arrow batches as blocks of concatenated bytes, and byte-level features that several operators share."""

from __future__ import annotations

import ctypes
import functools
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Bytes of text handled at once; a longer document makes a block of its own.
BLOCK_BYTES = 1 << 18


def lean(run):
    """Wraps a function over Arrow batches: its worker, which Spark keeps, gives freed memory back when the task ends."""

    @functools.wraps(run)
    def wrapped(batches):
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            try:
                ctypes.CDLL("libc.so.6").malloc_trim(0)
            except (OSError, AttributeError):  # another C library
                pass

    return wrapped


def byte_texts(column) -> list[bytes]:
    """UTF-8 bytes of a string column; null counts as empty."""
    return [b"" if x is None else x for x in column.cast(pa.large_binary()).to_pylist()]


def cut_blocks(texts: list[bytes], most: int = BLOCK_BYTES):
    """Yields (first, last) of runs of documents with at most `most` bytes, one document at least."""
    first = size = 0
    for i, t in enumerate(texts):
        if i > first and size + len(t) > most:
            yield first, i
            first, size = i, 0
        size += len(t) + 1
    if first < len(texts):
        yield first, len(texts)


def text_blocks(column, most: int = BLOCK_BYTES):
    """Yields (first, last, texts) of runs of rows of a string column, so that few texts are held as objects at once."""
    raw = column.cast(pa.large_binary())
    sizes = pc.fill_null(pc.binary_length(raw), 0).to_numpy(zero_copy_only=False)
    first = size = 0
    for i, n in enumerate(sizes.tolist()):
        if i > first and size + n > most:
            yield first, i, byte_texts(raw.slice(first, i - first))
            first, size = i, 0
        size += n + 1
    if first < len(sizes):
        yield first, len(sizes), byte_texts(raw.slice(first))


def joined(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """One byte array with a newline before, between and after the texts; starts and ends of each text."""
    sizes = np.fromiter(map(len, texts), np.int64, len(texts))
    ends = np.cumsum(sizes + 1)
    return np.frombuffer(b"\n" + b"\n".join(texts) + b"\n", np.uint8), ends - sizes, ends


def lowered_latin(data: np.ndarray) -> np.ndarray:
    """A-Z and the two-byte capitals of Latin-1 in lower case."""
    out = data + ((data >= 65) & (data <= 90)).astype(np.uint8) * np.uint8(32)
    accents = (data[:-1] == 0xC3) & (data[1:] >= 0x80) & (data[1:] <= 0x9E) & (data[1:] != 0x97)
    out[1:][accents] += np.uint8(32)
    return out


def word_bounds(inside: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the runs of True; the first and last element are False."""
    edge = np.flatnonzero(inside[1:] != inside[:-1]) + 1
    return edge[0::2], edge[1::2]


def letter_table() -> np.ndarray:
    """Bytes that belong to a word for classifiers: digits, letters, @ and $ (used to disguise letters), non-ASCII."""
    table = np.zeros(256, bool)
    table[128:] = True
    for c in b"abcdefghijklmnopqrstuvwxyz0123456789@$":
        table[c] = True
    return table


def space_table() -> np.ndarray:
    table = np.zeros(256, bool)
    table[[0x20, *range(0x09, 0x0E)]] = True
    return table


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hash of each byte range: a polynomial over the ring of 64-bit integers, then mixed."""
    base = np.uint64(0x9E3779B97F4A7C15)
    inverse = pow(int(base), -1, 1 << 64)
    n = len(data)
    powers, back = powers_of(int(base), n + 1), powers_of(inverse, n + 1)
    total = np.zeros(n + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * back[:n], out=total[1:])
    return mixed((total[ends] - total[starts]) * powers[starts] + (ends - starts).astype(np.uint64))


def powers_of(base: int, n: int) -> np.ndarray:
    out = np.full(max(n, 1), base, np.uint64)
    out[0] = 1
    return np.cumprod(out, out=out)


def mixed(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> np.uint64(32))
    h = h * np.uint64(0xD6E8FEB86659FD93)
    h = h ^ (h >> np.uint64(32))
    h = h * np.uint64(0xD6E8FEB86659FD93)
    return h ^ (h >> np.uint64(32))


def gram_buckets(shown: np.ndarray, n: int, bits: int) -> np.ndarray:
    """Bucket of the n bytes from each position (uint32 arithmetic); positions near the end wrap to zero bytes."""
    size = len(shown) - n + 1
    if size <= 0:
        return np.zeros(0, np.uint32)
    h = np.full(size, n * 0x9E3779B1 & 0xFFFFFFFF, np.uint32)
    for k in range(n):
        h *= np.uint32(0x01000193)
        h ^= shown[k : k + size]
    h ^= h >> np.uint32(15)
    h *= np.uint32(0x85EBCA6B)
    return h >> np.uint32(32 - bits)


def unused_name(df, name: str) -> str:
    """`name`, or a longer one where df has such a column; Spark's names ignore case."""
    taken = {c.lower() for c in df.columns}
    name = f"_{name}"
    while name in taken:
        name += "_"
    return name


def split_of(doc_ids, parts: int) -> np.ndarray:
    """crc32 of the id as text, modulo parts; null ids count as the text 'null'."""
    return np.fromiter((zlib.crc32(str("null" if d is None else d).encode()) % parts for d in doc_ids), np.int64, len(doc_ids))
